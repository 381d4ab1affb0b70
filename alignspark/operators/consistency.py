"""Model consistency: predictions of the composed series, normalised error, the gate.

Models: last value (``locf``) and AR(1) as windows and aggregates; VAR(1) from
cross moments; the state-space model with gaps (``marss``) in numpy per group, or
over blocks of a long series (``marss_scan``).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from alignspark.operators.compose import materialise
from alignspark.operators.marss import estimates, groups_together
from alignspark.operators.marss_scan import predict_scan

PRED = "grp string, pos long, sid int, pred double"


def predict_locf(cells: DataFrame) -> DataFrame:
    """Last value seen before, per series of the composed result."""
    order = Window.partitionBy("grp", "sid").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return cells.withColumn("pred", F.last("val", ignorenulls=True).over(order))


def predict_ar1(cells: DataFrame) -> DataFrame:
    """Regression on the value one tuple before, fitted on the same series; falls back to no prediction."""
    lagged = cells.withColumn("lag", F.lag("val").over(Window.partitionBy("grp", "sid").orderBy("pos")))
    fit = lagged.groupBy("grp", "sid").agg(F.regr_slope("val", "lag").alias("a"), F.regr_intercept("val", "lag").alias("b"))
    return lagged.join(fit, ["grp", "sid"]).withColumn("pred", F.col("a") * F.col("lag") + F.col("b")).drop("lag", "a", "b")


def predict_var1(cells: DataFrame, m: int) -> DataFrame:
    """VAR(1) by normal equations over tuples whose cells and predecessors are complete; one task a group for the solve."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        wide = pdf.pivot(index="pos", columns="sid", values="val").reindex(columns=range(1, m + 1)).sort_index()
        y = wide.to_numpy(dtype=float)
        before = np.vstack([np.full((1, m), np.nan), y[:-1]])
        ok = ~(np.isnan(y).any(axis=1) | np.isnan(before).any(axis=1))
        pred = np.full_like(y, np.nan)
        if ok.sum() > m + 1:
            design = np.c_[np.ones(ok.sum()), before[ok]]
            coef = np.linalg.lstsq(design, y[ok], rcond=None)[0]
            can = ~np.isnan(before).any(axis=1)
            pred[can] = np.c_[np.ones(can.sum()), before[can]] @ coef
        out = pd.DataFrame(pred, index=wide.index, columns=wide.columns).stack(future_stack=True).rename("pred").reset_index()
        got = pdf.merge(out, on=["pos", "sid"], how="left")
        return got[["grp", "pos", "sid", "idx", "ts_us", "val", "pred"]]

    return cells.groupBy("grp").applyInPandas(run, "grp string, pos long, sid int, idx long, ts_us long, val double, pred double")


def predict_marss(cells: DataFrame, m: int, iters: int = 15, smoothed: bool = False) -> DataFrame:
    def run(groups: list[pd.DataFrame]):
        for pdf, pred in zip(groups, estimates(groups, "pos", m, iters, "smoothed" if smoothed else "one_step")):
            yield pdf.assign(pred=pred)

    return groups_together(cells.select("grp", "pos", "sid", "idx", "ts_us", "val"), run, "grp string, pos long, sid int, idx long, ts_us long, val double, pred double")


def predicted(aligned: DataFrame, series: DataFrame, m: int, model: str = "locf") -> DataFrame:
    cells = materialise(aligned, series)
    if model == "locf":
        return predict_locf(cells)
    if model == "ar1":
        return predict_ar1(cells)
    if model == "var1":
        return predict_var1(cells, m)
    if model in ("marss", "marss_smoothed"):
        return predict_marss(cells, m, smoothed=model.endswith("smoothed"))
    if model == "marss_scan":
        return predict_scan(cells)
    raise ValueError(f"unknown model {model!r}")


def cell_loss(pred: DataFrame) -> DataFrame:
    """Absolute error of every present value; missing values and missing predictions count 0."""
    return pred.withColumn("loss", F.coalesce(F.abs(F.col("pred") - F.col("val")), F.lit(0.0)))


def scale_mu(series: DataFrame) -> DataFrame:
    """(grp, sid, mu): present values times their range; null where that is 0 (the series leaves the mean)."""
    out = series.groupBy("grp", "sid").agg((F.count("val") * (F.max("val") - F.min("val"))).alias("mu"))
    return out.withColumn("mu", F.when(F.col("mu") > 0, F.col("mu")))


def series_nmae(pred: DataFrame, mu: DataFrame) -> DataFrame:
    return cell_loss(pred).groupBy("grp", "sid").agg(F.sum("loss").alias("loss")).join(mu, ["grp", "sid"]).select("grp", "sid", (F.col("loss") / F.col("mu")).alias("nmae"))


def delta(aligned: DataFrame, series: DataFrame, m: int, model: str = "locf", norm: str = "source") -> DataFrame:
    """(grp, delta): mean normalised error over the series."""
    pred = predicted(aligned, series, m, model)
    mu = scale_mu(series if norm == "source" else pred)
    return series_nmae(pred, mu).groupBy("grp").agg(F.avg("nmae").alias("delta"))


def subset_deltas(ranked: DataFrame, cand: DataFrame, series: DataFrame, m: int, model: str = "locf") -> DataFrame:
    """Adds ``delta`` to (grp, mask, w_fp) alternatives: every subset is composed and predicted as a group of its own."""
    numbered = cand.select("grp", "x", "lam", "w", F.col("w_fp").alias("own")).withColumn("k", F.row_number().over(Window.partitionBy("grp").orderBy("x")) - 1)
    named = ranked.withColumn("alt", F.concat_ws("@", "mask", "grp"))
    member = named.join(numbered, "grp").where("shiftright(mask, k) & 1 = 1")
    place = F.row_number().over(Window.partitionBy("alt").orderBy("k"))
    alternatives = member.select(F.col("alt").alias("grp"), place.cast("long").alias("pos"), "x", "lam", "w", F.col("own").alias("w_fp"))
    sources = named.select("grp", "alt").join(series.select("grp", "sid", "idx", "ts_us", "val"), "grp").drop("grp").withColumnRenamed("alt", "grp")
    errors = delta(alternatives, sources, m, model).withColumnRenamed("grp", "alt")
    return named.join(errors, "alt").select("grp", "mask", "w_fp", "delta")


def satisfies_model(delta_df: DataFrame, limit: float) -> DataFrame:
    return delta_df.where(F.col("delta") <= limit)


def pick_feasible(alternatives: DataFrame, limit: float) -> DataFrame:
    """(grp, alt): the heaviest alternative within the limit; rows are (grp, alt, w_fp, delta)."""
    return alternatives.where(F.col("delta") <= limit).groupBy("grp").agg(F.max_by("alt", F.struct("w_fp", "alt")).alias("alt"), F.max("w_fp").alias("w_fp"))
