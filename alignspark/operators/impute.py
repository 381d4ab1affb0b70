"""Imputers that the baselines need; the composers take none.

``imp_lr`` and ``imp_gbt`` (regression and boosted trees on neighbouring values
of the own and the other series) stand in for deep imputers, whose libraries are
not at hand; results carry these names only.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from alignspark.operators.conflicts import settled
from alignspark.operators.marss import estimates, groups_together


def interpolate(series: DataFrame, column: str = "ts_us") -> DataFrame:
    """Linear interpolation over row numbers; ends extend the nearest known value."""
    back = Window.partitionBy("grp", "sid").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    # the next known value is the last one seen from the end: a frame that only grows takes one pass
    ahead = Window.partitionBy("grp", "sid").orderBy(F.desc("idx")).rowsBetween(Window.unboundedPreceding, 0)
    point = F.when(F.col(column).isNotNull(), F.struct(F.col("idx").alias("i"), F.col(column).cast("double").alias("v")))
    with_ends = series.withColumns({"_p": F.last(point, ignorenulls=True).over(back), "_n": F.last(point, ignorenulls=True).over(ahead)})
    share = (F.col("idx") - F.col("_p.i")) / (F.col("_n.i") - F.col("_p.i"))
    value = (F.when(F.col(column).isNotNull(), F.col(column).cast("double"))
             .when(F.col("_p").isNull(), F.col("_n.v")).when(F.col("_n").isNull(), F.col("_p.v"))
             .otherwise(F.col("_p.v") + (F.col("_n.v") - F.col("_p.v")) * share))
    if column == "ts_us":
        value = F.floor(value).cast("long")
    return with_ends.withColumn(column, value).drop("_p", "_n")


def interpolated(v: np.ndarray, known: np.ndarray, group: np.ndarray) -> np.ndarray:
    """``interpolate`` of groups side by side, a place for each row number; where a group has no known value, NaN."""
    at = np.arange(len(v))
    back = np.maximum.accumulate(np.where(known, at, -1))
    ahead = np.minimum.accumulate(np.where(known, at, len(v))[::-1])[::-1]
    has_back = (back >= 0) & (group[np.maximum(back, 0)] == group)
    has_ahead = (ahead < len(v)) & (group[np.minimum(ahead, len(v) - 1)] == group)
    p, n = np.where(has_back, back, ahead), np.where(has_ahead, ahead, back)  # ends extend the nearest known value
    p, n = (np.clip(x, 0, len(v) - 1) for x in (p, n))
    out = np.where(p == n, v[p], v[p] + (v[n] - v[p]) * ((at - p) / np.maximum(n - p, 1)))
    return np.where(has_back | has_ahead, out, np.nan)


def impute_simple(series: DataFrame, how: str = "mean") -> DataFrame:
    """``mean``, ``median``, ``locf`` (ends take the next value) or ``seasonal`` (mean by hour of day; else the mean)."""
    if how == "locf":
        back = Window.partitionBy("grp", "sid").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
        ahead = Window.partitionBy("grp", "sid").orderBy("idx").rowsBetween(0, Window.unboundedFollowing)
        return series.withColumn("val", F.coalesce(F.last("val", ignorenulls=True).over(back), F.first("val", ignorenulls=True).over(ahead)))
    if how in ("mean", "median"):
        # the mean in whole millionths: a sum of integers does not depend on the order of the rows
        micro, n = F.sum(F.round(F.col("val") * 1_000_000).cast("long")), F.count("val")
        mean = F.when(n > 0, F.call_function("div", 2 * micro + n, 2 * F.greatest(n, F.lit(1)))) / F.lit(1_000_000.0)
        fill = series.groupBy("grp", "sid").agg((mean if how == "mean" else F.percentile("val", F.lit(0.5))).alias("_f"))
        return series.join(fill, ["grp", "sid"]).withColumn("val", F.coalesce("val", "_f")).drop("_f")
    if how == "seasonal":
        hour = F.floor(F.col("ts_us") / F.lit(3_600_000_000)) % 24
        marked = series.withColumn("_h", hour)
        by_hour = marked.groupBy("grp", "sid", "_h").agg(F.avg("val").alias("_s"))
        mean = series.groupBy("grp", "sid").agg(F.avg("val").alias("_f"))
        return marked.join(by_hour, ["grp", "sid", "_h"], "left").join(mean, ["grp", "sid"]).withColumn("val", F.coalesce("val", "_s", "_f")).select("grp", "sid", "idx", "ts_us", "val")
    raise ValueError(f"unknown imputer {how!r}")


def _features(series: DataFrame, m: int, lags: int) -> tuple[DataFrame, list[str]]:
    """Rough fill (interpolation) of the neighbours in time and of the other series at the same row."""
    rough = interpolate(series, "val").select("grp", "sid", "idx", F.coalesce("val", F.lit(0.0)).alias("r"))
    own = Window.partitionBy("grp", "sid").orderBy("idx")
    names = []
    base = rough
    for k in range(1, lags + 1):
        base = base.withColumn(f"b{k}", F.coalesce(F.lag("r", k).over(own), "r")).withColumn(f"a{k}", F.coalesce(F.lead("r", k).over(own), "r"))
        names += [f"b{k}", f"a{k}"]
    others = rough.groupBy("grp", "idx").agg(*[F.max(F.when(F.col("sid") == j, F.col("r"))).alias(f"o{j}") for j in range(1, m + 1)])
    base = base.join(others, ["grp", "idx"])
    for j in range(1, m + 1):  # the own value must not explain itself
        base = base.withColumn(f"o{j}", F.when(F.col("sid") == j, (F.col("b1") + F.col("a1")) / 2).otherwise(F.coalesce(f"o{j}", F.lit(0.0))))
        names.append(f"o{j}")
    return series.join(base.drop("r"), ["grp", "sid", "idx"]), names


def impute_model(series: DataFrame, m: int, kind: str = "imp_lr", lags: int = 2) -> DataFrame:
    """One model per series, learned where values are present."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GBTRegressor, LinearRegression

    data, names = _features(series, m, lags)
    data = settled(data, "features")  # every series' learner reads them again and again
    data = VectorAssembler(inputCols=names, outputCol="features").transform(data)
    out = None
    for j in range(1, m + 1):
        own = data.where(F.col("sid") == j)
        known = own.where("val IS NOT NULL").select(F.col("val").alias("label"), "features")
        learner = LinearRegression(regParam=0.01) if kind == "imp_lr" else GBTRegressor(maxIter=10, maxDepth=3, seed=3)
        filled = learner.fit(known).transform(own) if not known.isEmpty() else own.withColumn("prediction", F.lit(0.0))
        part = filled.select("grp", "sid", "idx", "ts_us", F.coalesce("val", "prediction").alias("val"))
        out = part if out is None else out.unionByName(part)
    return out


def impute_marss(series: DataFrame, m: int, iters: int = 10) -> DataFrame:
    def run(groups: list[pd.DataFrame]):
        for pdf, smooth in zip(groups, estimates(groups, "idx", m, iters, "smoothed")):
            val = pdf["val"].to_numpy(dtype=float)
            yield pdf.assign(val=np.where(np.isnan(val), smooth, val))

    return groups_together(series.select("grp", "sid", "idx", "ts_us", "val"), run, "grp string, sid int, idx long, ts_us long, val double")


def complete_for(series: DataFrame, m: int, imputer: str = "imp_lr") -> DataFrame:
    """Series without gaps, as the baselines take them: clocks interpolated, values by the imputer."""
    timed = interpolate(series, "ts_us")
    if imputer in ("imp_lr", "imp_gbt"):
        return impute_model(timed, m, imputer)
    if imputer == "linear":
        return interpolate(timed, "val")
    if imputer == "marss":
        return impute_marss(timed, m)
    return impute_simple(timed, imputer)
