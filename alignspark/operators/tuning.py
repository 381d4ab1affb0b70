"""Parameters without ground truth, and sweeps that share one candidate set."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from alignspark.functions import measures as M
from alignspark.operators import candidates as C
from alignspark.operators import gate
from alignspark.operators.compose import ALIGN, _result, solve
from alignspark.operators.consistency import delta
from alignspark.params import AlignParams


def gaps(series: DataFrame) -> DataFrame:
    """(grp, gap): differences of present timestamps of one row, over pairs of series."""
    rows = series.where("ts_us IS NOT NULL").groupBy("grp", "idx").agg(F.array_sort(F.collect_list("ts_us")).alias("t"))
    pairs = F.flatten(F.transform("t", lambda a, i: F.transform(F.slice("t", i + 2, F.greatest(F.size("t") - i - 1, F.lit(0))), lambda b: b - a)))
    return rows.select("grp", F.explode(pairs).alias("gap"))


def fit_theta(series: DataFrame, q: float = 0.95, exact: bool = True) -> DataFrame:
    """One row (theta): a high percentile of same-row differences. ``exact`` holds all different ones in one task; else a sketch of bounded size."""
    value = F.percentile("gap", F.lit(q)) if exact else F.percentile_approx("gap", F.lit(q), F.lit(10_000)).cast("double")
    return gaps(series).agg(value.alias("theta"))


def row_distances(cand: DataFrame) -> DataFrame:
    pairs = F.flatten(F.transform("x", lambda a, i: F.transform(F.slice("x", i + 2, F.greatest(F.size("x") - i - 1, F.lit(0))), lambda b: F.abs(b - a))))
    return cand.select(F.explode(pairs).alias("dist"))


def fit_beta(series: DataFrame, m: int, p: AlignParams, beta_lo: int = 0, beta_cap: int = 4, q: float = 0.8) -> int:
    """Percentile of row distances in candidates made under a loose beta, above the lower bound."""
    top = beta_cap + 1

    def distances(grp, x, lam, spread) -> pd.DataFrame:
        n = sum((np.bincount(np.abs(x[:, i] - x[:, j]), minlength=top) for i in range(m) for j in range(i + 1, m)), np.zeros(top, np.int64))
        return pd.DataFrame({"dist": np.arange(top), "n": n})

    counts = C.by_block(series, m, p.with_(beta=beta_cap), distances, "dist long, n long").groupBy("dist").agg(F.sum("n").alias("n"))
    got = counts.where("n > 0").agg(F.percentile("dist", F.lit(q), F.col("n"))).first()[0]
    return max(beta_lo + 1, math.ceil(got or 0))


def compose_grid(series: DataFrame, m: int, grid: list[AlignParams], method: str = "greedy", share: int | None = None, model: str | None = None) -> DataFrame:
    """ALIGN rows with ``point``, the number of a grid point, from one job; with ``model`` (locf or marss) only each
    result's error, (point, grp, delta), which the task computes from the values that it holds.

    A task makes a group's candidates once, for the loosest theta and beta of its ``share`` of the points, and every
    point filters and weighs them. Unless it is given, the share is the largest that still gives every core some tasks:
    all points for many groups, few for one long series.
    """
    spark = series.sparkSession
    if share is None:
        groups = max(1, series.select("grp").distinct().count())
        share = -(-len(grid) // max(1, -(-4 * spark.sparkContext.defaultParallelism // groups)))
    order = sorted(range(len(grid)), key=lambda k: (grid[k].beta, grid[k].theta, k))
    tasks = [order[k : k + max(1, share)] for k in range(0, len(order), max(1, share))]

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        points = [(number, grid[number]) for number in tasks[int(key[1])]]
        theta, beta, any_ = max(g.theta for _, g in points), max(g.beta for _, g in points), points[0][1]
        times, values, has, first = C.matrices(pdf, m, any_.lam_mode == "cell")
        x, lam, spread = C.expand_block(times, has, m, theta, beta, first, first + len(times) - 1, first, any_.cap)
        phi = x.max(axis=1) - x.min(axis=1) if len(x) else spread
        parts = []
        for number, g in points:
            keep = (spread <= g.theta) & (phi <= g.beta)
            _, w, w_fp = C.numpy_weights(x[keep], lam[keep], g)
            chosen = solve(x[keep], w_fp, g, method, spread[keep])
            if model is not None:
                if chosen:
                    parts.append((number, (values, first, x[keep][sorted(chosen)])))
                continue
            part = _result(key[0], x[keep], lam[keep], w, w_fp, chosen)
            part.insert(0, "point", number)
            parts.append(part)
        if model is not None:
            return pd.DataFrame({"point": [number for number, _ in parts], "grp": key[0], "delta": gate.consistencies_of([part for _, part in parts], model)}).astype({"point": "int32", "delta": "float64"})
        return pd.concat(parts, ignore_index=True)

    sent = series.select("grp", "sid", "idx", "ts_us", "val", F.explode(F.sequence(F.lit(0), F.lit(len(tasks) - 1))).alias("task"))
    return sent.groupBy("grp", "task").applyInPandas(run, "point int, " + ALIGN if model is None else "point int, grp string, delta double")


def fit_weights(series: DataFrame, m: int, p: AlignParams, k1=range(1, 7), k2=range(1, 7), n_seeds: int = 1, method: str = "greedy", model: str = "locf") -> DataFrame:
    """(k1, k2, delta): mean consistency error of the results of each weight pair with b = c = 1."""
    grid = [p.with_(k1=float(a), k2=float(b), b=1.0, c=1.0, seed=s, tie="hash" if n_seeds > 1 else p.tie) for a, b, s in itertools.product(k1, k2, range(n_seeds))]
    if model in ("locf", "marss"):
        # each task has its group's values: a result becomes one number before it leaves
        made = compose_grid(series, m, grid, method, model=model)
        errors = made.select("point", F.when(~F.isnan("delta"), F.col("delta")).alias("delta"))
    else:
        made = compose_grid(series, m, grid, method)
        # one group per grid point and grp: the consistency operators work on all of them at once
        tagged = made.withColumn("grp", F.concat_ws("@", F.col("point"), F.col("grp")))
        spread = series.withColumn("point", F.explode(F.sequence(F.lit(0), F.lit(len(grid) - 1))))
        spread = spread.withColumn("grp", F.concat_ws("@", F.col("point"), F.col("grp"))).select("grp", "sid", "idx", "ts_us", "val")
        errors = delta(tagged, spread, m, model).withColumn("point", F.split("grp", "@")[0].cast("int"))
    params = series.sparkSession.createDataFrame([(i, g.k1, g.k2) for i, g in enumerate(grid)], "point int, k1 double, k2 double")
    return errors.join(F.broadcast(params), "point").groupBy("k1", "k2").agg(F.avg("delta").alias("delta"))


def best_weights(table: DataFrame) -> DataFrame:
    """The pair of least error and that error as the model limit; ties go to the smaller pair."""
    return table.orderBy("delta", "k1", "k2").limit(1)


def auto_params(series: DataFrame, m: int, p: AlignParams = AlignParams(), method: str = "greedy", model: str = "locf", k1=range(1, 7), k2=range(1, 7), beta_cap: int = 4) -> AlignParams:
    """theta, beta (from candidates under ``beta_cap``), then (k1, k2) and delta, each from the data."""
    p = p.with_(theta=int(fit_theta(series, exact=False).first()[0] or 0))
    p = p.with_(beta=fit_beta(series, m, p, beta_cap=beta_cap))
    best = best_weights(fit_weights(series, m, p, k1, k2, method=method, model=model)).first()
    return p.with_(k1=best.k1, k2=best.k2, b=1.0, c=1.0, delta=best.delta)


def sweep_counts(series: DataFrame, m: int, thetas: list[int], betas: list[int], p: AlignParams) -> DataFrame:
    """(theta, beta, n): candidates of every grid point, from one loosest set; every block counts its own in a histogram of (spread, phi)."""
    t, b = np.array(sorted(set(thetas))), np.array(sorted(set(betas)))

    def histogram(grp, x, lam, spread) -> pd.DataFrame:
        phi = x.max(axis=1) - x.min(axis=1) if len(x) else spread
        place = np.searchsorted(t, spread) * len(b) + np.searchsorted(b, phi)
        n = np.bincount(place, minlength=len(t) * len(b)).reshape(len(t), len(b)).cumsum(axis=0).cumsum(axis=1)
        return pd.DataFrame({"theta": np.repeat(t, len(b)), "beta": np.tile(b, len(t)).astype("int32"), "n": n.ravel()})

    made = C.by_block(series, m, p.with_(theta=max(thetas), beta=max(betas)), histogram, "theta long, beta int, n long")
    return made.where("n > 0").groupBy("theta", "beta").agg(F.sum("n").alias("n"))
