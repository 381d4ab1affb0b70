"""The state-space model over one very long series: moments in one aggregate, the filter in blocks.

Parameters come from sums that any number of tasks can add up: the
autocovariances at lags 0 to 2 of the composed values give each series' slope
(lag 2 over lag 1), state variance and observation noise. The filter of a block
of tuples is a map of its entry state, and such maps compose; one bounded map a
block goes to the driver, which chains them and sends every block its true entry
state. A second pass then filters each block alone. The result equals the
filter over the whole series.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FLOOR = 1e-6
PRED = "grp string, pos long, sid int, idx long, ts_us long, val double, pred double"


def step_element(y: np.ndarray, slope: np.ndarray, q: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, ...]:
    """One tuple as a map (A, b, C, eta, J) of diagonal parts: series do not mix, so every part is a vector."""
    seen = ~np.isnan(y)
    s = q + r
    gain = np.where(seen, q / s, 0.0)
    v = np.nan_to_num(y)
    return (1 - gain) * slope, gain * v, (1 - gain) * q, np.where(seen, slope * v / s, 0.0), np.where(seen, slope * slope / s, 0.0)


def chain(i: tuple[np.ndarray, ...], j: tuple[np.ndarray, ...]) -> tuple[np.ndarray, ...]:
    """First ``i``, then ``j``."""
    a1, b1, c1, e1, j1 = i
    a2, b2, c2, e2, j2 = j
    d = 1 / (1 + c1 * j2)
    return a2 * d * a1, a2 * d * (b1 + c1 * e2) + b2, a2 * d * c1 * a2 + c2, a1 * d * (e2 - j2 * b1) + e1, a1 * d * j2 * a1 + j1


def apply(element: tuple[np.ndarray, ...], mean: np.ndarray, var: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The filtered state after a block that was entered with filtered state (mean, var)."""
    a, b, c, e, j = element
    d = 1 / (1 + var * j)
    return a * d * (mean + var * e) + b, a * d * var * a + c


def filter_block(y: np.ndarray, slope: np.ndarray, q: np.ndarray, r: np.ndarray, mean: np.ndarray, var: np.ndarray) -> np.ndarray:
    """One-step predictions of a block entered with filtered state (mean, var)."""
    out = np.empty_like(y)
    for t in range(len(y)):
        mean, var = slope * mean, slope * slope * var + q
        out[t] = mean
        gain = np.where(np.isnan(y[t]), 0.0, var / (var + r))
        mean, var = mean + gain * (np.nan_to_num(y[t]) - mean), (1 - gain) * var
    return out


def moments(cells: DataFrame) -> DataFrame:
    """(grp, sid, mean, slope, q, r) from sums over tuples one and two apart; gaps leave out the products they break."""
    mean = cells.groupBy("grp", "sid").agg(F.avg("val").alias("mean"))
    v = cells.join(mean, ["grp", "sid"]).select("grp", "sid", "pos", (F.col("val") - F.col("mean")).alias("v"))
    # the own value and those one and two tuples later meet at one position: sums, no window over the series
    lags = v.select("grp", "sid", F.posexplode(F.array(F.col("pos"), F.col("pos") + 1, F.col("pos") + 2)).alias("lag", "pos"), "v")
    met = lags.groupBy("grp", "sid", "pos").agg(*[F.max(F.when(F.col("lag") == k, F.col("v"))).alias(f"v{k}") for k in range(3)])
    sums = met.groupBy("grp", "sid").agg(*[F.avg(F.col("v0") * F.col(f"v{k}")).alias(f"g{k}") for k in range(3)])
    g0, g1, g2 = (F.coalesce(f"g{k}", F.lit(0.0)) for k in range(3))
    slope = F.when(g1 > FLOOR, F.least(F.greatest(g2 / g1, F.lit(0.0)), F.lit(0.999))).otherwise(0.0)
    state = F.when(slope > FLOOR, F.least(g1 / slope, g0)).otherwise(g0)
    out = sums.select("grp", "sid", slope.alias("slope"), F.greatest(state * (1 - slope * slope), F.lit(FLOOR)).alias("q"), F.greatest(g0 - state, F.lit(FLOOR)).alias("r"))
    return mean.join(out, ["grp", "sid"])


def _block(pdf: pd.DataFrame, size: int, blk: int) -> tuple[np.ndarray, tuple[np.ndarray, ...], np.ndarray, np.ndarray]:
    """Centred values (tuples x series), parameters by series, and where each row of the frame stands."""
    sids = np.unique(pdf["sid"].to_numpy())
    par = pdf.drop_duplicates("sid").sort_values("sid")
    mean, slope, q, r = (par[c].to_numpy(dtype=float) for c in ("mean", "slope", "q", "r"))
    mean = np.nan_to_num(mean)
    at = pdf["pos"].to_numpy() - blk * size - 1, np.searchsorted(sids, pdf["sid"].to_numpy())
    y = np.full((int(at[0].max()) + 1, len(sids)), np.nan)
    y[at] = pdf["val"].to_numpy(dtype=float)
    return y - mean, (slope, q, r), mean, at


def predict_scan(cells: DataFrame, size: int = 5000) -> DataFrame:
    """Adds one-step predictions to composed cells (grp, pos, sid, idx, ts_us, val); one task holds ``size`` tuples."""
    spark = cells.sparkSession
    rows = cells.select("grp", "pos", "sid", "idx", "ts_us", "val").join(moments(cells), ["grp", "sid"]).withColumn("blk", F.floor((F.col("pos") - 1) / size))

    def element(key, pdf: pd.DataFrame) -> pd.DataFrame:
        y, par, _, _ = _block(pdf, size, int(key[1]))
        got = step_element(y[0], *par)
        for t in range(1, len(y)):
            got = chain(got, step_element(y[t], *par))
        var = par[1] / (1 - par[0] ** 2)
        return pd.DataFrame({"grp": [key[0]], "blk": [key[1]], "element": [np.concatenate(got).tolist()], "var": [var.tolist()]})

    maps = rows.groupBy("grp", "blk").applyInPandas(element, "grp string, blk long, element array<double>, var array<double>")
    entry, last, state = [], None, (None, None)
    for grp, blk, flat, var in sorted(tuple(x) for x in maps.collect()):
        parts = tuple(np.array(flat).reshape(5, -1))
        if grp != last:
            last, state = grp, (np.zeros(len(var)), np.array(var))
        entry.append((grp, blk, state[0].tolist(), state[1].tolist()))
        state = apply(parts, *state)
    known = spark.createDataFrame(entry, "grp string, blk long, m0 array<double>, v0 array<double>")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        y, par, mean, at = _block(pdf, size, int(key[1]))
        pred = filter_block(y, *par, np.array(pdf["m0"].iloc[0]), np.array(pdf["v0"].iloc[0])) + mean
        return pdf.assign(pred=pred[at])[["grp", "pos", "sid", "idx", "ts_us", "val", "pred"]]

    return rows.join(known, ["grp", "blk"]).groupBy("grp", "blk").applyInPandas(run, PRED)
