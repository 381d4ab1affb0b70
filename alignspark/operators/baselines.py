"""Baselines: controls, joins on time, the sequential matcher, and the warping family on complete series."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from alignspark.operators import warping as W
from alignspark.operators.candidates import matrices, spans
from alignspark.operators.compose import ALIGN, align, whole_tables
from alignspark.operators.impute import interpolated
from alignspark.params import AlignParams


def _rows(df: DataFrame) -> DataFrame:
    """ALIGN columns from (grp, x): position by x."""
    order = Window.partitionBy("grp").orderBy("x")
    return df.select("grp", F.row_number().over(order).cast("long").alias("pos"), "x", F.size("x").alias("lam"), F.lit(0.0).alias("w"), F.lit(0).cast("long").alias("w_fp"))


def align_diagonal(series: DataFrame, m: int, theta: int) -> DataFrame:
    """Control: cells of equal row number, where theta allows. Knows the truth of the stand-ins by construction."""
    rows = series.groupBy("grp", "idx").agg(F.count("*").alias("n"), F.coalesce(F.max("ts_us") - F.min("ts_us"), F.lit(0)).alias("s"))
    return _rows(rows.where((F.col("n") == m) & (F.col("s") <= theta)).select("grp", F.array_repeat("idx", m).alias("x")))


def align_exact_ts(series: DataFrame, m: int) -> DataFrame:
    """Strawman: equal timestamps in all series. Of equal times in a series the first row is taken."""
    first = series.where("ts_us IS NOT NULL").groupBy("grp", "ts_us", "sid").agg(F.min("idx").alias("idx"))
    met = first.groupBy("grp", "ts_us").agg(F.array_sort(F.collect_list(F.struct("sid", "idx"))).alias("c"))
    return _rows(met.where(F.size("c") == m).select("grp", F.transform("c", lambda c: c["idx"]).alias("x")))


def align_asof(series: DataFrame, m: int, theta: int) -> DataFrame:
    """For each cell of series 1 the latest row of every other series at or before it, within theta.

    Both sides stand in one ordered list, and each cell takes the last row seen: no pairs are made. Clock blocks of
    width theta keep every list bounded: a match is in the own block or the one before.
    """
    timed = series.where("ts_us IS NOT NULL")
    home = F.floor(F.col("ts_us") / max(theta, 1))
    left = timed.where("sid = 1").select("grp", F.explode(F.sequence(F.lit(2), F.lit(max(m, 2)))).alias("sid"), home.alias("blk"), "ts_us", F.lit(0).alias("side"), "idx")
    right = timed.where("sid > 1").select("grp", "sid", F.explode(F.array(home, home + 1)).alias("blk"), "ts_us", F.lit(1).alias("side"), "idx")
    order = Window.partitionBy("grp", "sid", "blk").orderBy("ts_us", F.desc("side"), "idx").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("side") == 1, F.struct(F.col("ts_us").alias("t"), F.col("idx").alias("i"))), ignorenulls=True).over(order)
    best = left.unionByName(right).withColumn("seen", seen).where((F.col("side") == 0) & (F.col("seen.t") >= F.col("ts_us") - theta))
    best = best.select("grp", F.col("idx").alias("i1"), "sid", F.col("seen.i").alias("idx"))
    met = best.groupBy("grp", "i1").agg(F.array_sort(F.collect_list(F.struct("sid", "idx"))).alias("c"))
    return _rows(met.where(F.size("c") == m - 1).select("grp", F.concat(F.array("i1"), F.transform("c", lambda c: c["idx"])).alias("x")))


def reach_of(series: DataFrame, theta: int) -> int:
    """The largest distance in rows of two cells of different series whose times differ by theta at most.

    First and last row of each series in each clock block of width theta: cells within theta stand in one block or in
    neighbouring ones, so the answer is never too small.
    """
    home = F.floor(F.col("ts_us") / max(theta, 1))
    ends = series.where("ts_us IS NOT NULL").groupBy("grp", "sid", home.alias("blk")).agg(F.min("idx").alias("lo"), F.max("idx").alias("hi"))
    near = ends.withColumn("blk", F.explode(F.array("blk", F.col("blk") + 1))).groupBy("grp", "blk").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    return int(near.agg(F.max(F.col("hi") - F.col("lo"))).first()[0] or 0)


def align_sequential(series: DataFrame, m: int, p: AlignParams) -> DataFrame:
    """Sequential matcher on complete series: a time threshold and nothing else, one ordered scan, of conflicting
    tuples the one of tightest time spread. Rows are as far apart as the threshold lets them be."""
    return align(series, m, p.with_(beta=reach_of(series, p.theta), k2=0.0), "sequential")


def _places(values: list[np.ndarray], method: str, band: int | None, iters: int) -> list[np.ndarray]:
    """For each row of every group the row read from each series, from 0. Many groups are warped together."""
    if method in ("dtw", "ddtw"):
        return W.procrustes_dtw(values, band, method == "ddtw", iters)
    if method == "ctw":
        return W.procrustes_many(values, lambda a, b: W.ctw_many(a, b, band=band), iters)
    return [W.ttw(v) if method == "ttw" else W.procrustes(v, W.gtw, iters) for v in values]


def warp(series: DataFrame, m: int, method: str = "dtw", band: int | None = 50, iters: int = 3) -> DataFrame:
    """Warping baselines on complete series: one tuple for each row of the input. Many groups are warped together."""

    def run(pdf: pd.DataFrame, starts: np.ndarray) -> pd.DataFrame:
        first, size, base, row = spans(pdf["idx"].to_numpy(dtype=np.int64), starts)
        values = np.zeros((int(size.sum()), m))
        values[row, pdf["sid"].to_numpy(dtype=np.int64) - 1] = np.nan_to_num(pd.to_numeric(pdf["val"]).to_numpy(dtype=float, na_value=np.nan))
        where = np.concatenate(_places([values[lo : lo + n] for lo, n in zip(base, size)], method, band, iters)) + np.repeat(first, size)[:, None]
        return pd.DataFrame({"grp": np.repeat(pdf["grp"].to_numpy(dtype=object)[starts], size), "pos": np.arange(1, len(where) + 1) - np.repeat(base, size),
                             "x": pd.Series(list(where), dtype=object), "lam": np.int32(m), "w": 0.0, "w_fp": 0})

    # clocks are not read: without them their delays and interpolation need not be made
    return whole_groups(series.select("grp", "sid", "idx", "val"), run, ALIGN)


def warp_rows(rows: DataFrame, m: int, method: str = "dtw", band: int | None = 50, iters: int = 3, gone: Callable[[int, np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """``warp`` of the linearly interpolated values of (grp, idx, v1..vm), a row for each row number of all series: no cell is
    a row of its own. ``gone`` marks values, by sid and idx, that are taken as missing."""

    def run(table: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
        first, size, base, row = spans(idx := table["idx"].to_numpy(), starts)
        n = int(size.sum())
        values, group = np.zeros((n, m)), np.repeat(np.arange(len(size)), size)
        for j in range(m):
            column = table[f"v{j + 1}"]
            known, v = np.zeros(n, dtype=bool), np.zeros(n)
            known[row], v[row] = column.is_valid().to_numpy(), column.fill_null(0.0).to_numpy()
            if gone is not None:
                known[row] &= ~gone(j + 1, idx)
            values[row, j] = np.nan_to_num(interpolated(v, known, group)[row])  # numbers without a row stay 0
        where = np.concatenate(_places([values[lo : lo + k] for lo, k in zip(base, size)], method, band, iters)) + np.repeat(first, size)[:, None]
        x = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * np.int32(m)), pa.array(where.reshape(-1)))
        same = lambda v, kind: pa.array(np.full(n, v, dtype=kind))
        return pa.RecordBatch.from_arrays([table["grp"].take(pa.array(starts)).combine_chunks().take(pa.array(group)), pa.array(np.arange(1, n + 1) - np.repeat(base, size)), x, same(m, np.int32), same(0, float), same(0, np.int64)],
                                          ["grp", "pos", "x", "lam", "w", "w_fp"])

    return whole_tables(rows.select("grp", "idx", *[F.col(f"v{j + 1}").cast("double") for j in range(m)]), run, ALIGN)


def whole_groups(df: DataFrame, run: Callable[[pd.DataFrame, np.ndarray], pd.DataFrame], schema: str, cells: int = 400_000) -> DataFrame:
    """``run`` over whole groups (by grp), ``cells`` rows and the rest of a group at a time, and the rows where its groups start."""

    def stream(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, starts, n, last = [], [], 0, None
        for frame in frames:
            if not len(frame):
                continue
            grp = frame["grp"].to_numpy(dtype=object)
            cuts = np.flatnonzero(np.append(not held or grp[0] != last, grp[1:] != grp[:-1]))
            if n >= cells and len(cuts):  # all that is held before the last group that starts here
                cut = int(cuts[-1])
                yield run(pd.concat([*held, frame.iloc[:cut]], ignore_index=True), np.concatenate([*starts, cuts[:-1] + n]))
                held, starts, n, frame, cuts = [], [], 0, frame.iloc[cut:], cuts[-1:] - cut
            held.append(frame)
            starts.append(cuts + n)
            n, last = n + len(frame), grp[-1]
        if held:
            yield run(pd.concat(held, ignore_index=True), np.concatenate(starts))

    return df.repartition("grp").sortWithinPartitions("grp").mapInPandas(stream, schema)


def warp_costs(series: DataFrame, m: int, derivative: bool = False) -> DataFrame:
    """(grp, sid, cost): least warping cost of series 1 and each other series, of the values or of their slopes."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        _, values, _, _ = matrices(pdf, m)
        shape = W.slopes if derivative else np.asarray
        cols = [shape(np.nan_to_num(values[:, j])) for j in range(m)]
        return pd.DataFrame({"grp": key[0], "sid": range(2, m + 1), "cost": [W.dtw(cols[0], c)[0] for c in cols[1:]]})

    return series.select("grp", "sid", "idx", "ts_us", "val").groupBy("grp").applyInPandas(run, "grp string, sid int, cost double")


WARPS = ("dtw", "ddtw", "ctw", "gtw", "ttw")
