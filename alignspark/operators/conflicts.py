"""Conflict structure of candidates: edges, degrees, cliques, cut points, components.

The functions on a candidate table are relational. Those named ``*_of`` start from the series: a block of leads makes
its candidates and finds their conflicts in one task, so that neither candidates nor edges are shuffled.
"""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from alignspark.operators import candidates as C
from alignspark.params import AlignParams


def shared_path(spark: SparkSession, label: str) -> str:
    """A path in the folder that driver and executors share (spark.checkpoint.dir).

    A folder of our own is made only where driver and executors are one process; on a cluster that is an error.
    """
    top = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not top:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        top = tempfile.mkdtemp(prefix="alignspark-")
        spark.sparkContext.setCheckpointDir(top)
    return f"{top.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def settled(df: DataFrame, label: str) -> DataFrame:
    """Written to the shared folder and read back: cuts the lineage of iterations, survives lost executors."""
    path = shared_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def conflict_edges(cand: DataFrame) -> DataFrame:
    """(grp, a, b), a before b: tuples that share a cell."""
    cell = cand.select("grp", "x", F.posexplode("x").alias("s", "idx"))
    left, right = cell.select("grp", "s", "idx", F.col("x").alias("a")), cell.select("grp", "s", "idx", F.col("x").alias("b"))
    return left.join(right, ["grp", "s", "idx"]).where(F.col("a") < F.col("b")).select("grp", "a", "b").distinct()


def conflict_degree(cand: DataFrame) -> DataFrame:
    """(grp, x, degree) of every candidate, 0 included."""
    edges = conflict_edges(cand)
    ends = edges.select("grp", F.col("a").alias("x")).unionByName(edges.select("grp", F.col("b").alias("x")))
    return cand.select("grp", "x").join(ends.groupBy("grp", "x").agg(F.count("*").alias("degree")), ["grp", "x"], "left").fillna(0, ["degree"])


def is_clique(cands: DataFrame) -> DataFrame:
    """(grp, missing): pairs of a set of candidates that don't conflict; a clique has none."""
    n = cands.groupBy("grp").agg(F.count("*").alias("n"))
    edges = conflict_edges(cands).groupBy("grp").agg(F.count("*").alias("e"))
    return n.join(edges, "grp", "left").select("grp", (F.col("n") * (F.col("n") - 1) / 2 - F.coalesce("e", F.lit(0))).cast("long").alias("missing"))


def segments(cand: DataFrame) -> DataFrame:
    """CAND with ``seg``: runs of leads that no candidate straddles. Works on one row a lead, not on candidates."""
    reach = cand.groupBy("grp", F.col("x")[0].alias("lead")).agg(F.max(F.array_max("x")).alias("top"), F.min(F.array_min("x")).alias("low"))
    order = Window.partitionBy("grp").orderBy("lead")
    before = F.max("top").over(order.rowsBetween(Window.unboundedPreceding, -1))
    after = F.min("low").over(order.rowsBetween(0, Window.unboundedFollowing))
    cut = reach.withColumn("new", F.when(before.isNull() | (before < after), 1).otherwise(0))
    numbered = cut.select("grp", "lead", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("seg"))
    return cand.withColumn("lead", F.col("x")[0]).join(numbered, ["grp", "lead"]).drop("lead")


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """(grp, x, root): smallest tuple reachable, by labels that spread and are followed until nothing changes."""
    both = settled(edges.select("grp", F.col("a").alias("x"), F.col("b").alias("y")).unionByName(edges.select("grp", F.col("b").alias("x"), F.col("a").alias("y"))), "edges")
    label = settled(both.groupBy("grp", "x").agg(F.least(F.min("y"), F.first("x")).alias("root")), "labels")
    for _ in range(max_rounds):
        spread = both.join(label.select("grp", F.col("x").alias("y"), "root"), ["grp", "y"]).groupBy("grp", "x").agg(F.min("root").alias("near"))
        moved = label.join(spread, ["grp", "x"]).select("grp", "x", F.least("root", "near").alias("up"), "root")
        jump = moved.select("grp", F.col("x").alias("up"), F.col("up").alias("upper"))
        fresh = settled(moved.join(jump, ["grp", "up"], "left").select("grp", "x", F.least("up", F.coalesce("upper", "up")).alias("root"), (F.col("root") != F.least("up", F.coalesce("upper", "up"))).alias("changed")), "labels")
        label = fresh.drop("changed")
        if fresh.where("changed").isEmpty():
            return label
    raise RuntimeError("components did not settle")


# --- in one task a block of leads -------------------------------------------------------------------------------------


def conflict_pairs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions a < b of all pairs of tuples that share a cell, each pair once; ``x`` in lexicographic order."""
    left, right = [], []
    for j in range(x.shape[1]):
        order = np.argsort(x[:, j], kind="stable")
        held = x[order, j]
        later = np.searchsorted(held, held, side="right") - np.arange(len(order)) - 1
        at = np.repeat(np.arange(len(order)), later)
        nth = np.arange(len(at)) - np.repeat(np.cumsum(later) - later, later)
        a, b = order[at], order[at + 1 + nth]
        first = ~(x[a, :j] == x[b, :j]).any(axis=1)  # a pair counts at the first series it shares
        left.append(a[first])
        right.append(b[first])
    return np.concatenate(left), np.concatenate(right)


def _blocks_of(series: DataFrame, m: int, p: AlignParams, run, schema: str, size: int) -> DataFrame:
    """``run(grp, x, own)`` for each block of leads: its candidates and those that may conflict with them, and which are its own.

    Tuples that share a cell have leads at most 2 beta apart.
    """
    sent = C.with_blocks(series.select("grp", "sid", "idx", "ts_us", "val"), size, 3 * p.beta)

    def task(key, pdf: pd.DataFrame) -> pd.DataFrame:
        lo, hi = int(key[1]) * size + 1, (int(key[1]) + 1) * size
        times, _, has, first = C.matrices(pdf, m, p.lam_mode == "cell")
        x, _, _ = C.expand_block(times, has, m, p.theta, p.beta, lo - 2 * p.beta, hi + 2 * p.beta, first, p.cap)
        return run(key[0], x, (x[:, 0] >= lo) & (x[:, 0] <= hi))

    return sent.groupBy("grp", "blk").applyInPandas(task, schema)


def _tuples(x: np.ndarray) -> pd.Series:
    return pd.Series(list(x), dtype=object)


def edges_of(series: DataFrame, m: int, p: AlignParams, size: int = 500) -> DataFrame:
    """``conflict_edges`` of a series' candidates: an edge is made by the block of its earlier tuple."""

    def run(grp, x, own):
        a, b = conflict_pairs(x)
        mine = own[a]
        return pd.DataFrame({"grp": grp, "a": _tuples(x[a[mine]]), "b": _tuples(x[b[mine]])})

    return _blocks_of(series, m, p, run, "grp string, a array<long>, b array<long>", size)


def degree_of(series: DataFrame, m: int, p: AlignParams, size: int = 500) -> DataFrame:
    """``conflict_degree`` of a series' candidates."""

    def run(grp, x, own):
        a, b = conflict_pairs(x)
        degree = np.bincount(a, minlength=len(x)) + np.bincount(b, minlength=len(x))
        return pd.DataFrame({"grp": grp, "x": _tuples(x[own]), "degree": degree[own]})

    return _blocks_of(series, m, p, run, "grp string, x array<long>, degree long", size)


def counts_of(series: DataFrame, m: int, p: AlignParams, size: int = 500) -> DataFrame:
    """(grp, n, edges, beyond): candidates, edges, and edges whose later tuple is past the earlier one's largest row + beta."""

    def run(grp, x, own):
        a, b = conflict_pairs(x)
        a, b = a[own[a]], b[own[a]]
        top = x.max(axis=1, initial=0)
        return pd.DataFrame({"grp": [grp], "n": [int(own.sum())], "edges": [len(a)], "beyond": [int((top[b] > top[a] + p.beta).sum())]})

    parts = _blocks_of(series, m, p, run, "grp string, n long, edges long, beyond long", size)
    return parts.groupBy("grp").agg(*[F.sum(c).alias(c) for c in ("n", "edges", "beyond")]).where("n > 0")


def _local_roots(x: np.ndarray) -> np.ndarray:
    """For each tuple the position of the first one that it is connected with."""
    label = np.arange(len(x))
    runs = []
    for j in range(x.shape[1]):
        order = np.argsort(x[:, j], kind="stable")
        starts = np.flatnonzero(np.r_[True, np.diff(x[order, j]) != 0]) if len(x) else np.zeros(0, np.int64)
        runs.append((order, starts, np.diff(np.r_[starts, len(x)])))
    while len(x):
        before = label
        for order, starts, sizes in runs:
            fresh = np.empty_like(label)
            fresh[order] = np.repeat(np.minimum.reduceat(label[order], starts), sizes)
            label = fresh[fresh]
        if (label == before).all():
            break
    return label


def component_sizes_of(series: DataFrame, m: int, p: AlignParams, size: int = 500) -> DataFrame:
    """(grp, root, n) of the components with an edge: smallest tuple and number of tuples.

    Blocks find their own components; those that touch a cell near a block's edge are joined through these cells.
    """

    def run(grp, x, own):
        x = x[own]
        lo, hi = ((x[0, 0] - 1) // size * size + 1, (x[0, 0] - 1) // size * size + size) if len(x) else (0, 0)
        root = _local_roots(x)
        count = np.bincount(root, minlength=len(x))
        near = (x < lo + p.beta) & (lo > 1) | (x > hi - p.beta)
        ports: dict[int, set] = {}
        for k, j in zip(*np.nonzero(near)):
            ports.setdefault(int(root[k]), set()).add((int(j), int(x[k, j])))
        kept = np.flatnonzero(count)
        return pd.DataFrame({"grp": grp, "root": _tuples(x[kept]), "n": count[kept],
                             "ports": pd.Series([[{"s": s, "idx": i} for s, i in sorted(ports.get(int(k), ()))] for k in kept], dtype=object)})

    made = settled(_blocks_of(series, m, p, run, "grp string, root array<long>, n long, ports array<struct<s: int, idx: long>>", size), "parts")
    port = made.select("grp", "root", F.explode("ports").alias("c")).select("grp", "root", "c.s", "c.idx")
    least = port.groupBy("grp", "s", "idx").agg(F.min("root").alias("a"), F.max("root").alias("top")).where("a < top").drop("top")
    links = settled(port.join(least, ["grp", "s", "idx"]).where("a < root").select("grp", "a", F.col("root").alias("b")).distinct(), "links")
    sizes = made.select("grp", "root", "n")
    if not links.isEmpty():
        moved = components(links).select("grp", F.col("x").alias("root"), F.col("root").alias("to"))
        sizes = sizes.join(moved, ["grp", "root"], "left").groupBy("grp", F.coalesce("to", "root").alias("root")).agg(F.sum("n").alias("n"))
    return sizes.where("n > 1")
