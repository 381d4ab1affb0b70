"""One very long series: the fold in blocks of leads, exact whatever the data.

A block's task makes the candidates of its leads (plus a warm-up of earlier ones
and the look-ahead rows) and folds them. The state at a block's edge is small:
the open clique and the cells of winners at most 2 beta leads back. Each block
starts from a guess of that state, gained from the warm-up, and reports the
state it was entered with and the state it left. Where a block's entry state is
not what its predecessor left, it is run again from the true state; the driver
only sees one row of hashes per block. Since every emission clears the clique,
a guess is nearly always right.
"""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from alignspark.operators import candidates as C
from alignspark.operators.compose import ALIGN
from alignspark.operators.conflicts import settled
from alignspark.operators.fold import _choose, expectation_scores, tie_key
from alignspark.params import AlignParams

OUT = "grp string, blk long, entry string, left string, x array<long>, lam int, w double, w_fp long"


def _run(x: np.ndarray, w: np.ndarray, p: AlignParams, method: str, state: dict, lo: int, hi: int) -> tuple[list[int], dict, dict]:
    """Folds candidates whose lead is in lo..hi, starting from ``state``; what is chosen, the entry and the exit state."""
    m = x.shape[1]
    rows = x.tolist()
    lead = x[:, 0] if len(x) else np.zeros(0, np.int64)
    start, stop = np.searchsorted(lead, [lo, hi + 1])
    where = {tuple(r): k for k, r in enumerate(rows)}
    ties = tie_key(x, p)
    used = [set() for _ in range(m)]
    for r in state["won"]:
        for v, u in zip(r, used):
            u.add(v)
    clique = [where[tuple(r)] for r in state["clique"]]
    won = [list(r) for r in state["won"]]
    chosen: list[int] = []

    def emit():
        if len(clique) == 1:
            best = clique[0]
        elif method == "expectation":
            best = _choose(clique, expectation_scores(x, w, clique, p), ties)
        else:
            best = _choose(clique, w[clique], ties)
        chosen.append(best)
        won.append(rows[best])
        for v, u in zip(rows[best], used):
            u.add(v)
        return rows[best]

    for k in range(int(start), int(stop)):
        r = rows[k]
        if any(v in u for v, u in zip(r, used)):
            continue
        if all(any(a == b for a, b in zip(rows[g], r)) for g in clique):
            clique.append(k)
            continue
        best = emit()
        clique = [] if any(a == b for a, b in zip(best, r)) else [k]
    if clique and int(x[clique].max()) + p.beta <= hi:
        # no later lead can conflict with a member: the winner is settled, and the next clique starts afresh either way
        emit()
        clique = []
    return chosen, {"clique": [rows[g] for g in clique], "won": sorted(r for r in won if r[0] >= hi + 1 - 2 * p.beta)}, state


def align_blocks(series: DataFrame, m: int, p: AlignParams, method: str = "greedy", size: int = 2000, warm: int = 40, max_passes: int = 100) -> DataFrame:
    """ALIGN rows equal to the one-task fold's, for groups of any length."""
    if p.literal or p.expect_live_only or method not in ("greedy", "expectation"):
        raise ValueError("blocks fold greedy and expectation with carry and flush")
    before, after = warm + 3 * p.beta + 2, 4 * p.beta + 2
    rows = C.with_blocks(series.select("grp", "sid", "idx", "ts_us", "val"), size, after, before)
    ends = settled(series.groupBy("grp").agg(F.max("idx").alias("n")), "ends")

    def fold_block(pdf: pd.DataFrame, grp: str, blk: int, state: dict | None, last: int) -> pd.DataFrame:
        lo, hi = blk * size + 1, (blk + 1) * size
        times, _, has, first = C.matrices(pdf, m, p.lam_mode == "cell")
        x, lam, _ = C.expand_block(times, has, m, p.theta, p.beta, max(first, lo - warm - 2 * p.beta), min(hi + after - p.beta, last), first, p.cap)
        _, w, w_fp = C.numpy_weights(x, lam, p)
        if state is None:
            state = {"clique": [], "won": []}
            if lo > 1:
                _, state, _ = _run(x, w_fp, p, method, state, lo - warm, lo - 1)
                state["won"] = [r for r in state["won"] if r[0] >= lo - 2 * p.beta]
        chosen, left, _ = _run(x, w_fp, p, method, state, lo, hi)
        if hi >= last and left["clique"]:  # the end of the group: flush
            ids = {tuple(r): k for k, r in enumerate(x.tolist())}
            clique = [ids[tuple(r)] for r in left["clique"]]
            score = expectation_scores(x, w_fp, clique, p) if method == "expectation" and len(clique) > 1 else w_fp[clique]
            chosen.append(_choose(clique, score, tie_key(x, p)))
            left = {"clique": [], "won": []}
        k = np.array(chosen, dtype=np.int64)
        enter, leave = (json.dumps({"clique": s["clique"], "won": sorted(s["won"])}) for s in (state, left))
        out = pd.DataFrame({"x": list(x[k]), "lam": lam[k].astype("int32"), "w": w[k], "w_fp": w_fp[k]}) if len(k) else pd.DataFrame({"x": [None], "lam": [None], "w": [None], "w_fp": [None]})
        out.insert(0, "grp", grp)
        out.insert(1, "blk", blk)
        out.insert(2, "entry", enter)
        out.insert(3, "left", leave)
        return out

    def first_pass(key, pdf: pd.DataFrame) -> pd.DataFrame:
        return fold_block(pdf, key[0], int(key[1]), None, int(pdf["n"].iloc[0]))

    def again(key, pdf: pd.DataFrame) -> pd.DataFrame:
        return fold_block(pdf, key[0], int(key[1]), json.loads(pdf["state"].iloc[0]), int(pdf["n"].iloc[0]))

    rows = rows.join(ends, "grp").where((F.col("blk") * size < F.col("n")))
    done = settled(rows.groupBy("grp", "blk").applyInPandas(first_pass, OUT), "blocks")
    for _ in range(max_passes):
        states = done.select("grp", "blk", "entry", "left").distinct()
        before_it = states.select("grp", (F.col("blk") + 1).alias("blk"), F.col("left").alias("state"))
        wrong = states.join(before_it, ["grp", "blk"]).where("entry <> state").select("grp", "blk", "state")
        wrong = settled(wrong, "wrong")
        if wrong.isEmpty():
            break
        mended = rows.join(wrong, ["grp", "blk"]).groupBy("grp", "blk").applyInPandas(again, OUT)
        done = settled(done.join(wrong, ["grp", "blk"], "left_anti").unionByName(mended), "blocks")
    else:
        raise RuntimeError("block states did not settle")
    kept = done.where("x IS NOT NULL")
    # positions without a window over the whole series: rank within the block plus what earlier blocks hold
    sizes = kept.groupBy("grp", "blk").agg(F.count("*").alias("c"))
    from pyspark.sql import Window

    base = sizes.withColumn("base", F.coalesce(F.sum("c").over(Window.partitionBy("grp").orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    rank = F.row_number().over(Window.partitionBy("grp", "blk").orderBy("x"))
    return kept.withColumn("rank", rank).join(base.select("grp", "blk", "base"), ["grp", "blk"]).select("grp", (F.col("base") + F.col("rank")).cast("long").alias("pos"), "x", "lam", "w", "w_fp")


ALIGN_COLUMNS = [c.split()[0] for c in ALIGN.split(", ")]
