"""Chooses how to run an alignment from the sizes of its groups."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from alignspark.functions.measures import candidate_count_bound
from alignspark.operators import compose as K
from alignspark.params import AlignParams
from alignspark.plans.blocks import align_blocks

#: Candidates that one task may hold; rows of a block aimed at.
TASK_CANDIDATES, BLOCK_ROWS = 2_000_000, 20_000


@dataclass(frozen=True)
class AlignPlan:
    executor: str
    block_rows: int
    longest: int
    bound: int
    method: str

    def explain(self) -> str:
        return f"{self.method} by {self.executor}: longest group {self.longest} rows, at most {self.bound} candidates" + (f", blocks of {self.block_rows} rows" if self.executor == "block" else "")


def plan(series: DataFrame, m: int, p: AlignParams, method: str) -> AlignPlan:
    """One aggregate over the row numbers; the closed-form candidate bound decides between one task a group and blocks."""
    row = series.groupBy("grp").agg((F.max("idx") - F.min("idx") + 1).alias("n")).agg(F.max("n").alias("n")).first()
    longest = int(row.n or 0)
    bound = candidate_count_bound(longest, m, p.beta)
    per_row = max(1, bound // max(1, longest))
    block = max(16 * p.beta + 64, min(BLOCK_ROWS, TASK_CANDIDATES // per_row))
    blocky = bound > TASK_CANDIDATES and method in ("greedy", "expectation") and not (p.literal or p.expect_live_only)
    return AlignPlan("block" if blocky else "group", block, longest, bound, method)


def align_planned(series: DataFrame, m: int, p: AlignParams, method: str = "expectation") -> DataFrame:
    chosen = plan(series, m, p, method)
    if chosen.executor == "block":
        return align_blocks(series, m, p, method, size=chosen.block_rows)
    return K.align(series, m, p, method)


def align_until_feasible(series: DataFrame, m: int, p: AlignParams, method: str = "greedy", model: str = "locf") -> DataFrame:
    """ALIGN with ``status``: rounds with new tie seeds for the groups whose model error is still above delta.

    Every round runs as the planner says, so long series go in blocks. A group that no round satisfies keeps its best
    round and is marked infeasible. Only the list of groups' errors moves between rounds, as a table. Composers with
    alternatives of their own (packing, exact) choose among them in one round instead.
    """
    from alignspark.operators.conflicts import settled
    from alignspark.operators.consistency import delta

    if p.delta is None:
        return align_planned(series, m, p, method).withColumn("status", F.lit("feasible"))
    if method in ("packing", "exact"):
        return K.align_gated(series, m, p, method, model)
    todo, best = series, None
    for turn in range(p.max_rounds):
        made = settled(align_planned(todo, m, p if turn == 0 else p.with_(tie="random", seed=turn), method), "round")
        errors = settled(delta(made, todo, m, model), "errors")
        scored = made.join(errors, "grp", "left").withColumn("turn", F.lit(turn))
        best = scored if best is None else best.unionByName(scored)
        failing = errors.where(F.col("delta") > p.delta).select("grp")
        if failing.isEmpty():
            break
        todo = settled(todo.join(failing, "grp", "left_semi"), "todo")
    pick = best.groupBy("grp").agg(F.min_by("turn", F.struct((F.col("delta") > p.delta), F.when(F.col("delta") > p.delta, F.col("delta")).otherwise(0.0), "turn")).alias("turn"))
    kept = best.join(pick, ["grp", "turn"])
    return kept.withColumn("status", F.when(F.col("delta") > p.delta, "infeasible").otherwise("feasible")).drop("turn")
