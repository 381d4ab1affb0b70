"""Connected components of an edge table by hooking and contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from alignspark.llm.common import discard, stash


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b: long); root is the smallest node reachable.

    Each round hooks every node to its smallest neighbour, follows parents three
    times, and keeps the edges between what is still apart. Every frame is
    written to the shared folder, so no round recomputes another; only the result
    stays there. No edges, no rows; repeated edges and loops change nothing.
    """
    both = edges.where("a <> b").select("a", "b").unionByName(edges.where("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b")))
    live = stash(both.distinct(), "edges")
    maps: list[DataFrame] = []
    for _ in range(max_rounds):
        hooked = live.groupBy("a").agg(F.min("b").alias("b")).select(F.col("a").alias("node"), F.least("a", "b").alias("up"))
        hooked = stash(hooked, "parents")
        parent = hooked
        for _ in range(2):
            above = parent.select(F.col("node").alias("up"), F.col("up").alias("upper"))
            parent = parent.join(above, "up", "left").select("node", F.coalesce("upper", "up").alias("up"))
        parent = stash(parent, "parents")
        maps.append(parent)
        left = parent.select(F.col("node").alias("a"), F.col("up").alias("x"))
        right = parent.select(F.col("node").alias("b"), F.col("up").alias("y"))
        apart = live.join(left, "a").join(right, "b").where("x <> y").select(F.col("x").alias("a"), F.col("y").alias("b"))
        rest = stash(apart.distinct(), "edges")
        discard(live, hooked)
        live = rest
        if live.isEmpty():
            break
    else:
        raise RuntimeError("components did not settle")
    out = maps[0].select("node", F.col("up").alias("root"))
    for step in maps[1:]:
        out = out.join(step.select(F.col("node").alias("root"), "up"), "root", "left").select("node", F.coalesce("up", "root").alias("root"))
    out = stash(out, "components")
    discard(live, *maps)
    return out
