"""Accuracy measures: recovered variable pairs against the truth, tuples, weight, diagnostics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pairs_recovered(aligned: DataFrame, series: DataFrame | None = None, universe: str = "index") -> DataFrame:
    """PAIR rows of a result. ``observed`` keeps pairs whose two values are both present."""
    cell = F.transform("x", lambda v, j: F.struct((j + 1).cast("int").alias("sid"), v.alias("idx")))
    pairs = aligned.select("grp", F.explode(F.flatten(F.transform(cell, lambda a: F.transform(F.filter(cell, lambda b: b["sid"] > a["sid"]), lambda b: F.struct(a.alias("a"), b.alias("b")))))).alias("p"))
    out = pairs.select("grp", F.col("p.a.sid").alias("sid_a"), F.col("p.a.idx").alias("idx_a"), F.col("p.b.sid").alias("sid_b"), F.col("p.b.idx").alias("idx_b"))
    return _observed(out, series) if universe == "observed" else out


def pairs_truth(series: DataFrame, universe: str = "index") -> DataFrame:
    """Cells of one base row belong together: pairs of equal idx."""
    a = series.select("grp", "idx", F.col("sid").alias("sid_a"))
    b = series.select("grp", "idx", F.col("sid").alias("sid_b"))
    out = a.join(b, ["grp", "idx"]).where("sid_a < sid_b").select("grp", "sid_a", F.col("idx").alias("idx_a"), "sid_b", F.col("idx").alias("idx_b"))
    return _observed(out, series) if universe == "observed" else out


def _observed(pairs: DataFrame, series: DataFrame) -> DataFrame:
    seen = series.where("val IS NOT NULL")
    for end in "ab":
        pairs = pairs.join(seen.select("grp", F.col("sid").alias(f"sid_{end}"), F.col("idx").alias(f"idx_{end}")), ["grp", f"sid_{end}", f"idx_{end}"], "left_semi")
    return pairs.select("grp", "sid_a", "idx_a", "sid_b", "idx_b")


def f1_score(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: pairs found, true and both; precision, recall, f1 (0 where nothing meets)."""
    keys = ["grp", "sid_a", "idx_a", "sid_b", "idx_b"]
    marked = found.distinct().withColumn("f", F.lit(1)).join(truth.distinct().withColumn("t", F.lit(1)), keys, "full")
    n = marked.agg(F.count("f").alias("found"), F.count("t").alias("truth"), F.count(F.when(F.col("f").isNotNull() & F.col("t").isNotNull(), 1)).alias("both"))
    precision = F.when(F.col("found") > 0, F.col("both") / F.col("found")).otherwise(0.0)
    recall = F.when(F.col("truth") > 0, F.col("both") / F.col("truth")).otherwise(0.0)
    out = n.withColumn("precision", precision).withColumn("recall", recall)
    return out.withColumn("f1", F.when(F.col("both") > 0, 2 * F.col("precision") * F.col("recall") / (F.col("precision") + F.col("recall"))).otherwise(0.0))


def total_weight(aligned: DataFrame) -> DataFrame:
    return aligned.groupBy("grp").agg(F.count("*").alias("n_aligned"), F.sum("w_fp").alias("w_fp"))


def align_profile(aligned: DataFrame) -> DataFrame:
    """Tuples by lambda and by whether all rows are equal, with subtotals."""
    diagonal = F.array_max("x") == F.array_min("x")
    return aligned.select("lam", diagonal.alias("diagonal"), (F.array_max("x") - F.array_min("x")).alias("gap")).cube("lam", "diagonal").agg(F.count("*").alias("n"), F.avg("gap").alias("gap"))


def approx_ratio(aligned: DataFrame, exact: DataFrame) -> DataFrame:
    """(grp, ratio) of a result's weight to the exact one's."""
    a = aligned.groupBy("grp").agg(F.sum("w_fp").alias("a"))
    e = exact.groupBy("grp").agg(F.sum("w_fp").alias("e"))
    return e.join(a, "grp", "left").select("grp", (F.coalesce("a", F.lit(0)) / F.col("e")).alias("ratio"))
