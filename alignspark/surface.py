"""What lies around the methods: file formats, SQL functions and streams, as queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.functions.udfs import delta_udaf, register_align_series, register_candidates, weight_udf
from alignspark.operators import candidates as C
from alignspark.operators.conflicts import shared_path
from alignspark.params import AlignParams
from alignspark.sources import workloads as W
from alignspark.streaming import aligner, aggregates

QUERIES: dict[str, tuple] = {}
P = AlignParams()

EVENTS = "SELECT event_id, user_id, event_type, round(value, 6) AS value FROM events"


def _round_trip(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """Events written in another format to the shared folder and read back with an explicit schema."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "event_type", F.round("value", 6).alias("value"))
    path = shared_path(spark, f"events-{kind}")
    writer = e.write.option("header", True) if kind == "csv" else e.write
    getattr(writer, kind)(path)
    reader = spark.read.schema(e.schema)
    return getattr(reader.option("header", True) if kind == "csv" else reader, kind)(path)


for _kind in ("csv", "json", "orc"):
    QUERIES[f"src_{_kind}"] = ((lambda k: lambda s, d: _round_trip(s, d, k))(_kind), EVENTS)


def src_multi(spark, sf_dir):
    """One file set per series, as separate recorders leave them; the series number comes from the folder."""
    s = W.build(spark, sf_dir, "ev4", 0.2)
    path = shared_path(spark, "recorders")
    s.write.partitionBy("sid").parquet(path)
    back = spark.read.parquet(path)
    return back.groupBy(F.col("sid").cast("int").alias("sid")).agg(F.count("*").alias("n"), F.count("ts_us").alias("n_t"))


_SERIES = f"WITH {W.sql('ev4', 0.2)}"
QUERIES["src_multi"] = (src_multi, f"{_SERIES} SELECT sid, count(*)::BIGINT AS n, count(ts_us)::BIGINT AS n_t FROM series GROUP BY 1")


def sink_parquet(spark, sf_dir):
    """A result partitioned by bucket of group and by block, read back with both filters pruned at the folders."""
    s = W.build(spark, sf_dir, "evu", 0.2).withColumns({"bucket": F.pmod(F.crc32("grp"), F.lit(8)).cast("int"), "blk": F.floor((F.col("idx") - 1) / 50).cast("int")})
    path = shared_path(spark, "sink")
    s.write.partitionBy("bucket", "blk").parquet(path)
    return spark.read.parquet(path).groupBy("blk").agg(F.count("*").alias("n"), F.count("val").alias("n_v"))


QUERIES["sink_parquet"] = (sink_parquet, f"WITH {W.sql('evu', 0.2)} SELECT ((idx - 1) // 50)::INT AS blk, count(*)::BIGINT AS n, count(val)::BIGINT AS n_v FROM series GROUP BY 1")

_CAND = f"{_SERIES},\n{C.sql(4, P)}"
QUERIES["udf_weight"] = (
    lambda s, d: C.candidates(W.build(s, d, "ev4", 0.2), 4, P).select(*[F.col("x")[j].alias(f"i{j + 1}") for j in range(4)], F.round(weight_udf(P)("lam", "d"), 6).alias("w")),
    f"{_CAND} SELECT i1, i2, i3, i4, round(w, 6) AS w FROM cand")


def udaf_delta(spark, sf_dir):
    """Mean absolute step of every series by a grouped pandas aggregate."""
    s = W.build(spark, sf_dir, "evu", 0.0)
    return s.groupBy("grp", "sid").agg(F.round(delta_udaf("idx", "val"), 9).alias("step"))


QUERIES["udaf_delta"] = (udaf_delta, f"WITH {W.sql('evu', 0.0)}, l AS (SELECT grp, sid, abs(val - lag(val) OVER (PARTITION BY grp, sid ORDER BY idx)) AS s FROM series) SELECT grp, sid, round(avg(s), 9) AS step FROM l GROUP BY 1, 2")


def udtf_align(spark, sf_dir):
    """SQL entry: align_series over a table argument, partitioned by group."""
    W.build(spark, sf_dir, "evu", 0.2).createOrReplaceTempView("_align_series")
    register_align_series(spark)
    return spark.sql(f"SELECT grp, x[0] AS i1, x[1] AS i2, x[2] AS i3, x[3] AS i4, w_fp FROM align_series(TABLE(SELECT grp, sid, idx, ts_us, val FROM _align_series) PARTITION BY (grp), 4, {P.theta}L, {P.beta}, 'greedy')")


QUERIES["udtf_align_series"] = (udtf_align, None)

for _name, (_f, _sql) in aggregates.QUERIES.items():
    QUERIES[_name] = (_f, _sql)
QUERIES["st_aligner"] = (lambda s, d: aligner.replay(s, W.build(s, d, "evu", 0.2), 4, P), None)


def udtf_candidates(spark, sf_dir):
    """SQL entry: the candidate tuples of a table argument, partitioned by group."""
    W.build(spark, sf_dir, "evu", 0.2).createOrReplaceTempView("_align_cells")
    register_candidates(spark)
    return spark.sql(f"SELECT grp, x[0] AS i1, x[1] AS i2, x[2] AS i3, x[3] AS i4, CAST(lam AS BIGINT) AS lam, spread_us FROM align_candidates(TABLE(SELECT grp, sid, idx, ts_us, val FROM _align_cells) PARTITION BY (grp), 4, {P.theta}L, {P.beta})")


QUERIES["udtf_candidates"] = (udtf_candidates, f"WITH {W.sql('evu', 0.2)},\n{C.sql(4, P)} SELECT grp, i1, i2, i3, i4, lam, spread_us FROM cand")


def cogroup_ends(spark, sf_dir):
    """Cells and tuples of each group in one task (cogroup over Arrow): how many cells no candidate of the group holds."""
    import pyarrow as pa
    import pyarrow.compute as pc

    s = W.build(spark, sf_dir, "evu", 0.2)
    held = C.candidates(s, 4, P).select("grp", F.posexplode("x").alias("j", "idx")).select("grp", (F.col("j") + 1).alias("sid"), "idx").distinct()

    def count(cells: pa.Table, used: pa.Table) -> pa.Table:
        return pa.table({"grp": [(cells if cells.num_rows else used)["grp"][0].as_py()], "cells": [pc.count(cells["idx"]).as_py()], "held": [used.num_rows]})

    return s.select("grp", "sid", "idx").groupBy("grp").cogroup(held.groupBy("grp")).applyInArrow(count, "grp string, cells long, held long")


QUERIES["cogroup_held"] = (cogroup_ends, f"WITH {W.sql('evu', 0.2)},\n{C.sql(4, P)}, u AS (SELECT grp, 1 AS s, i1 AS i FROM cand UNION SELECT grp, 2, i2 FROM cand UNION SELECT grp, 3, i3 FROM cand UNION SELECT grp, 4, i4 FROM cand), n AS (SELECT grp, count(*)::BIGINT AS held FROM u GROUP BY 1) SELECT c.grp, c.cells, coalesce(n.held, 0)::BIGINT AS held FROM (SELECT grp, count(*)::BIGINT AS cells FROM series GROUP BY 1) c LEFT JOIN n USING (grp)")
