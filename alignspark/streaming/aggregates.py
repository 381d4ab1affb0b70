"""Windowed aggregates over the event stream; each batch form has SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.operators.conflicts import shared_path

QUERIES: dict[str, tuple] = {}


def stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a file stream with event time."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    # a pattern, so that a table of one file and a table of many are both taken as a set of files
    raw = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]")
    return raw.withColumn("at", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a streaming frame over what is available; the last complete result, written to the shared folder."""
    spark = df.sparkSession
    top = shared_path(spark, "stream")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{top}/out")

    run = df.writeStream.outputMode(mode).option("checkpointLocation", f"{top}/state").trigger(availableNow=True).foreachBatch(keep).start()
    run.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{top}/out")


def tumbling(spark, sf_dir):
    e = stream(spark, sf_dir).withWatermark("at", "10 minutes")
    return drained(e.groupBy(F.window("at", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))).select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


def sliding(spark, sf_dir):
    e = stream(spark, sf_dir).withWatermark("at", "10 minutes")
    return drained(e.groupBy(F.window("at", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))).select(F.unix_micros("w.start").alias("start_us"), "n")


def session(spark, sf_dir):
    e = stream(spark, sf_dir).withWatermark("at", "10 minutes")
    got = drained(e.groupBy(F.session_window("at", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n")))
    return got.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def dedupe(spark, sf_dir):
    """Repeated deliveries dropped: every event is sent twice, each kept once."""
    e = stream(spark, sf_dir).withWatermark("at", "10 minutes")
    twice = e.select("event_id", "user_id", "at", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
    return drained(twice.dropDuplicates(["event_id", "at"]).select("event_id", "user_id"), "append")


def interval_join(spark, sf_dir):
    """Two channels as two streams: every click with the views of the same user in the six hours after it."""
    e = stream(spark, sf_dir)
    clicks = e.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("at").alias("ta")).withWatermark("ta", "1 day")
    views = stream(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("at").alias("tb")).withWatermark("tb", "1 day")
    met = clicks.join(views, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 6 HOURS"))
    return drained(met.select("a", "b"), "append")


DAY = 86_400_000_000
QUERIES["st_tumbling"] = (tumbling, f"SELECT (epoch_us(ts) // {DAY} * {DAY})::BIGINT AS start_us, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
QUERIES["st_sliding"] = (sliding, f"SELECT s AS start_us, count(*)::BIGINT AS n FROM (SELECT unnest([epoch_us(ts) // {DAY} * {DAY}, (epoch_us(ts) // {DAY} - 1) * {DAY}])::BIGINT AS s FROM events) GROUP BY 1")
QUERIES["st_session"] = (session, f"WITH g AS (SELECT user_id, epoch_us(ts) AS u, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < {DAY // 2} THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY u) AS k FROM g) SELECT user_id, min(u)::BIGINT AS start_us, count(*)::BIGINT AS n FROM s GROUP BY user_id, k")
QUERIES["st_join"] = (interval_join, f"SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view' AND epoch_us(b.ts) BETWEEN epoch_us(a.ts) AND epoch_us(a.ts) + {DAY // 4}")
QUERIES["st_dedupe"] = (dedupe, "SELECT event_id, user_id FROM events")
