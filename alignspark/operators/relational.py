"""Generic operators that users of the alignment methods need around them, with their SQL.

Each entry is (Spark function of a table reader, DuckDB SQL). Computed columns
carry the same names on both sides; doubles are rounded to six digits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from alignspark.operators.conflicts import settled
from alignspark.params import SECOND

OPS: dict[str, tuple] = {}


def op(name: str, sql: str | None):
    def add(f):
        OPS[name] = (f, sql)
        return f

    return add


def r6(c):
    return F.round(c, 6)


us = lambda c: F.unix_micros(F.col(c).cast("timestamp"))


# --- projection, filters, reshaping ------------------------------------------------------------------------------------


@op("src_parquet", "SELECT event_id, user_id, event_type FROM events")
def src_parquet(t) -> DataFrame:
    return t("events").select("event_id", "user_id", "event_type")


@op("op_project", "SELECT event_id, round(value * 2 + 1, 6) AS scaled, upper(event_type) AS kind, CASE WHEN value > 50 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band FROM events")
def op_project(t):
    return t("events").select("event_id", r6(F.col("value") * 2 + 1).alias("scaled"), F.upper("event_type").alias("kind"), F.when(F.col("value") > 50, "high").when(F.col("value") > 20, "mid").otherwise("low").alias("band"))


@op("op_filter", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderstatus IN ('F','O') AND o_orderpriority LIKE '%-%'")
def op_filter(t):
    return t("orders").where(F.col("o_totalprice").between(1000, 50000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("%-%")).select("o_orderkey", "o_totalprice")


@op("op_null_pred", "SELECT count(*) FILTER (v IS NULL)::BIGINT AS n_null, count(v)::BIGINT AS n_present, count(*) FILTER (v IS NOT DISTINCT FROM NULL)::BIGINT AS n_safe FROM (SELECT nullif(user_id % 7, 0) AS v FROM events)")
def op_null_pred(t):
    v = t("events").select(F.nullif(F.col("user_id") % 7, F.lit(0)).alias("v"))
    return v.agg(F.count(F.when(F.col("v").isNull(), 1)).alias("n_null"), F.count("v").alias("n_present"), F.count(F.when(F.col("v").eqNullSafe(F.lit(None)), 1)).alias("n_safe"))


@op("op_melt", "SELECT o_orderkey, name, round(v, 6) AS v FROM (SELECT o_orderkey, o_totalprice AS price, o_custkey::DOUBLE AS cust FROM orders) UNPIVOT (v FOR name IN (price, cust))")
def op_melt(t):
    return t("orders").select("o_orderkey", F.col("o_totalprice").alias("price"), F.col("o_custkey").cast("double").alias("cust")).unpivot("o_orderkey", ["price", "cust"], "name", "v").withColumn("v", r6("v"))


@op("op_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}')::BIGINT AS n_{k}" for k in ("click", "view", "purchase")) + " FROM events GROUP BY 1")
def op_pivot(t):
    kinds = ["click", "view", "purchase"]
    p = t("events").groupBy("user_id").pivot("event_type", kinds).count()
    return p.select("user_id", *[F.coalesce(F.col(k), F.lit(0)).alias(f"n_{k}") for k in kinds])


@op("op_index", "SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)::BIGINT AS idx FROM events")
def op_index(t):
    return t("events").select("user_id", "event_id", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long").alias("idx"))


@op("op_resample", """WITH h AS (SELECT epoch_us(ts) // 86400000000 AS day, sum(value) AS v FROM events GROUP BY 1), g AS (SELECT unnest(range((SELECT min(day) FROM h), (SELECT max(day) + 1 FROM h))) AS day)
SELECT g.day::BIGINT AS day, round(coalesce(h.v, 0), 4) AS v FROM g LEFT JOIN h USING (day)""")
def op_resample(t):
    h = t("events").groupBy(F.floor(us("ts") / 86_400_000_000).alias("day")).agg(F.sum("value").alias("v"))
    grid = h.agg(F.min("day").alias("a"), F.max("day").alias("b")).select(F.explode(F.sequence("a", "b")).alias("day"))
    return grid.join(h, "day", "left").select("day", F.round(F.coalesce("v", F.lit(0.0)), 4).alias("v"))


@op("op_gaps", "SELECT user_id, event_id, (epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id))::BIGINT AS gap_us FROM events QUALIFY gap_us > 36000000000")
def op_gaps(t):
    e = t("events").withColumn("u", us("ts"))
    return e.select("user_id", "event_id", (F.col("u") - F.lag("u").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).alias("gap_us")).where("gap_us > 36000000000")


# --- joins -------------------------------------------------------------------------------------------------------------


@op("join_inner", "SELECT o_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 6) AS net FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F'")
def join_inner(t):
    return t("orders").where("o_orderstatus = 'F'").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", r6(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net"))


@op("join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(t):
    # nation and region have 25 and 5 rows at every scale
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@op("join_left", "SELECT c_custkey, count(o_orderkey)::BIGINT AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@op("join_full", "SELECT coalesce(a.k, b.k) AS k, a.n AS n_a, b.n AS n_b FROM (SELECT user_id AS k, count(*)::BIGINT AS n FROM events GROUP BY 1) a FULL JOIN (SELECT c_custkey AS k, count(*)::BIGINT AS n FROM customer GROUP BY 1) b ON a.k = b.k")
def join_full(t):
    a = t("events").groupBy(F.col("user_id").alias("k")).agg(F.count("*").alias("n_a"))
    b = t("customer").groupBy(F.col("c_custkey").alias("k")).agg(F.count("*").alias("n_b"))
    return a.join(b, "k", "full")


@op("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000)")
def join_semi(t):
    return t("customer").join(t("orders").where("o_totalprice > 100000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@op("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@op("join_self", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id > a.event_id AND b.event_id <= a.event_id + 200 ")
def join_self(t):
    e = t("events")
    return e.alias("a").join(e.alias("b"), (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.event_id") > F.col("a.event_id")) & (F.col("b.event_id") <= F.col("a.event_id") + 200)).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


@op("join_theta", "SELECT r_regionkey, n_nationkey FROM region JOIN nation ON n_nationkey > r_regionkey * 5")
def join_theta(t):
    return t("nation").join(F.broadcast(t("region")), F.col("n_nationkey") > F.col("r_regionkey") * 5).select("r_regionkey", "n_nationkey")


BAND = 60 * SECOND


@op("join_band", f"SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON abs(epoch_us(a.ts) - epoch_us(b.ts)) <= {BAND} AND a.event_id < b.event_id")
def join_band(t):
    """Clock buckets of the band's width: each left row looks into three of them."""
    e = t("events").select("event_id", us("ts").alias("u"))
    left = e.select(F.col("event_id").alias("a"), F.col("u").alias("ua"), F.explode(F.array(*[F.floor(F.col("u") / BAND) + k for k in (-1, 0, 1)])).alias("bk"))
    right = e.select(F.col("event_id").alias("b"), F.col("u").alias("ub"), F.floor(F.col("u") / BAND).alias("bk"))
    return left.join(right, "bk").where((F.abs(F.col("ua") - F.col("ub")) <= BAND) & (F.col("a") < F.col("b"))).select("a", "b")


DAY = 86_400 * SECOND


@op("join_interval", f"SELECT o_orderkey, event_id FROM orders JOIN events ON epoch_us(ts) >= epoch_us(o_orderdate) AND epoch_us(ts) < epoch_us(o_orderdate) + {DAY} WHERE o_custkey = user_id")
def join_interval(t):
    e = t("events").select("event_id", "user_id", us("ts").alias("u"))
    e = e.withColumn("bk", F.floor(F.col("u") / DAY))
    o = t("orders").select("o_orderkey", "o_custkey", us("o_orderdate").alias("d"))
    o = o.withColumn("bk", F.explode(F.array(F.floor(F.col("d") / DAY), F.floor(F.col("d") / DAY) + 1)))
    return o.join(e, (o["bk"] == e["bk"]) & (F.col("o_custkey") == F.col("user_id"))).where((F.col("u") >= F.col("d")) & (F.col("u") < F.col("d") + DAY)).select("o_orderkey", "event_id").distinct()


@op("join_asof", "SELECT a.event_id AS a, b.event_id AS b FROM (SELECT * FROM events WHERE event_type = 'click') a ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts >= b.ts")
def join_asof(t):
    """Union of both sides and the last right row seen: one shuffle by key, no inequality join."""
    e = t("events").where("event_type IN ('click', 'view')").select("user_id", "ts", "event_id", (F.col("event_type") == "view").cast("int").alias("side"))
    right = F.when(F.col("side") == 1, F.col("event_id"))
    order = Window.partitionBy("user_id").orderBy("ts", F.col("side").desc()).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("b", F.last(right, ignorenulls=True).over(order)).where("side = 0 AND b IS NOT NULL").select(F.col("event_id").alias("a"), "b")


@op("join_nearest", "SELECT a, b FROM (SELECT a.event_id AS a, b.event_id AS b, row_number() OVER (PARTITION BY a.event_id ORDER BY abs(epoch_us(a.ts) - epoch_us(b.ts)), b.event_id) AS r FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view') WHERE r = 1")
def join_nearest(t):
    """Last row before and first row after by windows, then the closer one."""
    e = t("events").where("event_type IN ('click', 'view')").select("user_id", us("ts").alias("u"), "event_id", (F.col("event_type") == "view").cast("int").alias("side"))
    right = F.when(F.col("side") == 1, F.struct("u", "event_id"))
    order = Window.partitionBy("user_id").orderBy("u")
    both = e.withColumns({"p": F.last(right, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)), "n": F.first(right, ignorenulls=True).over(order.rowsBetween(0, Window.unboundedFollowing))})
    gap = lambda c: F.abs(F.col("u") - F.col(c)["u"])
    pick = F.when(F.col("p").isNull(), F.col("n")).when(F.col("n").isNull(), F.col("p")).when(F.struct(gap("p"), F.col("p.event_id")) <= F.struct(gap("n"), F.col("n.event_id")), F.col("p")).otherwise(F.col("n"))
    return both.where("side = 0").select(F.col("event_id").alias("a"), pick["event_id"].alias("b")).where("b IS NOT NULL")


# --- aggregation -------------------------------------------------------------------------------------------------------


@op("agg_basic", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, round(avg(l_discount), 6) AS avg_disc, count(*)::BIGINT AS n, min(l_tax) AS min_tax, max(l_extendedprice) AS max_price FROM lineitem GROUP BY 1, 2")
def agg_basic(t):
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), r6(F.avg("l_discount")).alias("avg_disc"), F.count("*").alias("n"), F.min("l_tax").alias("min_tax"), F.max("l_extendedprice").alias("max_price"))


@op("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey)::BIGINT AS n_cust, count(DISTINCT o_orderpriority)::BIGINT AS n_prio FROM orders GROUP BY 1")
def agg_distinct(t):
    return t("orders").groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("n_cust"), F.countDistinct("o_orderpriority").alias("n_prio"))


@op("agg_approx", None)
def agg_approx(t):
    return t("orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey").alias("n_cust"))


@op("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.95), 6) AS p95 FROM events GROUP BY 1")
def agg_percentile(t):
    return t("events").groupBy("event_type").agg(r6(F.percentile("value", F.lit(0.5))).alias("p50"), r6(F.percentile("value", F.lit(0.95))).alias("p95"))


@op("agg_regr", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem GROUP BY 1")
def agg_regr(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), r6(F.corr("l_extendedprice", "l_quantity")).alias("r"))


@op("agg_argmax", "SELECT user_id, arg_max(event_id, (value, event_id)) AS top, arg_min(event_id, (value, event_id)) AS low FROM events GROUP BY 1")
def agg_argmax(t):
    key = F.struct("value", "event_id")
    return t("events").groupBy("user_id").agg(F.max_by("event_id", key).alias("top"), F.min_by("event_id", key).alias("low"))


@op("agg_gsets", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def agg_gsets(t):
    t("lineitem").createOrReplaceTempView("_align_lineitem")
    return t("lineitem").sparkSession.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM _align_lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


@op("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(t):
    return t("orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@op("agg_rollup", "SELECT n_regionkey, n_name, count(*)::BIGINT AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_name)")
def agg_rollup(t):
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "n_name").agg(F.count("*").alias("n"))


@op("agg_collect", "SELECT user_id, string_agg(event_id::VARCHAR, ',' ORDER BY event_id) AS ids FROM events GROUP BY 1")
def agg_collect(t):
    return t("events").groupBy("user_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list("event_id")), lambda x: x.cast("string")), ",").alias("ids"))


@op("agg_filter", "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F')::BIGINT AS n_f, round(coalesce(sum(o_totalprice) FILTER (o_totalprice > 1000), 0), 2) AS big FROM orders GROUP BY 1")
def agg_filter(t):
    return t("orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("n_f"), F.round(F.coalesce(F.sum(F.when(F.col("o_totalprice") > 1000, F.col("o_totalprice"))), F.lit(0.0)), 2).alias("big"))


@op("agg_hist", "SELECT floor(value / 10)::BIGINT AS bin, count(*)::BIGINT AS n FROM events GROUP BY 1")
def agg_hist(t):
    return t("events").groupBy(F.floor(F.col("value") / 10).alias("bin")).agg(F.count("*").alias("n"))


# --- windows -------------------------------------------------------------------------------------------------------------

def by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@op("win_rank", "SELECT event_id, row_number() OVER w::BIGINT AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type)::BIGINT AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type)::BIGINT AS dr, ntile(4) OVER w::BIGINT AS nt FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_rank(t):
    k = Window.partitionBy("user_id").orderBy("event_type")
    return t("events").select("event_id", *[f.over(w).cast("long").alias(n) for f, w, n in ((F.row_number(), by_user(), "rn"), (F.rank(), k, "rk"), (F.dense_rank(), k, "dr"), (F.ntile(4), by_user(), "nt"))])


@op("win_analytic", "SELECT event_id, lag(value) OVER w AS prev, lead(value, 2) OVER w AS next2, first_value(event_id) OVER w AS f, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_analytic(t):
    return t("events").select("event_id", F.lag("value").over(by_user()).alias("prev"), F.lead("value", 2).over(by_user()).alias("next2"), F.first("event_id").over(by_user()).alias("f"), F.nth_value("event_id", 2).over(by_user()).alias("second"))


@op("win_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS ma FROM events")
def win_rows(t):
    return t("events").select("event_id", r6(F.avg("value").over(by_user().rowsBetween(-3, 0))).alias("ma"))


@op("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def win_range(t):
    return t("events").withColumn("u", us("ts")).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("u").rangeBetween(-86_400_000_000, 0)).alias("n"))


@op("win_running_max", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS top FROM events")
def win_running_max(t):
    return t("events").select("event_id", F.max("value").over(by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("top"))


@op("win_islands", """WITH g AS (SELECT user_id, event_id, event_type, CASE WHEN event_type IS DISTINCT FROM lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) THEN 1 ELSE 0 END AS new, ts FROM events),
i AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS island FROM g) SELECT user_id, island::BIGINT AS island, count(*)::BIGINT AS n, min(event_id) AS first_id FROM i GROUP BY 1, 2""")
def win_islands(t):
    new = F.when(~F.col("event_type").eqNullSafe(F.lag("event_type").over(by_user())), 1).otherwise(0)
    return t("events").withColumn("new", new).withColumn("island", F.sum("new").over(by_user())).groupBy("user_id", "island").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"))


@op("win_fill", "SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS filled FROM events")
def win_fill(t):
    return t("events").select("event_id", F.last(F.when(F.col("event_type") == "click", F.col("value")), ignorenulls=True).over(by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("filled"))


# --- order, limits, rows, sets ---------------------------------------------------------------------------------------------


def positions(df, *order):
    """Rows of a total order with their position: ranges are sorted apart, and sums of their sizes number them on."""
    local = settled(df.orderBy(*order).withColumns({"_part": F.spark_partition_id(), "_at": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))}), "sorted")
    sizes = sorted((r[0], r[1]) for r in local.groupBy("_part").count().collect())
    starts, total = {}, 0
    for part, n in sizes:
        starts[part], total = total, total + n
    base = F.create_map(*[F.lit(v) for pair in starts.items() for v in pair]) if starts else F.create_map(F.lit(0), F.lit(0))
    return local.withColumn("pos", (base[F.col("_part")] + F.col("_at") + 1).cast("long")).drop("_part", "_at")


@op("sort_multi", "SELECT row_number() OVER (ORDER BY o_orderpriority DESC, o_totalprice, o_orderkey)::BIGINT AS pos, o_orderkey FROM orders")
def sort_multi(t):
    return positions(t("orders").select("o_orderkey", "o_orderpriority", "o_totalprice"), F.desc("o_orderpriority"), "o_totalprice", "o_orderkey").select("pos", "o_orderkey")


@op("sort_nulls", "SELECT row_number() OVER (ORDER BY v NULLS LAST, event_id)::BIGINT AS pos, event_id, v FROM (SELECT event_id, nullif(user_id % 5, 0) AS v FROM events)")
def sort_nulls(t):
    e = t("events").select("event_id", F.nullif(F.col("user_id") % 5, F.lit(0)).alias("v"))
    return positions(e, F.asc_nulls_last("v"), "event_id").select("pos", "event_id", "v")


@op("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 25")
def limit_offset(t):
    return t("orders").select("o_orderkey").orderBy("o_orderkey").offset(25).limit(50)


@op("topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_group(t):
    return t("orders").withColumn("r", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 3").select("o_custkey", "o_orderkey")


@op("distinct_rows", "SELECT DISTINCT user_id, event_type FROM events")
def distinct_rows(t):
    return t("events").select("user_id", "event_type").distinct()


@op("drop_dups", "SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) = 1")
def drop_dups(t):
    return t("events").groupBy("user_id").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


@op("sample_hash", "SELECT event_id FROM events WHERE ('0x' || substr(md5(event_id::VARCHAR), 1, 8))::BIGINT < 429496730")
def sample_hash(t):
    return t("events").where(F.conv(F.substring(F.md5(F.col("event_id").cast("string")), 1, 8), 16, 10).cast("long") < 429496730).select("event_id")


@op("union_all", "SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region UNION ALL SELECT n_name FROM nation")
def union_all(t):
    n, r = t("nation").select(F.col("n_name").alias("name")), t("region").select(F.col("r_name").alias("name"))
    return n.union(r).union(n)


@op("union_distinct", "SELECT user_id AS k FROM events UNION SELECT c_custkey FROM customer")
def union_distinct(t):
    return t("events").select(F.col("user_id").alias("k")).union(t("customer").select("c_custkey")).distinct()


@op("intersect", "SELECT user_id AS k FROM events INTERSECT SELECT c_custkey FROM customer")
def intersect(t):
    return t("events").select(F.col("user_id").alias("k")).intersect(t("customer").select("c_custkey"))


@op("except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT user_id FROM events")
def except_(t):
    return t("customer").select(F.col("c_custkey").alias("k")).subtract(t("events").select("user_id"))


@op("except_all", "SELECT o_custkey AS k FROM orders EXCEPT ALL SELECT c_custkey FROM customer")
def except_all(t):
    return t("orders").select(F.col("o_custkey").alias("k")).exceptAll(t("customer").select("c_custkey"))


@op("union_by_name", "SELECT n_nationkey AS k, n_name AS name, NULL::INT AS region FROM nation UNION ALL BY NAME SELECT r_name AS name, r_regionkey AS k, r_regionkey AS region FROM region")
def union_by_name(t):
    n = t("nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name"))
    r = t("region").select(F.col("r_name").alias("name"), F.col("r_regionkey").alias("k"), F.col("r_regionkey").alias("region"))
    return n.unionByName(r, allowMissingColumns=True)


# --- functions -------------------------------------------------------------------------------------------------------------


@op("fn_string", r"""SELECT p_partkey, upper(p_name) AS up, substr(p_name, 1, 4) AS head, length(p_brand)::BIGINT AS len, md5(p_name) AS digest, concat_ws('-', p_brand, p_type) AS joined,
 regexp_extract(p_brand, '([0-9]+)', 1) AS num, regexp_replace(p_type, '[AEIOU]', '*', 'g') AS masked, split_part(p_type, ' ', 1) AS first_word, levenshtein(p_brand, p_type)::BIGINT AS dist FROM part""")
def fn_string(t):
    return t("part").select(
        "p_partkey", F.upper("p_name").alias("up"), F.substring("p_name", 1, 4).alias("head"), F.length("p_brand").cast("long").alias("len"), F.md5("p_name").alias("digest"),
        F.concat_ws("-", "p_brand", "p_type").alias("joined"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("num"), F.regexp_replace("p_type", "[AEIOU]", "*").alias("masked"),
        F.split_part("p_type", F.lit(" "), F.lit(1)).alias("first_word"), F.levenshtein("p_brand", "p_type").cast("long").alias("dist"))


@op("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, year(o_orderdate)::BIGINT AS y, dayofyear(o_orderdate)::BIGINT AS doy, epoch_us(o_orderdate) AS micros, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::BIGINT AS days FROM orders")
def fn_date(t):
    d = F.col("o_orderdate")
    return t("orders").select("o_orderkey", F.date_trunc("month", d).cast("date").alias("month"), F.year(d).cast("long").alias("y"), F.dayofyear(d).cast("long").alias("doy"), us("o_orderdate").alias("micros"), F.date_diff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@op("fn_math", "SELECT l_orderkey, l_linenumber, abs(l_quantity - 25) AS a, greatest(l_quantity, l_tax * 100, 10) AS g, least(l_quantity, 10) AS l, floor(l_extendedprice / 7)::BIGINT AS f, ceil(l_extendedprice / 7)::BIGINT AS c, round(sqrt(l_quantity), 6) AS s, round(power(l_discount + 1, 3), 6) AS p, (l_partkey & 255) AS b, (l_partkey >> 2) AS sh, xor(l_partkey, 77) AS x FROM lineitem")
def fn_math(t):
    q = F.col("l_quantity")
    return t("lineitem").select("l_orderkey", "l_linenumber", F.abs(q - 25).alias("a"), F.greatest(q, F.col("l_tax") * 100, F.lit(10.0)).alias("g"), F.least(q, F.lit(10.0)).alias("l"), F.floor(F.col("l_extendedprice") / 7).alias("f"), F.ceil(F.col("l_extendedprice") / 7).alias("c"), r6(F.sqrt(q)).alias("s"), r6(F.pow(F.col("l_discount") + 1, 3)).alias("p"), F.col("l_partkey").bitwiseAND(255).alias("b"), F.shiftright("l_partkey", 2).alias("sh"), F.col("l_partkey").bitwiseXOR(77).alias("x"))


@op("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 3) AS norm2, round(list_max(embedding)::DOUBLE, 5) AS top, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS n_pos, round(list_sort(embedding)[1]::DOUBLE, 5) AS low FROM embeddings")
def fn_array(t):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return t("embeddings").select("vec_id", F.round(F.aggregate(F.transform(e, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 3).alias("norm2"), F.round(F.array_max(e), 5).alias("top"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("n_pos"), F.round(F.array_sort(e)[0], 5).alias("low"))


@op("fn_map", "SELECT event_id, event_type AS k, value AS v, 2::BIGINT AS n FROM events WHERE value > 10")
def fn_map(t):
    m = F.map_from_arrays(F.array("event_type", F.lit("other")), F.array("value", F.lit(0.0)))
    e = t("events").where("value > 10").select("event_id", "event_type", m.alias("m"))
    return e.select("event_id", F.map_keys(F.map_filter("m", lambda k, v: v > 10))[0].alias("k"), F.element_at("m", F.col("event_type")).alias("v"), F.size("m").cast("long").alias("n"))


@op("fn_json", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, json_extract_string(props, '$.k') AS txt FROM events")
def fn_json(t):
    return t("events").select("event_id", F.from_json("props", "k int")["k"].cast("long").alias("k"), F.get_json_object("props", "$.k").alias("txt"))


@op("sql_subquery", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity > 40)")
def sql_subquery(t):
    for name in ("orders", "customer", "lineitem"):
        t(name).createOrReplaceTempView(f"_align_{name}")
    return t("orders").sparkSession.sql("SELECT o_orderkey FROM _align_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM _align_orders) AND o_custkey IN (SELECT c_custkey FROM _align_customer WHERE c_acctbal > 0) AND EXISTS (SELECT 1 FROM _align_lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity > 40)")


@op("sql_cte", "WITH t AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY 1), m AS (SELECT max(s) AS top FROM t) SELECT o_custkey, round(s, 2) AS s FROM t, m WHERE s > 0.9 * top")
def sql_cte(t):
    t("orders").createOrReplaceTempView("_align_orders")
    return t("orders").sparkSession.sql("WITH t AS (SELECT o_custkey, sum(o_totalprice) AS s FROM _align_orders GROUP BY 1) SELECT o_custkey, round(s, 2) AS s FROM t WHERE s > 0.9 * (SELECT max(s) FROM t)")
