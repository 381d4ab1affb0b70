"""The experiments: accuracy and tuple counts over data sets, rates, parameters and sizes, each as one frame.

All cells of a table that share a method run in one job: rates, grid points and
sizes are groups of one series table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.operators import baselines as B
from alignspark.operators import compose as K
from alignspark.operators import impute as I
from alignspark.operators import tuning as T
from alignspark.operators.conflicts import settled
from alignspark.params import AlignParams
from alignspark.sources import workloads as W

SETS, RATES, IMPUTERS = ("ev4", "li4", "or4", "ev11"), (0.1, 0.2, 0.3, 0.4), ("imp_lr", "imp_gbt")
SIZES = (1000, 2000, 3000, 4000, 5000, 6000)


def params(name: str, p: AlignParams) -> AlignParams:
    """The data set's own time threshold."""
    return p.with_(theta=W.theta_of(name))


def scored(aligned: DataFrame, rows: DataFrame, m: int, *keys: str) -> DataFrame:
    """(keys, n_aligned, precision, recall, f1) of results; ``rows`` (keys, n) has the true number of rows.

    Truth is that cells of one row belong together, so of a tuple's pairs those of equal row numbers count.
    """
    pairs = F.flatten(F.transform("x", lambda a, i: F.transform(F.slice("x", i + 2, F.greatest(F.lit(m - 1) - i, F.lit(0))), lambda b: (a == b).cast("int"))))
    got = aligned.select(*keys, F.aggregate(pairs, F.lit(0), lambda s, v: s + v).alias("both"))
    sums = got.groupBy(*keys).agg(F.count("*").alias("n_aligned"), F.sum("both").alias("both"))
    per = m * (m - 1) // 2
    f1 = 2 * F.col("both") / ((F.col("n_aligned") + F.col("n")) * per)
    return sums.join(rows, list(keys)).select(
        *keys, "n_aligned", F.round(F.col("both") / (F.col("n_aligned") * per), 6).alias("precision"), F.round(F.col("both") / (F.col("n") * per), 6).alias("recall"), F.round(f1, 6).alias("f1"))


def at_rates(spark: SparkSession, sf_dir: str, name: str, rates=RATES) -> DataFrame:
    """The series at every missing rate: the rate in percent leads the group's name."""
    out = None
    for rate in rates:
        one = W.build(spark, sf_dir, name, rate).withColumn("grp", F.concat(F.lit(f"{round(rate * 100)}@"), F.col("grp")))
        out = one if out is None else out.unionByName(one)
    return out


def _rate(df: DataFrame) -> DataFrame:
    return df.withColumn("rate", F.split("grp", "@")[0].cast("int"))


def true_rows(series: DataFrame, *keys: str) -> DataFrame:
    return series.where("sid = 1").groupBy(*keys).agg(F.count("*").alias("n"))


def ours(spark: SparkSession, sf_dir: str, name: str, p: AlignParams = AlignParams(), rates=RATES) -> DataFrame:
    """(method, rate, n_aligned, precision, recall, f1) of the two scan composers, the sequential matcher and the control."""
    s, m, p = at_rates(spark, sf_dir, name, rates), W.arity(name), params(name, p)
    rows = true_rows(_rate(s), "rate")
    runs = {"greedy": K.align(s, m, p, "greedy"), "expectation": K.align(s, m, p, "expectation"), "diagonal": B.align_diagonal(s, m, p.theta),
            "sequential": B.align_sequential(I.complete_for(s, m, "linear"), m, p)}
    out = None
    for method, aligned in runs.items():
        part = scored(_rate(aligned), rows, m, "rate").withColumn("method", F.lit(method))
        out = part if out is None else out.unionByName(part)
    return out


def warped(spark: SparkSession, sf_dir: str, name: str, rates=(0.2,), imputers=IMPUTERS) -> DataFrame:
    """(method, imputer, rate, n_aligned, precision, recall, f1) of the warping family after each imputer."""
    s, m = at_rates(spark, sf_dir, name, rates), W.arity(name)
    rows = true_rows(_rate(s), "rate")
    out = None
    for imputer in imputers:
        full = settled(I.complete_for(s, m, imputer), "filled")
        for method in B.WARPS:
            part = scored(_rate(B.warp(full, m, method)), rows, m, "rate").withColumns({"method": F.lit(method), "imputer": F.lit(imputer)})
            out = part if out is None else out.unionByName(part)
    return out


def grid(spark: SparkSession, sf_dir: str, name: str, points: list[AlignParams], method: str, rate: float = 0.2) -> DataFrame:
    """F1, tuples and weight of every grid point, from one composition job."""
    s, m = W.build(spark, sf_dir, name, rate), W.arity(name)
    made = T.compose_grid(s, m, points, method)
    point = spark.createDataFrame([(i, g.theta, g.beta, g.k1, g.k2) for i, g in enumerate(points)], "point int, theta long, beta int, k1 double, k2 double")
    rows = point.select("point", F.lit(s.where("sid = 1").count()).alias("n"))
    weight = made.groupBy("point").agg(F.sum("w_fp").alias("w_fp"))
    return scored(made, rows, m, "point").join(weight, "point").join(F.broadcast(point), "point").select("theta", "beta", "k1", "k2", "n_aligned", "w_fp", "f1")


def theta_grid(name: str, p: AlignParams = AlignParams(), betas=(1, 2, 3, 4)) -> list[AlignParams]:
    """Thresholds from a sixth of the clocks' jitter to a sixth beyond it, as 20 to 140 stand to 120."""
    return [p.with_(theta=W.jitter_of(name) * k // 6, beta=b) for k in range(1, 8) for b in betas]


def weight_grid(name: str, p: AlignParams = AlignParams()) -> list[AlignParams]:
    return [params(name, p).with_(k1=float(a), k2=float(b)) for a in range(1, 7) for b in range(1, 7)]


def sizes(spark: SparkSession, sf_dir: str, p: AlignParams = AlignParams(), rows=SIZES, rate: float = 0.2) -> DataFrame:
    """(method, size, n_aligned, precision, recall, f1) for the first rows of the event recording."""
    s = None
    for n in rows:
        one = W.build(spark, sf_dir, "ev4", rate, n=n).withColumn("grp", F.lit(str(n)))
        s = one if s is None else s.unionByName(one)
    size = lambda df: df.withColumn("size", F.col("grp").cast("int"))
    truth = true_rows(size(s), "size")
    out = None
    for method in ("greedy", "expectation"):
        part = scored(size(K.align(s, 4, p, method)), truth, 4, "size").withColumn("method", F.lit(method))
        out = part if out is None else out.unionByName(part)
    return out


def chosen_params(spark: SparkSession, sf_dir: str, name: str, rate: float = 0.2) -> DataFrame:
    """One row of the parameters that the data themselves suggest. With eleven series the loose set has beta 1: under
    4 the cells without a clock combine to millions of tuples."""
    got = T.auto_params(W.build(spark, sf_dir, name, rate), W.arity(name), beta_cap=4 if W.arity(name) <= 4 else 1)
    return spark.createDataFrame([(got.theta, got.beta, got.k1, got.k2, got.delta)], "theta long, beta int, k1 double, k2 double, delta double")
