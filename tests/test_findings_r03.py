"""One small test for each finding of round 3 that changed code."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from alignspark.operators import candidates as C
from alignspark.operators import compose as K
from alignspark.operators.candidates import expand_block, numpy_weights
from alignspark.params import SECOND, AlignParams
from alignspark.sources import workloads as W

P = AlignParams()


def rows_of(df):
    return sorted((tuple(tuple(v) if isinstance(v, list) else v for v in r) for r in df.collect()), key=repr)


def made(rng, groups=40, m=3, beta=1, most=5):
    """Candidates of many small groups side by side: x, weights, spreads, first and end of each group that has any."""
    x, w, spread, sizes = [], [], [], []
    for _ in range(groups):
        rows = int(rng.integers(1, most))
        times = (40 * np.arange(rows)[:, None] + rng.integers(0, 30, (rows, m))) * float(SECOND)
        times[rng.random(times.shape) < 0.4] = np.nan
        has = (rng.random(times.shape) < 0.5).astype(np.int8)
        has[rng.random(times.shape) < 0.1] = -1
        got, lam, s = expand_block(times, has, m, 60 * SECOND, beta, 1, rows)
        x.append(got), w.append(numpy_weights(got, lam, P)[2]), spread.append(s), sizes.append(len(got))
    ends = np.cumsum([n for n in sizes if n])
    return np.concatenate(x), np.concatenate(w), np.concatenate(spread), np.append(0, ends[:-1]), ends


def together(method, p, parts):
    x, w, spread, starts, ends = parts
    one = [lo + k for lo, hi in zip(starts, ends) for k in sorted(K.solve(x[lo:hi], w[lo:hi], p, method, spread[lo:hi]))]
    assert K.solve_many(x, w, starts, p, method, spread).tolist() == one


def test_exact_ties():
    """of equal weights the subset of smaller bit mask, as the SQL has it, in one segment and in many together."""
    x = np.array([[1, 2, 1], [1, 2, 2], [2, 1, 1], [2, 1, 2], [2, 2, 2]])
    w = np.array([8, 2, 8, 2, 10]) * 10**8
    assert K.free_subsets(x, w)[0] == sorted(K.exact_bnb(x, w)) == K.solve_many(x, w, np.array([0]), P, "exact", w).tolist() == [1, 2]


@pytest.mark.parametrize("beta", [0, 1, 2])
def test_exact_of_many_groups(beta):
    """segments searched together get what one after another gets, and what all subsets give."""
    parts = made(np.random.default_rng(beta), beta=beta)
    together("exact", P, parts)
    x, w, spread, starts, ends = parts
    got = K.solve_many(x, w, starts, P, "exact", spread)
    for lo, hi in zip(starts, ends):
        if hi - lo <= 12:
            assert (got[(got >= lo) & (got < hi)] - lo).tolist() == K.free_subsets(x[lo:hi], w[lo:hi])[0]


def test_exact_tiny_has_no_call_a_group(spark):
    """groups pass in tables of many, and are shuffled once, as users' rows."""
    from alignspark import queries as Q

    plan = Q.QUERIES["exact_tiny"][0](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "FlatMapGroupsInPandas" not in plan and plan.count("Exchange") == 1


def test_align_cuts_tables_at_groups(spark):
    """groups cut into steps, with numbers that begin late, gaps and a null name, align as from the JVM's candidates."""
    rng = np.random.default_rng(9)
    rows = []
    for g in range(30):
        for s in (1, 2, 3):
            for i in range(int(rng.integers(1, 40)), 44):
                if rng.random() < 0.8:
                    t = None if rng.random() < 0.2 else int((40 * i + rng.integers(0, 30)) * SECOND)
                    rows.append((None if g == 7 else f"g{g}", s, i, t, None if rng.random() < 0.2 else 1.0))
    series = spark.createDataFrame(rows, W.SERIES)
    cand = C.candidates(series, 3, P, "lead").persist()
    for method in ("greedy", "expectation", "packing_init"):
        got = K.align(series, 3, P.with_(cap=700), method)  # some groups a step, and none beyond the cap
        assert rows_of(got) == rows_of(K.compose(cand, 3, P, method))


@pytest.mark.parametrize("n,rate", [(2, 0.2), (4, 0.0)])
def test_windows_are_the_cells_of_build(spark, tmp_path, n, rate):
    """cells made row by row are those of ``build``, also of users over several batches, without names, times, values."""
    start = dt.datetime(2024, 1, 1)
    rng = np.random.default_rng(4)
    rows = [(i, None if rng.random() < 0.1 else start + dt.timedelta(seconds=9 * i), (None, 1, 2, 3)[int(rng.integers(0, 4))], "a",
             None if rng.random() < 0.1 else float("nan") if rng.random() < 0.1 else float(rng.normal()), None if rng.random() < 0.1 else '{"k": %d}' % i) for i in range(900)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, event_type string, value double, props string").write.parquet(str(tmp_path / "events.parquet"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 100)
    try:
        place = F.col("idx") - 1
        want = W.build(spark, str(tmp_path), "evu", rate).where("sid <= 3").select(F.concat_ws("#", "grp", F.floor(place / n)).alias("grp"), "sid", (place % n + 1).alias("idx"), "ts_us", "val")
        got = W.windows(spark, str(tmp_path), n, rate)
        assert got.schema.simpleString() == want.schema.simpleString() and repr(rows_of(got)) == repr(rows_of(want))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_rounded_as_spark(spark):
    """values rounded in numpy are Spark's, at halves, near them, beyond whole millionths and not finite."""
    rng = np.random.default_rng(8)
    halves = (rng.integers(-(10**9), 10**9, 300) * 10 + 5) / 1e7
    v = np.concatenate([halves, np.nextafter(halves, 0), np.nextafter(halves, 1e9), rng.normal(size=300) * 10.0 ** rng.integers(-9, 22, 300), [0.0, -0.0, -1e-9, np.nan, np.inf, -np.inf]])
    want = [r[0] for r in spark.createDataFrame([(k, float(x)) for k, x in enumerate(v)], "k int, v double").orderBy("k").select(F.round("v", 6)).collect()]
    assert [repr(x) for x in W.rounded(v).tolist()] == [repr(x) for x in want]


@pytest.mark.parametrize("literal", [False, True])
def test_greedy_of_many_groups(literal):
    """greedy folds of small groups in steps of many give what one fold after another gives."""
    for beta in (0, 1, 2):
        together("greedy", P.with_(literal=literal), made(np.random.default_rng(beta + 10), beta=beta))
        together("greedy", P.with_(tie="hash", literal=literal), made(np.random.default_rng(beta + 20), beta=beta, groups=9))


def test_ratio_tiny_has_no_call_a_group(spark):
    """both results are made in tables of many groups."""
    from alignspark import queries as Q

    plan = Q.QUERIES["ratio_tiny"][0](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "FlatMapGroupsInPandas" not in plan
