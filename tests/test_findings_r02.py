"""One small test for each finding of round 2 that changed code."""

import numpy as np
import pytest

from alignspark.operators import candidates as C
from alignspark.operators import conflicts as X
from alignspark.params import SECOND, AlignParams

P = AlignParams()


def long_series(spark, n=90, m=3, seed=5, gaps=0.3, groups=2):
    rng = np.random.default_rng(seed)
    rows = []
    for g in range(groups):
        for s in range(1, m + 1):
            for i in range(1, n + 1):
                t = None if rng.random() < gaps else int((40 * i + rng.integers(0, 30)) * SECOND)
                v = None if rng.random() < gaps else float(rng.normal())
                rows.append((f"g{g}", s, i, t, v))
    return spark.createDataFrame(rows, "grp string, sid int, idx long, ts_us long, val double")


def rows_of(df):
    return sorted(tuple(tuple(v) if isinstance(v, list) else v for v in r) for r in df.collect())


@pytest.mark.parametrize("beta", [1, 2])
def test_conflicts_by_blocks(spark, beta):
    """Blocks of seven leads give the edges, degrees, counts and components of the whole."""
    p = P.with_(beta=beta)
    s = long_series(spark)
    cand = C.candidates(s, 3, p)
    edges = X.conflict_edges(cand)
    assert rows_of(X.edges_of(s, 3, p, 7)) == rows_of(edges)
    assert rows_of(X.degree_of(s, 3, p, 7)) == rows_of(X.conflict_degree(cand).select("grp", "x", "degree"))
    counts = {r.grp: (r.n, r.edges, r.beyond) for r in X.counts_of(s, 3, p, 7).collect()}
    n, e = ({r[0]: r[1] for r in df.groupBy("grp").count().collect()} for df in (cand, edges))
    assert counts == {g: (n[g], e[g], 0) for g in n}
    whole = X.components(edges).groupBy("grp", "root").count()
    assert rows_of(X.component_sizes_of(s, 3, p, 7)) == rows_of(whole)


def test_conflict_queries_shuffle_no_candidates(spark):
    """The plans end in the blocks' task; no join follows the candidates."""
    s = long_series(spark, n=10)
    for df in (X.edges_of(s, 3, P), X.degree_of(s, 3, P)):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("FlatMapGroupsInPandas") == 1 and "Join" not in plan


def test_many_models_equal_single_ones():
    """Variables fitted together get what the full recursion of one series gives."""
    from alignspark.operators.marss import Marss, fit_many

    rng = np.random.default_rng(3)
    ys = [rng.normal(size=(n, 2)).cumsum(axis=0) for n in (0, 1, 2, 3, 9, 40)]
    for y in ys:
        y[rng.random(y.shape) < 0.2] = np.nan
    for y, model in zip(ys, fit_many(ys, 2, 5, cells=60)):
        if not len(y):
            assert model.predict().shape == (0, 2)
            continue
        # the matrix recursions from the learned parameters are the reference for both passes
        ref = Marss(2, 5, "full")
        ref._prepare(y)
        ref.B, ref.u, ref.Q, ref.R, ref.x0, ref.V0 = model.B, model.u, model.Q, model.R, model.x0, model.V0
        assert abs(ref._filter() - model.loglik[-1]) < 1e-8
        ref._smooth()
        assert np.allclose(ref.xp, model.xp) and np.allclose(ref.xs, model.xs)
        alone = Marss(2, 5).fit(y)
        assert np.allclose(alone.predict("smoothed"), model.predict("smoothed"), atol=1e-9)


def test_weights_leave_the_task_as_errors(spark):
    """the grid's errors are those of the results, and no join follows."""
    from alignspark.operators import compose as K
    from alignspark.operators import consistency as S
    from alignspark.operators import tuning as T

    s = long_series(spark, n=30)
    for model in ("locf", "marss"):
        made = T.fit_weights(s, 3, P, range(1, 3), range(1, 3), model=model)
        for r in made.collect():
            q = P.with_(k1=r.k1, k2=r.k2, b=1.0, c=1.0)
            want = [x.delta for x in S.delta(K.align(s, 3, q, "greedy"), s, 3, model).collect()]
            assert abs(r.delta - np.mean(want)) < 1e-9
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1 and "broadcast" in plan


@pytest.mark.parametrize("beta", [1, 3])
def test_odometer_scans_blocks(spark, beta):
    """blocks of leads give the candidates of the whole; the scan is not one task a group."""
    p = P.with_(beta=beta)
    s = long_series(spark, groups=1)
    made = C.odometer(s, 3, p, 11)
    assert rows_of(made.drop("w")) == rows_of(C.lead(s, 3, p).drop("w"))
    assert "blk" in made._jdf.queryExecution().optimizedPlan().toString()


def test_counts_and_distances_in_the_task(spark):
    """counted by block, equal to the counts of the candidate table; no candidate leaves a task."""
    from pyspark.sql import functions as F

    from alignspark.operators import tuning as T

    s = long_series(spark, groups=2)
    thetas, betas = [30 * SECOND, 90 * SECOND], [1, 2]
    cand = C.lead(s, 3, P.with_(theta=thetas[-1], beta=2)).cache()
    made = T.sweep_counts(s, 3, thetas, betas, P)
    assert rows_of(made) == [(t, b, cand.where((F.col("spread_us") <= t) & (F.col("phi") <= b)).count()) for t in thetas for b in betas]
    assert "w_fp" not in made._jdf.queryExecution().optimizedPlan().toString()
    want = T.row_distances(C.lead(s, 3, P.with_(beta=4))).agg(F.percentile("dist", F.lit(0.8))).first()[0]
    assert T.fit_beta(s, 3, P) == max(1, int(np.ceil(want)))


def test_interpolation_takes_one_pass(spark):
    """no frame that runs to the end of the series (its cost is the square of the length)."""
    from alignspark.operators import impute as I

    done = I.interpolate(long_series(spark, n=9, groups=1), "val")
    assert "UnboundedFollowing" not in done._jdf.queryExecution().optimizedPlan().toString().replace("unboundedfollowing", "UnboundedFollowing")


def test_long_series_goes_in_blocks(spark, monkeypatch):
    """queries over the one long series ask the planner, which cuts it into blocks."""
    from alignspark import queries as Q

    calls = []
    real = Q.align_planned
    monkeypatch.setattr(Q, "align_planned", lambda *a: calls.append(a[3]) or real(*a))
    for name in ("delta_marss_scan", "wl_f1_greedy_ev4", "wl_f1_expectation_ev4"):
        Q.QUERIES[name][0](spark, "/root/testdata/sf0.001")
    assert calls == ["greedy", "greedy", "expectation"]


@pytest.mark.parametrize("name", ["cand_naive", "dtw_cost_tiny", "exact_delta_tiny", "exact_deltas", "exact_nomodel", "exact_subsets", "exact_tiny", "ratio_tiny"])
def test_small_jobs_read_events(spark, name):
    """The job runs over windows of the given events, not over made rows."""
    from alignspark import queries as Q

    plan = Q.QUERIES[name][0](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "props" in plan and "LogicalRDD" not in plan and "LocalRelation" not in plan


def walks(seed=7, sizes=(1, 2, 3, 9, 40, 67, 67)):
    rng = np.random.default_rng(seed)
    return [rng.normal(size=(n, 3)).cumsum(axis=0) for n in sizes]


def warped_together(spark, method, single):
    """Places of all groups in one task's numpy steps, against ``single`` for one pair after the other."""
    from alignspark.operators import baselines as B
    from alignspark.operators import warping as W

    groups = walks()
    rows = [(f"g{g}", s + 1, i + 1, i * SECOND, float(v[i, s])) for g, v in enumerate(groups) for i in range(len(v)) for s in range(3)]
    series = spark.createDataFrame(rows, "grp string, sid int, idx long, ts_us long, val double")
    out = B.warp(series, 3, method, band=5)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInPandas" in plan and "FlatMapGroupsInPandas" not in plan
    got = {}
    for r in sorted(out.collect(), key=lambda r: (r.grp, r.pos)):
        got.setdefault(r.grp, []).append(r.x)
    return got, {f"g{g}": (W.procrustes(v, single) + 1).tolist() for g, v in enumerate(groups)}


def test_canonical_warps_of_many_groups(spark):
    """base_ctw warps many groups a step. Rounding decides ties, so a path may differ where one alone would, too."""
    from alignspark.operators import warping as W

    got, want = warped_together(spark, "ctw", lambda a, b: W.ctw(a, b, band=5))
    assert got.keys() == want.keys() and all(len(got[g]) == len(want[g]) for g in want)
    assert sum(got[g] == want[g] for g in want) >= 5
    a, b = [v[:, 0] for v in walks()], [v[:, 1] for v in walks()]
    for x, y, path in zip(a, b, W.ctw_many(a, b, iters=1, band=5)):
        assert (path == W.ctw(x, y, iters=1, band=5)).all()


def test_slope_warps_of_many_groups(spark):
    """F16: base_ddtw warps many groups a step, to the places that one pair after the other gets."""
    from alignspark.operators import warping as W

    got, want = warped_together(spark, "ddtw", lambda a, b: W.dtw(W.slopes(a), W.slopes(b), 5)[1])
    assert got == want


@pytest.mark.parametrize("cells", [1, 1 << 25])
def test_warps_of_many_groups(spark, monkeypatch, cells):
    """base_dtw warps many groups a step, to the places that one pair after the other gets; ties and rounds included."""
    from alignspark.operators import warping as W

    got, want = warped_together(spark, "dtw", lambda a, b: W.dtw(a, b, 5)[1])
    assert got == want
    monkeypatch.setattr(W, "CELLS", cells)
    for band in (None, 1, 50):
        a, b = [v[:, 0].round() for v in walks()], [v[:, 1].round() for v in walks()]
        assert all((p == W.dtw(x, y, band)[1]).all() for x, y, p in zip(a, b, W.dtw_many(a, b, band)))


@pytest.mark.parametrize("derivative", [False, True])
@pytest.mark.parametrize("cells", [1, 1 << 25])
def test_places_of_many_groups(monkeypatch, derivative, cells):
    """base_ddtw and base_dtw place whole rounds of groups in one array, as each group alone; ties and short groups included."""
    from alignspark.operators import warping as W

    monkeypatch.setattr(W, "CELLS", cells)
    groups = walks() + [v.round() for v in walks()] + [v[:n] for n, v in enumerate(walks(), 1)]
    for band in (None, 1, 5):
        one = lambda a, b: W.dtw(W.slopes(a), W.slopes(b), band)[1] if derivative else W.dtw(a, b, band)[1]
        for got, v in zip(W.procrustes_dtw(groups, band, derivative), groups, strict=True):
            assert (got == W.procrustes(v, one)).all()


@pytest.mark.parametrize("method", ["base_dtw", "base_ddtw"])
def test_warps_make_no_clocks(spark, method):
    """No step makes the clocks, which the warps don't read, and a user's rows are numbered and averaged in one window."""
    from alignspark import registry

    plan = registry.queries()[method](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "ts_us" not in plan and "Join" not in plan


def test_warps_keep_rows_whole(spark):
    """F16: base_ddtw makes no row of a cell, nor sorts cells: the values of a row of events stay together up to the warp."""
    from alignspark import registry

    plan = registry.queries()["base_ddtw"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "Generate" not in plan and plan.count("Window [") == 1


@pytest.mark.parametrize("method", ["dtw", "ddtw", "gtw"])
def test_warps_of_rows_and_of_cells(spark, method):
    """F16: values of whole rows are blanked, interpolated and warped as cells are, when batches and rounds cut groups, too."""
    from alignspark.operators import baselines as B
    from alignspark.operators import impute as I
    from alignspark.sources import workloads as W

    sf_dir = "/root/testdata/sf0.001"
    rows = lambda df: sorted((r.grp, r.pos, r.x, r.lam, r.w, r.w_fp) for r in df.collect())
    want = rows(B.warp(I.complete_for(W.build(spark, sf_dir, "evu"), 4, "linear"), 4, method))
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        for batch in (7, 10000):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
            assert rows(B.warp_rows(W.values(spark, sf_dir, "evu"), 4, method, gone=W.blanked())) == want
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


def test_warps_of_rows_with_gaps(spark):
    """F16: gaps at ends and between, series without a value, numbers without a row, single rows and a group without a name."""
    from alignspark.operators import baselines as B
    from alignspark.operators import impute as I

    nan, walk = float("nan"), [float(v[0]) for v in walks()[4][:9]]
    rows = [("a", i, walk[i - 3] if i in (5, 6, 9) else None, None, walk[-i]) for i in range(3, 10)]
    rows += [("b", i, walk[i - 1], None if i < 8 else 2.0, nan if i == 4 else 1.0 * i * i) for i in (1, 2, 4, 5, 8, 9)]
    rows += [("c", 7, None, 1.0, None), (None, 1, 3.0, None, 1.0), (None, 2, 5.0, 1.0, None), (None, 3, None, 4.0, 2.0)]
    wide = spark.createDataFrame(rows, "grp string, idx long, v1 double, v2 double, v3 double")
    cells = spark.createDataFrame([(g, j, i, None, v) for g, i, *vs in rows for j, v in enumerate(vs, 1)], "grp string, sid int, idx long, ts_us long, val double")
    key = lambda df: sorted(((r.grp or "", r.pos, r.x) for r in df.collect()))
    for method in ("dtw", "ddtw"):
        got = key(B.warp_rows(wide, 3, method, band=3))
        assert got == key(B.warp(I.interpolate(cells, "val"), 3, method, band=3)) and len(got) == 7 + 9 + 1 + 3


def test_blanks_without_rows_of_cells(spark):
    """F16: the same values go missing as when every cell is hashed by Spark, whatever row number is asked for first."""
    from alignspark.sources import workloads as W

    cells = W.build(spark, "/root/testdata/sf0.001", "ev4", 0.3).select("sid", "idx", "val").toPandas()
    gone = W.blanked(0.3)
    for idx in (np.array([5, 2]), np.arange(1, 900), np.array([], dtype=np.int64)):
        for sid in (1, 2, 4):
            want = dict(zip(cells.idx[cells.sid == sid], cells.val[cells.sid == sid].isna()))
            assert gone(sid, idx).tolist() == [bool(want[i]) for i in idx]


def test_numbers_of_props(spark):
    """F16: texts that need no parser give the number that the parser gives; all others go to the parser."""
    from pyspark.sql import functions as F

    from alignspark.sources.workloads import _number

    texts = ['{"k": 0}', '{"k": 76}', '{"k": 007}', '{"k": -5}', '{"k": 999999999}', '{"k": 2147483647}', '{"k": 99999999999}', '{"k": 1.5}', '{"k": "4"}', '{"k":4}', '{"k": 4}\n',
             '{"a": 7, "k": 3}', '{"k": 3, "a": 7}', '{"k": null}', '{"k": 4', '[1]', 'none', '', ' {"k": 4}', '{"k": 4} x', '{"k": 4}\n{"k": 5}', '{"k": \u0664}', None]
    df = spark.createDataFrame([(t,) for t in texts], "props string").select("props", _number("props").alias("got"), F.from_json("props", "k int")["k"].alias("want"))
    assert all(r.got == r.want for r in df.collect())


def test_whole_tables_over_batches(spark):
    """F16: groups that cross the ends of Arrow batches and of rounds stay whole."""
    import pyarrow as pa

    from alignspark.operators.baselines import whole_tables

    sizes = [1, 7, 1, 20, 3, 3, 11, 2]
    df = spark.createDataFrame([(f"g{g}" if g else None, i) for g, n in enumerate(sizes) for i in range(n)], "grp string, idx long")

    def run(table, starts):
        grp, idx = table["grp"].to_pylist(), table["idx"].to_pylist()
        ends = [*starts[1:], len(idx)]
        return pa.RecordBatch.from_pydict({"grp": pa.array([grp[a] for a in starts], pa.string()), "n": [len(set(idx[a:b])) for a, b in zip(starts, ends)]})

    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        for batch, rows in ((1, 1), (3, 4), (3, 1000), (10000, 1)):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
            got = whole_tables(df, run, "grp string, n long", rows).collect()
            assert sorted((r.grp or "g0", r.n) for r in got) == [(f"g{g}", n) for g, n in enumerate(sizes)]
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


@pytest.mark.parametrize("step", [1, 200, 1 << 15])
def test_paths_by_blocks_of_pairs(monkeypatch, step):
    """F16: pairs are reckoned in blocks, of which each ends with its longest pair, to the paths and middles of one pair alone."""
    import numpy as np

    from alignspark.operators import warping as W

    monkeypatch.setattr(W, "STEP", step)
    a, b = [v[:, 0].round() for v in walks()], [v[:, 1].round() for v in walks()]
    size = np.array([len(v) for v in a])
    for band in (None, 1, 2, 50):
        paths = [W.dtw(x, y, band)[1] for x, y in zip(a, b)]
        assert all((p == q).all() for p, q in zip(W.dtw_many(a, b, band), paths))
        got = W._middles(W._padded(a), W._padded(b), size, band)
        for k, path in enumerate(paths):
            assert (got[: size[k], k] == W.last_per_frame(path, size[k])).all() and not got[size[k] :, k].any()


def test_whole_groups_over_batches(spark):
    """Groups that cross the ends of Arrow batches and of rounds stay whole."""
    from alignspark.operators.baselines import whole_groups

    sizes = [1, 7, 1, 20, 3, 3, 11, 2]
    df = spark.createDataFrame([(f"g{g}", i) for g, n in enumerate(sizes) for i in range(n)], "grp string, idx long")

    def run(pdf, starts):
        ends = [*starts[1:], len(pdf)]
        return type(pdf)({"grp": pdf["grp"].to_numpy()[starts], "n": [len(set(pdf["idx"][a:b])) for a, b in zip(starts, ends)]})

    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        for batch, cells in ((1, 1), (3, 4), (3, 1000), (10000, 1)):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
            got = whole_groups(df, run, "grp string, n long", cells).collect()
            assert sorted((r.grp, r.n) for r in got) == [(f"g{g}", n) for g, n in enumerate(sizes)]
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


@pytest.mark.parametrize("most", [1 << 20, 0])
def test_trusted_texts_stay_in_place(spark, monkeypatch, most):
    """op8_quality: trusted ids go to the texts as bits, so that labels too many to broadcast shuffle no text; without room for the bits the same are trusted."""
    from alignspark.llm import quality

    monkeypatch.setattr(quality, "WORDS", most)
    ids = [0, 1, 63, 64, 65, 127, 128, 1 << 40, (1 << 63) - 1, -1, -64, -65, -(1 << 63), 63, None, None]
    good = [0, 63, 65, 128, (1 << 63) - 1, -1, -64, -(1 << 63), 7 << 30, 63]
    docs = spark.createDataFrame([(i, f"t{n}") for n, i in enumerate(ids)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, 0) for i in good] + [(None, 1, 0), (1, 0, 0), (64, None, 0)], "doc_id long, quality int, toxic int")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        marked = quality._marked(docs, labels)
        assert {r.text: r.t for r in marked.collect()} == {f"t{n}": int(i in good) for n, i in enumerate(ids)}
        plan = marked._jdf.queryExecution().executedPlan().toString()
        assert ("BroadcastHashJoin" in plan, "SortMergeJoin" in plan) == (most > 0, most == 0)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_secrets_learn_from_all_documents(spark):
    """words, transitions and labelled findings come from every document, not from about 2000 of them."""
    from alignspark.llm import secrets

    code = lambda i: "".join("abcdefghijklmnopqrstuvwxyz"[i // 26**k % 26] for k in range(3))
    texts = [f"plain prose {code(i)} {'long' * 4 + code(i)} here" for i in range(4000)]
    docs = spark.createDataFrame([*enumerate(texts)], "doc_id long, text string")
    assert secrets.field_findings(docs.select("text")).count() == 4000
    style = secrets.fit(docs).style
    pairs = {}
    for text in texts:
        for word in text.split():
            numbers = [secrets.LETTERS.index(c) + 1 for c in word]
            for a, b in zip(numbers, numbers[1:]):
                pairs[a * secrets.CLASSES + b] = pairs.get(a * secrets.CLASSES + b, 0) + 1
    assert style.transitions == secrets._style([], pairs).transitions


def test_forest_in_expressions_votes_as_the_model(spark):
    """Pipeline's check, F26: the walk over constant arrays gives what most of the model's trees say; no literal is written out in the plan's SQL."""
    from pyspark.ml.feature import VectorAssembler

    from alignspark.llm import secrets

    scanner = secrets.train(secrets.findings(spark))
    found = secrets.scan(secrets.findings(spark, 600, first=70_000), scanner).select("_secrets", secrets.F.explode("_found").alias("c")).select("_secrets", "c.token", "c.f.*")
    got = VectorAssembler(inputCols=secrets.FEATURES, outputCol="v").transform(found).select("_secrets", "token", "v").collect()
    for r in got[::7]:
        votes = sum(tree.predict(r.v) for tree in scanner.forest.trees)
        assert (r.token in r._secrets) == (votes > len(scanner.forest.trees) / 2)


def test_frequent_tokens_are_counted_over_all_classes(spark, monkeypatch):
    """tokens of many classes are counted over all classes, copies once; before, over about ORDER_SAMPLE of them."""
    from alignspark.llm import jaccard

    monkeypatch.setattr(jaccard, "ORDER_SAMPLE", 10, raising=False)
    monkeypatch.setattr(jaccard, "COUNTED", 20, raising=False)
    words = [f"w{k}" for k in range(9)]
    texts = [" ".join([*words, f"own{i}", *words[: i % 5 + 5]]) for i in range(40)]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts + texts[:7] * 5 + [None, "", "two words"])], "doc_id long, text string").repartition(1)
    classes = jaccard.rows(docs, 5).where("cls <> 0").groupBy("cls").agg(jaccard.F.min("doc_id").alias("id"))
    token, n = jaccard.frequent_tokens(docs, classes, 5, 3)
    holders = {}
    for t in texts:
        w = t.split()
        for s in {tuple(w[k : k + 5]) for k in range(len(w) - 4)}:
            holders[s] = holders.get(s, 0) + 1
    assert sorted(n.tolist()) == sorted(k for k in holders.values() if k >= jaccard.FREQUENT)
    assert (token[1:] > token[:-1]).all()


def test_quality_trusts_all_good_documents(spark):
    """the shares of good documents come from all of them (before, from about 20,000 ids), rows without an id from none."""
    from alignspark.llm import quality

    docs = spark.range(25_000).select("id", quality.F.concat_ws(" ", quality.F.lit("word"), "id").alias("text")).withColumnRenamed("id", "doc_id")
    docs = docs.unionByName(spark.createDataFrame([(None, "word")] * 3, "doc_id long, text string"))
    labels = docs.select("doc_id", quality.F.lit(1).alias("quality"))
    assert quality.trusted_ids(labels).count() == 25_000
    got = quality.ratios(docs, labels)
    raw, good = [0] * quality.BUCKETS, [0] * quality.BUCKETS
    for r in docs.selectExpr("doc_id", "transform(split(text, ' '), w -> xxhash64(w)) AS _h").select("doc_id", quality.F.expr(quality._grams()).alias("g")).collect():
        for g in r.g:
            raw[g] += 1
            good[g] += r.doc_id is not None
    n_raw, prior = sum(raw) + quality.BUCKETS, quality.PRIOR * quality.BUCKETS
    want = [np.log((t + prior * (r + 1) / n_raw) / (sum(good) + prior) / ((r + 1) / n_raw)) for r, t in zip(raw, good)]
    assert np.allclose(got, want)
