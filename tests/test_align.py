"""The alignment methods: worked examples, equal strategies, invariants, bounds, degenerate inputs."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from alignspark.functions import measures as M
from alignspark.operators import candidates as C
from alignspark import experiments as E
from alignspark.operators import baselines as B
from alignspark.operators import compose as K
from alignspark.operators import conflicts as X
from alignspark.operators import consistency as S
from alignspark.operators import gate
from alignspark.operators import impute as I
from alignspark.operators import metrics as Q
from alignspark.operators import tuning as T
from alignspark.operators.fold import expectation_scores, fold
from alignspark.operators.marss import Marss
from alignspark.operators.warping import dtw, slopes
from alignspark.params import SECOND, AlignParams
from alignspark.plans.blocks import align_blocks
from alignspark.plans.planner import align_until_feasible, plan
from alignspark.sources import workloads as W
from alignspark.streaming import aligner

P = AlignParams()
T2 = P.with_(theta=5 * SECOND)


def chosen(df):
    return sorted(tuple(r.x) for r in df.collect())


def random_series(spark, n=60, m=3, seed=0, gaps=0.2, groups=1):
    rng = np.random.default_rng(seed)
    rows = []
    for g in range(groups):
        for s in range(1, m + 1):
            t = np.cumsum(rng.integers(5, 40, n)) * SECOND
            for i in range(n):
                rows.append((f"g{g}", s, i + 1, None if rng.random() < gaps else int(t[i]), None if rng.random() < gaps else float(rng.normal())))
    return spark.createDataFrame(rows, W.SERIES)


def test_t1_weights_and_counts(spark):
    c = C.candidates(W.tiny(spark, "t1"), 2, P).orderBy("x").collect()
    assert [tuple(r.x) for r in c] == [(1, 1), (1, 2), (2, 1), (2, 2), (2, 3), (3, 2), (3, 3)]
    assert [round(r.w, 6) for r in c] == [4, 1.333333, 1.333333, 4, 1.333333, 1.333333, 4]
    assert M.candidate_count_bound(3, 2, 1) == 7
    best = K.compose_exact(C.candidates(W.tiny(spark, "t1"), 2, P), 2).first()
    assert (best.mask, best.w_fp) == (73, 12 * M.SCALE)
    for method in ("greedy", "expectation", "packing", "exact"):
        assert chosen(K.align(W.tiny(spark, "t1"), 2, P, method)) == [(1, 1), (2, 2), (3, 3)]
    assert chosen(K.align(W.tiny(spark, "t1"), 2, P.with_(literal=True), "greedy")) == [(1, 1), (2, 2)]


def test_t2_everything(spark):
    s = W.tiny(spark, "t2")
    c = C.candidates(s, 3, T2).orderBy("x").collect()
    assert [(tuple(r.x), r.lam, r.d, r.spread_us // SECOND, r.w) for r in c] == [
        ((1, 1, 1), 2, 0, 3, 4.0), ((1, 2, 1), 2, 2, 3, 0.8), ((2, 2, 2), 3, 0, 2, 10.0), ((2, 2, 3), 3, 2, 0, 2.0), ((3, 2, 3), 2, 2, 0, 0.8), ((3, 3, 3), 2, 0, 2, 4.0)]
    x = np.array([r.x for r in c])
    w = np.array([r.w_fp for r in c])
    assert (expectation_scores(x, w, [0, 1], T2) / M.SCALE).round(6).tolist() == [16.8, 0.8]
    assert (expectation_scores(x, w, [2, 3, 4], T2) / M.SCALE).round(6).tolist() == [14, 2, 0.8]
    edges = {(r.a[0] * 100 + r.a[1] * 10 + r.a[2], r.b[0] * 100 + r.b[1] * 10 + r.b[2]) for r in X.conflict_edges(C.candidates(s, 3, T2)).collect()}
    assert len(edges) == 9 and (111, 121) in edges and (322, 333) not in edges
    diag = [(1, 1, 1), (2, 2, 2), (3, 3, 3)]
    for method in ("greedy", "expectation", "packing", "packing_init", "exact"):
        assert chosen(K.align(s, 3, T2, method)) == diag
    assert chosen(K.align(s, 3, T2.with_(literal=True), "greedy")) == [(1, 1, 1)]
    a = K.align(s, 3, T2, "greedy")
    assert abs(S.delta(a, s, 3).first().delta - 4 / 9) < 1e-12
    assert Q.f1_score(Q.pairs_recovered(a), Q.pairs_truth(s)).first().f1 == 1.0
    seen = Q.f1_score(Q.pairs_recovered(a, s, "observed"), Q.pairs_truth(s, "observed")).first()
    assert (seen.found, seen.both) == (5, 5)
    assert abs(T.fit_theta(s).first().theta - 2.8 * SECOND) < 1
    assert T.fit_beta(s, 3, T2, beta_cap=1) == 1
    assert M.weight_bounds(3, P) == (10.0, 0.2)


@pytest.mark.parametrize("beta", [0, 1, 2])
def test_strategies_agree(spark, beta):
    s, p = random_series(spark, 25, groups=2), P.with_(theta=60 * SECOND, beta=beta)
    want = sorted(map(tuple, C.flat(C.candidates(s, 3, p, "lead"), 3).collect()))
    assert want
    for name in ("anchor", "join", "odometer", "block"):
        assert sorted(map(tuple, C.flat(C.candidates(s, 3, p, name), 3).collect())) == want, name
    one = random_series(spark, 8)
    assert sorted(map(tuple, C.flat(C.candidates(one, 3, p, "naive"), 3).collect())) == sorted(map(tuple, C.flat(C.candidates(one, 3, p), 3).collect()))


def test_counts_monotone_and_closed_form(spark):
    s = random_series(spark, 30, gaps=0.0)
    n = [C.candidates(s, 3, P.with_(theta=10**15, beta=b)).count() for b in (0, 1, 2)]
    assert n == [M.candidate_count_bound(30, 3, b) for b in (0, 1, 2)]
    sizes = [C.candidates(s, 3, P.with_(theta=t * SECOND, beta=2)).count() for t in (0, 10, 40, 200)]
    assert sizes == sorted(sizes)


@pytest.mark.parametrize("method", ["greedy", "expectation", "packing", "exact"])
def test_results_are_feasible(spark, method):
    s = random_series(spark, 5 if method == "exact" else 60, groups=2, seed=3)
    p = P.with_(theta=60 * SECOND)
    a = K.align(s, 3, p, method)
    assert K.validate(a, s, p).count() == 0
    assert chosen(a) == chosen(K.compose(C.candidates(s.repartition(7), 3, p), 3, p, method))


def instance(seed, n=6, m=3):
    rng = np.random.default_rng(seed)
    times = np.sort(rng.integers(0, 90, (n, m)), axis=0).astype(float)
    times[rng.random((n, m)) < 0.2] = np.nan
    has = (rng.random((n, m)) > 0.3).astype(np.int8)
    p = AlignParams(theta=30, beta=1)
    x, lam, spread = C.expand_block(times, has, m, p.theta, p.beta, 1, n)
    _, w, w_fp = C.numpy_weights(x, lam, p)
    return x, w_fp, spread, p


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10_000))
def test_weights_and_ratios(seed):
    x, w, spread, p = instance(seed)
    if not len(x):
        return
    total = lambda k: sum(int(w[i]) for i in k)
    best = K.exact_bnb(x, w)
    top, low = M.weight_bounds(3, p)
    assert w.max() <= round(top * M.SCALE) and w.min() >= round(low * M.SCALE) - 1
    start = K.packing_start(x, w)
    branches = K.packing(x, w)
    moved = next(gate.by_weight(branches, w))
    ranked = [total(k) for _, k in zip(range(50), gate.by_weight(branches, w))]
    assert ranked == sorted(ranked, reverse=True)
    assert all((a == np.flatnonzero((x == r).any(axis=1))).all() for a, r in zip(K.conflict_lists(x), x))
    assert total(best) >= total(moved) >= total(start)
    assert total(moved) >= M.bound_packing(3) * total(best) - 1
    together = K.packing_parallel(x, w)
    assert total(best) >= total(together) >= total(start)
    n = len(best)
    assert total(fold(x, w, p, "greedy")) >= M.bound_greedy(n, 3, top, low) * total(best) - 1
    assert total(fold(x, w, p, "expectation")) >= M.bound_expectation(n, 3, top, low) * total(best) - 1
    # nothing free is left by the heaviest-first start, and no result repeats a cell
    used = [{int(x[k, j]) for k in start} for j in range(3)]
    assert all(any(int(v) in u for v, u in zip(r, used)) for r in x)
    for k in (fold(x, w, p, "greedy"), fold(x, w, p, "expectation"), moved, together, best):
        assert all(len({int(x[i, j]) for i in k}) == len(k) for j in range(3))
    # exact equals enumeration of all subsets on small candidate sets
    if len(x) <= 12:
        bits = max(sum(int(w[i]) for i in range(len(x)) if b >> i & 1) for b in range(1 << len(x))
                   if all(not (x[i] == x[j]).any() for i in range(len(x)) if b >> i & 1 for j in range(i) if b >> j & 1))
        assert bits == total(best)


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000))
def test_look_ahead_is_enough(seed):
    """Later candidates that meet nobody add the same to every score, so the lemma's window decides alike."""
    x, w, _, p = instance(seed, n=10)
    for first in range(0, len(x), 3):
        clique = [first]
        for k in range(first + 1, len(x)):
            if all((x[g] == x[k]).any() for g in clique):
                clique.append(k)
            else:
                break
        near = expectation_scores(x, w, clique, p)
        after = clique[-1]
        full = [int(w[g]) + sum(int(w[r]) for r in range(g + 1, len(x)) if not (x[r] == x[g]).any() and (r > after or (x[r] == x[clique]).any())) for g in clique]
        assert int(np.argmax(near)) == int(np.argmax(full))


@pytest.mark.parametrize("method", ["greedy", "expectation"])
@pytest.mark.parametrize("warm", [0, 30])
def test_blocks_equal_group(spark, method, warm):
    s, p = random_series(spark, 150, seed=9, gaps=0.4), P.with_(theta=60 * SECOND, beta=2)
    want = {tuple(r.x): r.pos for r in K.align(s, 3, p, method).collect()}
    got = {tuple(r.x): r.pos for r in align_blocks(s, 3, p, method, size=40, warm=warm).collect()}
    assert got == want


def test_stream_equals_batch(spark):
    s, p = random_series(spark, 60, groups=3, seed=4), P.with_(theta=60 * SECOND)
    for method in ("greedy", "expectation"):
        got = aligner.replay(spark, s, 3, p, method).collect()
        assert {r.kind for r in got} == {"tuple"}
        assert sorted((r.grp, tuple(r.x)) for r in got) == sorted((r.grp, tuple(r.x)) for r in K.align(s, 3, p, method).collect())


def test_stream_late_cells_and_idle_groups():
    """Cells behind the next lead's reach leave as late rows; a group that timed out is flushed."""
    import pandas as pd

    class State:
        def __init__(self):
            self.exists, self.hasTimedOut, self.get = False, False, None

        def update(self, value):
            self.exists, self.get = True, value

        def remove(self):
            self.exists = False

        def setTimeoutDuration(self, ms):
            self.ms = ms

    rows = [(s, i, i * 10 * SECOND, 1.0) for i in range(1, 41) for s in (1, 2)]
    frame = lambda r: pd.DataFrame(r, columns=["sid", "idx", "ts_us", "val"])
    state, step = State(), aligner.stepper(2, P, "greedy", idle_ms=5000)
    first = next(step(("g",), iter([frame(rows)]), state))
    assert len(first) and set(first["kind"]) == {"tuple"} and state.ms == 5000
    late = next(step(("g",), iter([frame([(1, 2, 20 * SECOND, 7.0)])]), state))
    assert late[["kind", "x"]].values.tolist() == [["late", [1, 2]]]
    state.hasTimedOut = True
    rest = next(step(("g",), iter([]), state))
    assert len(first) + len(rest) == 40 and not state.exists


def test_marss_matches_gaussian_conditioning():
    rng = np.random.default_rng(2)
    y = rng.normal(size=(6, 2))
    y[1, 0] = y[3, 1] = np.nan
    model = Marss(2, 4).fit(y)
    n, m = y.shape
    big = np.zeros((n * m, n * m))
    mean, cov = [model.x0], [model.V0]
    for _ in range(n - 1):
        mean.append(model.B @ mean[-1] + model.u)
        cov.append(model.B @ cov[-1] @ model.B.T + np.diag(model.Q))
    for a in range(n):
        c = cov[a]
        for b in range(a, n):
            big[b * m : (b + 1) * m, a * m : (a + 1) * m] = c
            big[a * m : (a + 1) * m, b * m : (b + 1) * m] = c.T
            c = model.B @ c
    mu, obs = np.concatenate(mean), model.y.ravel()
    seen = ~np.isnan(obs)
    s = big[np.ix_(seen, seen)] + np.diag(np.tile(model.R, n)[seen])
    direct = mu + big[:, seen] @ np.linalg.solve(s, obs[seen] - mu[seen])
    assert np.allclose(model.xs.ravel(), direct, atol=1e-6)


def test_marss_likelihood_rises_and_finds_persistence():
    rng = np.random.default_rng(1)
    x = np.zeros((400, 2))
    for t in range(1, 400):
        x[t] = 0.9 * x[t - 1] + rng.normal(size=2) * 0.5
    y = x + rng.normal(size=x.shape) * 0.2
    y[rng.random(y.shape) < 0.2] = np.nan
    model = Marss(2, 25).fit(y)
    assert all(b >= a - 1e-3 for a, b in zip(model.loglik, model.loglik[1:]))
    assert np.abs(np.diag(model.B) - 0.9).max() < 0.12


def test_warping_basics():
    cost, path = dtw([1, 3, 4, 9], [1, 4, 5, 8, 9])
    assert cost == 3.0 and tuple(path[0]) == (0, 0) and tuple(path[-1]) == (3, 4)
    assert (np.diff(path, axis=0) >= 0).all()
    assert dtw(np.arange(30.0), np.arange(30.0), band=3)[0] == 0
    assert np.allclose(slopes(np.arange(5.0) * 2), 2)


def test_degenerate_inputs(spark):
    empty = spark.createDataFrame([], W.SERIES)
    none = spark.createDataFrame([("", s, i, None, None) for s in (1, 2) for i in (1, 2, 3)], W.SERIES)
    lonely = spark.createDataFrame([("", 1, i, i * SECOND, 1.0) for i in (1, 2)], W.SERIES)
    for method in ("greedy", "expectation", "packing"):
        assert chosen(K.align(empty, 2, P, method)) == []
        assert chosen(K.align(none, 2, P, method)) == [(1, 1), (2, 2), (3, 3)]
        assert chosen(K.align(lonely, 2, P, method)) == []
        assert chosen(K.align(lonely, 1, P, method)) == [(1,), (2,)]
    assert S.delta(K.align(none, 2, P, "greedy"), none, 2).first().delta is None
    with pytest.raises(ValueError):
        AlignParams(theta=-1)
    with pytest.raises(Exception, match="more than 20"):
        K.subsets(C.candidates(random_series(spark, 40), 3, P), 3).count()


def test_gate_and_planner(spark):
    s = random_series(spark, 40, groups=2)
    p = P.with_(theta=60 * SECOND)
    assert {r.status for r in align_until_feasible(s, 3, p.with_(delta=10.0)).collect()} == {"feasible"}
    assert {r.status for r in align_until_feasible(s, 3, p.with_(delta=1e-9, max_rounds=2)).collect()} == {"infeasible"}
    assert plan(s, 3, p, "greedy").executor == "group"
    assert plan(s.withColumn("idx", s.idx * 100_000), 3, p, "greedy").executor == "block"


def test_plans_have_no_nested_loops(spark):
    s = random_series(spark, 20)
    for name in ("lead", "anchor", "join"):
        text = C.candidates(s, 3, P, name)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in text and "Cartesian" not in text, name


# --- the model constraint -----------------------------------------------------------------------------------------------------


def test_exact_under_delta(spark):
    """Spark's subset table and the search inside a task agree, and both with plain enumeration, at every limit."""
    s = W.tiny(spark, "t2")
    cand = C.candidates(s, 3, T2)
    table = {r.mask: (r.w_fp, r.delta) for r in S.subset_deltas(K.subsets(cand, 3), cand, s, 3).collect()}
    assert len(table) == 13 and abs(table[0b100101][1] - 4 / 9) < 1e-12
    for limit in (0.0, 0.2, 0.3, 0.45, 1.0):
        fit = [(-w, mask) for mask, (w, d) in table.items() if d is None or d <= limit]
        best = K.compose_exact(cand, 3, lambda r: S.subset_deltas(r, cand, s, 3), limit).first()
        gated = K.align_gated(s, 3, T2.with_(delta=limit), "exact").collect()
        assert (-best.w_fp, best.mask) == min(fit)
        assert gated[0].status == "feasible" and sum(r.w_fp for r in gated) == best.w_fp


@pytest.mark.parametrize("model", ["locf", "marss"])
def test_packing_under_delta(spark, model):
    s, p = random_series(spark, 25, groups=3, seed=5), P.with_(theta=60 * SECOND)
    free = {r.grp: r.delta for r in S.delta(K.align(s, 3, p, "packing"), s, 3, model).collect()}
    for limit in (min(free.values()) * 0.999, max(free.values()) * 1.001):
        got = K.align_gated(s, 3, p.with_(delta=limit), "packing", model, most=40)
        status = {r.grp: r.status for r in got.select("grp", "status").distinct().collect()}
        assert set(status) == set(free) and set(status.values()) <= {"feasible", "infeasible", "untested"}
        kept = got.where("x IS NOT NULL")
        assert all(r.delta <= limit + 1e-9 for r in S.delta(kept, s, 3, model).collect())
        if limit > max(free.values()):
            assert set(status.values()) == {"feasible"} and chosen(kept) == chosen(K.align(s, 3, p, "packing"))


def test_delta_inside_a_task(spark):
    s, p = random_series(spark, 40, seed=8), P.with_(theta=60 * SECOND)
    a = K.align(s, 3, p, "greedy")
    _, values, _, first = C.matrices(s.toPandas(), 3)
    x = np.array([r.x for r in a.orderBy("pos").collect()])
    for model in ("locf", "marss"):
        assert abs(gate.consistency_of(values, first, x, model) - S.delta(a, s, 3, model).first().delta) < 1e-9


def test_rounds_run_in_blocks_too(spark, monkeypatch):
    from alignspark.plans import planner

    s, p = random_series(spark, 150, groups=2, seed=6), P.with_(theta=60 * SECOND, delta=0.5, max_rounds=2)
    want = sorted(map(tuple, align_until_feasible(s, 3, p).select("grp", "pos", "w_fp", "status").collect()))
    monkeypatch.setattr(planner, "TASK_CANDIDATES", 100)
    assert plan(s, 3, p, "greedy").executor == "block"
    assert sorted(map(tuple, align_until_feasible(s, 3, p).select("grp", "pos", "w_fp", "status").collect())) == want


def test_scan_filter_equals_whole_filter(spark):
    s = random_series(spark, 60, seed=2)
    cells = K.materialise(K.align(s, 3, P.with_(theta=60 * SECOND), "greedy"), s)
    from alignspark.operators.marss_scan import predict_scan

    whole, blocks = ({(r.pos, r.sid): r.pred for r in predict_scan(cells, size).collect()} for size in (10_000, 7))
    assert whole.keys() == blocks.keys() and max(abs(whole[k] - blocks[k]) for k in whole) < 1e-8


# --- baselines, parameters, experiments ----------------------------------------------------------------------------------------


def test_band_does_not_change_what_fits():
    rng = np.random.default_rng(3)
    for n, k in ((12, 12), (9, 17), (1, 5), (20, 7)):
        a, b = rng.normal(size=n), rng.normal(size=k)
        cost = np.full((n + 1, k + 1), np.inf)
        cost[0, 0] = 0
        for i in range(n):
            for j in range(k):
                cost[i + 1, j + 1] = abs(a[i] - b[j]) + min(cost[i, j], cost[i, j + 1], cost[i + 1, j])
        for band in (None, 40):
            got, path = dtw(a, b, band)
            assert abs(got - cost[-1, -1]) < 1e-9 and abs(sum(abs(a[i] - b[j]) for i, j in path) - got) < 1e-9
        assert dtw(a, b, 2)[0] >= cost[-1, -1] - 1e-9


def test_sequential_knows_time_only(spark):
    """Its candidates are all tuples within theta, however far apart their rows are."""
    rows = [("", 1, i, (100 + i) * SECOND, 1.0) for i in range(1, 7)] + [("", 2, i, (90 + 4 * i) * SECOND, 1.0) for i in range(1, 7)]
    s = spark.createDataFrame(rows, W.SERIES)
    p = P.with_(theta=3 * SECOND)
    far = max(abs(a[2] - b[2]) for a in rows for b in rows if a[1] != b[1] and abs(a[3] - b[3]) <= p.theta)
    assert B.reach_of(s, p.theta) >= far
    times = {(r[1], r[2]): r[3] for r in rows}
    x = np.array([(i, j) for i in range(1, 7) for j in range(1, 7) if abs(times[1, i] - times[2, j]) <= p.theta])
    spread = np.array([abs(times[1, i] - times[2, j]) for i, j in x])
    assert chosen(B.align_sequential(s, 2, p)) == sorted(tuple(x[k]) for k in fold(x, np.zeros(len(x), np.int64), p, "sequential", spread))


def test_imputer_beats_the_mean(spark):
    sf = "/root/testdata/sf0.001"
    s, full = W.build(spark, sf, "evu", 0.2), W.complete(spark, sf, "evu").select("grp", "sid", "idx", W.F.col("val").alias("true"))
    # the trailing mean has a course that neighbours explain
    hole = s.where("sid = 3 AND val IS NULL").select("grp", "sid", "idx")
    error = lambda done: done.join(hole, ["grp", "sid", "idx"]).join(full, ["grp", "sid", "idx"]).agg(W.F.avg(W.F.abs(W.F.col("val") - W.F.col("true")))).first()[0]
    assert error(I.impute_model(s, 4, "imp_lr")) < error(I.impute_simple(s, "mean"))


def test_experiments_and_parameters(spark):
    sf = "/root/testdata/sf0.001"
    table = {(r.method, r.rate): r for r in E.ours(spark, sf, "or4", rates=(0.1, 0.4)).collect()}
    assert len(table) == 8 and all(0 <= r.f1 <= 1 for r in table.values())
    for rate in (10, 40):
        assert table["expectation", rate].n_aligned >= table["greedy", rate].n_aligned and table["diagonal", rate].precision == 1.0
    one = W.build(spark, sf, "or4", 0.1)
    f1 = Q.f1_score(Q.pairs_recovered(K.align(one, 4, E.params("or4", P), "greedy")), Q.pairs_truth(one)).first().f1
    assert abs(table["greedy", 10].f1 - f1) < 1e-6
    got = T.auto_params(W.build(spark, sf, "or4", 0.2), 4, k1=(1, 3), k2=(1, 2), beta_cap=2)
    assert got.theta > 0 and got.beta >= 1 and got.delta > 0 and got.k1 in (1, 3)
    points = E.theta_grid("or4", betas=(1, 2))
    swept = {(r.theta, r.beta): r for r in E.grid(spark, sf, "or4", points, "greedy").collect()}
    assert len(swept) == 14
    for r in swept.values():
        a = K.align(W.build(spark, sf, "or4", 0.2), 4, P.with_(theta=r.theta, beta=r.beta), "greedy") if r.theta == points[-1].theta else None
        assert a is None or a.count() == r.n_aligned


def test_series_log_source(spark, tmp_path):
    from alignspark.sources.serieslog import SeriesLog

    (tmp_path / "a-1.log").write_text("1,1000,2.5\n2,,3.0\n3,3000,\n")
    (tmp_path / "a-2.log").write_text("1,1500,1.0\n")
    (tmp_path / "notes.txt").write_text("none")
    spark.dataSource.register(SeriesLog)
    got = spark.read.format("series_log").load(str(tmp_path))
    assert sorted(map(str, got.collect())) == sorted(map(str, spark.createDataFrame([("a", 1, 1, 1000, 2.5), ("a", 1, 2, None, 3.0), ("a", 1, 3, 3000, None), ("a", 2, 1, 1500, 1.0)], W.SERIES).collect()))


def test_scratch_folder_is_shared_on_a_cluster(spark):
    from types import SimpleNamespace

    from alignspark.operators.conflicts import shared_path

    cluster = SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=SimpleNamespace(master="spark://host:7077", getCheckpointDir=lambda: None))
    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        shared_path(cluster, "x")
