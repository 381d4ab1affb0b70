"""Composers: from candidates to a conflict-free result.

Greedy, Expectation and the sequential matcher fold a group's candidates in
order; Exact tries all subsets; Packing improves a heaviest-first start by local
search. ``align`` fuses candidate generation with the fold in one task per
group, so candidates are never shuffled.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator
from fractions import Fraction

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from alignspark.operators import gate
from alignspark.operators.candidates import expand_block, matrices, numpy_weights, spans
from alignspark.operators.fold import Counters, fold
from alignspark.operators.marss import groups_together
from alignspark.params import AlignParams

ALIGN = "grp string, pos long, x array<long>, lam int, w double, w_fp long"


def _result(grp: str, x: np.ndarray, lam: np.ndarray, w: np.ndarray, w_fp: np.ndarray, chosen: list[int]) -> pd.DataFrame:
    k = np.array(sorted(chosen), dtype=np.int64)
    return pd.DataFrame({"grp": grp, "pos": np.arange(1, len(k) + 1), "x": pd.Series(list(x[k]), dtype=object), "lam": lam[k].astype("int32"), "w": w[k], "w_fp": w_fp[k]})


def compose(cand: DataFrame, m: int, p: AlignParams, method: str = "greedy") -> DataFrame:
    """ALIGN rows from CAND rows; each group's candidates meet in one task, in order."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.array(pdf["x"].tolist(), dtype=np.int64).reshape(-1, m)
        order = np.lexsort(tuple(x[:, j] for j in reversed(range(m))))
        x, lam, w, w_fp, spread = x[order], *(pdf[c].to_numpy()[order] for c in ("lam", "w", "w_fp", "spread_us"))
        chosen = solve(x, w_fp, p, method, spread)
        return _result(key[0], x, lam, w, w_fp, chosen)

    return cand.groupBy("grp").applyInPandas(run, ALIGN)


def solve(x: np.ndarray, w_fp: np.ndarray, p: AlignParams, method: str, spread: np.ndarray | None = None) -> list[int]:
    if method in ("greedy", "expectation", "sequential"):
        return fold(x, w_fp, p, method, spread)
    if method == "packing_init":
        return packing_start(x, w_fp)
    if method == "packing":
        return next(gate.by_weight(packing(x, w_fp), w_fp))
    if method == "packing_parallel":
        return packing_parallel(x, w_fp)
    if method == "exact":
        return exact_bnb(x, w_fp)
    raise ValueError(f"unknown composer {method!r}")


def whole_tables(df: DataFrame, run: Callable[[pa.Table, np.ndarray], pa.RecordBatch], schema: str, rows: int = 200_000, clustered: bool = False) -> DataFrame:
    """``run`` over Arrow tables of whole groups (by grp), ``rows`` rows and the rest of a group at a time, and the rows where
    its groups start. ``clustered``: the rows of every group stand side by side already, and no shuffle is made."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, starts, n, last = [], [], 0, None
        for batch in batches:
            if not batch.num_rows:
                continue
            codes = batch.column("grp").dictionary_encode(null_encoding="encode")
            names, at = codes.dictionary.to_pylist(), codes.indices.to_numpy()
            cuts = np.flatnonzero(np.append(not held or names[at[0]] != last, at[1:] != at[:-1]))
            if n >= rows and len(cuts):  # all that is held before the last group that starts here
                cut = int(cuts[-1])
                yield run(pa.Table.from_batches([*held, batch.slice(0, cut)]), np.concatenate([*starts, cuts[:-1] + n]))
                held, starts, n, batch, cuts = [], [], 0, batch.slice(cut), cuts[-1:] - cut
            held.append(batch)
            starts.append(cuts + n)
            n, last = n + batch.num_rows, names[at[-1]]
        if held:
            yield run(pa.Table.from_batches(held), np.concatenate(starts))

    return (df if clustered else df.repartition("grp").sortWithinPartitions("grp")).mapInArrow(stream, schema)


def align(series: DataFrame, m: int, p: AlignParams, method: str = "expectation", clustered: bool = False) -> DataFrame:
    """Candidates and composition of whole groups, many in one numpy step: one shuffle, by group, and none where the cells
    of every group stand side by side already (``clustered``)."""
    #: places of the groups that are expanded together: their prefixes stay within this number, and within the cap
    most = min(250_000, p.cap or 250_000) // ((p.beta + 1) ** m - p.beta**m)

    def run(table: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
        idx, sid = table.column("idx").to_numpy(), table.column("sid").to_numpy()
        first, size, base, row = spans(idx, starts, p.beta + 1)
        times = table.column("ts_us").to_numpy().astype(float)  # NaN where null
        seen = ~np.isnan(table.column("val").to_numpy())
        if p.lam_mode == "cell":
            seen &= ~np.isnan(times)
        ends, at, lo, parts = np.append(starts[1:], len(idx)), base + size, 0, []
        while lo < len(starts):
            hi = max(lo + 1, int(np.searchsorted(at, base[lo] + most, side="right")))
            cells, zero = slice(starts[lo], ends[hi - 1]), base[lo]
            clock, has = np.full((at[hi - 1] - zero, m), np.nan), np.full((at[hi - 1] - zero, m), -1, dtype=np.int8)
            clock[row[cells] - zero, sid[cells] - 1] = times[cells]
            has[row[cells] - zero, sid[cells] - 1] = seen[cells]
            place, lam, spread = expand_block(clock, has, m, p.theta, p.beta, 0, len(clock) - 1, 0, p.cap if hi == lo + 1 else None)
            of = np.searchsorted(base[lo:hi], place[:, 0] + zero, side="right") + lo - 1
            x = place + (zero - base + first)[of][:, None]
            _, w, w_fp = numpy_weights(x, lam, p)
            k = solve_many(x, w_fp, np.flatnonzero(np.diff(of, prepend=-1)), p, method, spread)
            parts.append((of[k], x[k], lam[k], w[k], w_fp[k]))
            lo = hi
        of, x, lam, w, w_fp = (np.concatenate(c) for c in zip(*parts))
        new = np.flatnonzero(np.diff(of, prepend=-1))
        pos = np.arange(1, len(of) + 1) - np.repeat(new, np.diff(np.append(new, len(of))))
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, m, dtype=np.int32)), pa.array(x.ravel()))
        names = table.column("grp").take(pa.array(starts[of])).combine_chunks()
        return pa.RecordBatch.from_arrays([names, pa.array(pos), lists, pa.array(lam.astype(np.int32)), pa.array(w), pa.array(w_fp)], names=["grp", "pos", "x", "lam", "w", "w_fp"])

    clock = F.col("ts_us") if dict(series.dtypes)["ts_us"] == "bigint" else F.col("ts_us").cast("double").alias("ts_us")
    cells = series.select("grp", F.col("sid").cast("int").alias("sid"), F.col("idx").cast("long").alias("idx"), clock, F.col("val").cast("double").alias("val"))
    return whole_tables(cells, run, ALIGN, clustered=clustered)


def solve_many(x: np.ndarray, w_fp: np.ndarray, starts: np.ndarray, p: AlignParams, method: str, spread: np.ndarray) -> np.ndarray:
    """``solve`` of groups side by side, where each starts given: numbers of the candidates chosen, in order. Small groups are
    folded, small segments searched, in steps of many; all others one after another."""
    ends = np.append(starts[1:], len(x))
    if method == "exact":
        of = np.repeat(np.arange(len(starts)), ends - starts)
        starts, ends = _segments(x, of)
        small, alike, limit = ends - starts <= 10, exact_alike, 1 << 20
    elif method == "greedy" and p.tie == "first":
        small, alike, limit = ends - starts <= 32, greedy_alike(p.literal), 1 << 16
    else:
        small, limit = np.zeros(len(starts), dtype=bool), 1
    chosen = [np.zeros(0, dtype=np.int64)]
    sizes = (ends - starts)[small]
    for n in np.unique(sizes).tolist():
        own = starts[small][sizes == n][:, None] + np.arange(n)
        step = max(1, limit >> n) if method == "exact" else max(1, limit // n)
        chosen += [part[alike(x[part], w_fp[part])] for part in np.split(own, range(step, len(own), step))]
    for lo, hi in zip(starts[~small].tolist(), ends[~small].tolist()):
        chosen.append(lo + np.array(solve(x[lo:hi], w_fp[lo:hi], p, method, spread[lo:hi]), dtype=np.int64))
    return np.sort(np.concatenate(chosen))


def _clashes(x: np.ndarray) -> np.ndarray:
    """Of sets of equally many candidates (set x candidate x series): bits of the candidates that share a cell with each, itself included."""
    bits = np.zeros(x.shape[:2], dtype=np.int64)
    for k in range(x.shape[1]):
        bits |= (x == x[:, k : k + 1]).any(axis=2).astype(np.int64) << k
    return bits


def _taken(mask: np.ndarray, n: int) -> np.ndarray:
    return (mask[:, None] >> np.arange(n)) & 1 == 1


def greedy_alike(literal: bool):
    """The greedy fold of groups of equally many candidates, one candidate of all groups a step; a set is a bit mask."""

    def run(x: np.ndarray, w: np.ndarray) -> np.ndarray:
        n, meets = x.shape[1], _clashes(x)
        clique, blocked, chosen = (np.zeros(len(x), dtype=np.int64) for _ in range(3))

        def emit(rows: np.ndarray) -> np.ndarray:
            best = np.where(_taken(clique[rows], n), w[rows], -1).argmax(axis=1)
            chosen[rows] |= 1 << best
            blocked[rows] |= meets[rows, best]
            clique[rows] = 0
            return best

        for k in range(n):
            free = blocked >> k & 1 == 0
            joins = clique & ~meets[:, k] == 0
            clique[free & joins] |= 1 << k
            closed = np.flatnonzero(free & ~joins)
            won = emit(closed)
            if not literal:
                clique[closed[meets[closed, won] >> k & 1 == 0]] = 1 << k
        if not literal:
            emit(np.flatnonzero(clique))
        return _taken(chosen, n)

    return run


GATED = ALIGN + ", delta double, status string"


def align_gated(series: DataFrame, m: int, p: AlignParams, method: str = "packing", model: str = "locf", most: int = 1000) -> DataFrame:
    """ALIGN rows with delta and status: of a group's alternatives the heaviest whose model error is within ``p.delta``.

    ``packing``: all tie branches of every segment, combined; ``exact``: all conflict-free subsets. Alternatives are
    tried from the heaviest down, at most ``most`` of them. A group without a result has one row, with null x, that
    gives its status.
    """
    if p.delta is None or method not in ("packing", "exact"):
        raise ValueError("the gate needs delta and a composer with alternatives")

    def run(groups: list[pd.DataFrame]):
        made, ranked = [], []
        for pdf in groups:
            times, values, has, first = matrices(pdf, m, p.lam_mode == "cell")
            x, lam, _ = expand_block(times, has, m, p.theta, p.beta, first, first + len(times) - 1, first, p.cap)
            _, w, w_fp = numpy_weights(x, lam, p)
            ranked.append(gate.by_weight(packing(x, w_fp), w_fp) if method == "packing" else free_subsets(x, w_fp))
            made.append((values, first, x, lam, w, w_fp))

        def errors(drawn: list[tuple[int, list[int]]]) -> list[float]:
            return gate.consistencies_of([(*made[k][:2], made[k][2][np.array(chosen, dtype=np.int64)]) for k, chosen in drawn], model)

        for pdf, (_, _, x, lam, w, w_fp), (chosen, delta, status) in zip(groups, made, gate.first_feasible(ranked, errors, p.delta, most)):
            out = _result(pdf["grp"].iloc[0], x, lam, w, w_fp, chosen)
            if not len(out):
                out = pd.DataFrame({"grp": [pdf["grp"].iloc[0]], "pos": [None], "x": [None], "lam": [None], "w": [None], "w_fp": [None]})
            yield out.assign(delta=delta, status=status)

    return groups_together(series.select("grp", "sid", "idx", "ts_us", "val"), run, GATED)


REPORT = "grp string, candidates long, conflict_tests long, cliques long, largest_clique long, looked_ahead long"


def report(series: DataFrame, m: int, p: AlignParams, method: str = "greedy") -> DataFrame:
    """What the fold of each group did: candidates, conflict tests, cliques, the largest of them, tuples looked ahead at."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        times, _, has, first = matrices(pdf, m, p.lam_mode == "cell")
        x, lam, spread = expand_block(times, has, m, p.theta, p.beta, first, first + len(times) - 1, first, p.cap)
        c = Counters()
        fold(x, numpy_weights(x, lam, p)[2], p, method, spread, counters=c)
        return pd.DataFrame([(key[0], c.candidates, c.conflict_tests, c.cliques, c.largest_clique, c.looked_ahead)], columns=[f.split()[0] for f in REPORT.split(", ")])

    return series.select("grp", "sid", "idx", "ts_us", "val").groupBy("grp").applyInPandas(run, REPORT)


# --- exact -----------------------------------------------------------------------------------------------------------


def subsets(cand: DataFrame, m: int, max_candidates: int = 20) -> DataFrame:
    """(grp, mask, w_fp) of every conflict-free subset, by bit mask over the candidates in order.

    A group with more than ``max_candidates`` candidates is an error: the table has 2**k rows.
    """
    order = Window.partitionBy("grp").orderBy("x")
    numbered = cand.select("grp", "x", "w_fp").withColumn("k", F.row_number().over(order) - 1)
    packed = numbered.groupBy("grp").agg(F.array_sort(F.collect_list(F.struct("k", "x", "w_fp"))).alias("c"))
    guarded = packed.withColumn("size", F.when(F.size("c") <= max_candidates, F.size("c")).otherwise(F.raise_error(F.lit(f"more than {max_candidates} candidates"))))
    ruled = guarded.withColumn("conf", F.transform("c", lambda a: F.aggregate(
        F.filter("c", lambda b: (b["k"] != a["k"]) & F.exists(F.zip_with(a["x"], b["x"], lambda u, v: u == v), lambda s: s)),
        F.lit(0).cast("long"), lambda acc, b: acc + F.pow(F.lit(2), b["k"]).cast("long"))))
    masks = ruled.select("grp", "c", "conf", F.explode(F.sequence(F.lit(1).cast("long"), F.pow(F.lit(2), F.col("size")).cast("long") - 1)).alias("mask"))
    free = F.expr("forall(c, e -> shiftright(mask, e.k) & 1 = 0 OR (mask & conf[e.k]) = 0)")
    weight = F.expr("aggregate(c, 0L, (s, e) -> s + IF(shiftright(mask, e.k) & 1 = 1, e.w_fp, 0L))")
    return masks.where(free).select("grp", "mask", weight.alias("w_fp"))


def compose_exact(cand: DataFrame, m: int, delta_of=None, delta: float | None = None, max_candidates: int = 20) -> DataFrame:
    """The heaviest subset of each group (smallest mask wins ties); with ``delta``, the heaviest that the model accepts.

    ``delta_of`` adds the consistency to (grp, mask, w_fp) alternatives (``consistency.subset_deltas``).
    """
    ranked = subsets(cand, m, max_candidates)
    if delta is None:
        return ranked.groupBy("grp").agg(F.max_by("mask", F.struct(F.col("w_fp"), -F.col("mask"))).alias("mask"), F.max("w_fp").alias("w_fp"))
    checked = delta_of(ranked)
    return checked.where(F.col("delta") <= delta).groupBy("grp").agg(F.max_by("mask", F.struct(F.col("w_fp"), -F.col("mask"))).alias("mask"), F.max("w_fp").alias("w_fp"))


def free_subsets(x: np.ndarray, w: np.ndarray, max_candidates: int = 20) -> list[list[int]]:
    """All non-empty conflict-free subsets, heaviest first; of equal weights the one of smaller bit mask."""
    if len(x) > max_candidates:
        raise ValueError(f"more than {max_candidates} candidates")
    conf = [sum(1 << int(k) for k in near) for near in conflict_lists(x)]
    made = [(0, 0, [])]
    for k in range(len(x)):
        made += [(total - int(w[k]), mask | 1 << k, [*own, k]) for total, mask, own in made if not mask & conf[k]]
    return [own for _, _, own in sorted(made[1:], key=lambda s: s[:2])]


def conflict_lists(x: np.ndarray) -> list[np.ndarray]:
    """The candidates that share a cell with each candidate, itself included, by an index of cells."""
    near: list[list[np.ndarray]] = [[] for _ in range(len(x))]
    for j in range(x.shape[1]):
        order = np.argsort(x[:, j], kind="stable")
        for held in np.split(order, np.flatnonzero(np.diff(x[order, j])) + 1):
            for k in held.tolist():
                near[k].append(held)
    return [np.unique(np.concatenate(parts)) for parts in near]


def segments_of(x: np.ndarray) -> list[tuple[int, int]]:
    """Runs of candidates between which nothing conflicts: a cut where no earlier row reaches the next lead."""
    if not len(x):
        return []
    top, low = np.maximum.accumulate(x.max(axis=1)), np.minimum.accumulate(x.min(axis=1)[::-1])[::-1]
    cuts = np.flatnonzero(top[:-1] < low[1:]) + 1
    return list(zip(np.r_[0, cuts].tolist(), np.r_[cuts, len(x)].tolist()))


def _segments(x: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``segments_of`` of groups side by side (``of``: the group of each candidate): where segments start and end."""
    top, low = x.max(axis=1, initial=0), x.min(axis=1, initial=np.iinfo(np.int64).max)
    shift = of * (int(top.max(initial=0)) - int(low.min(initial=0)) + 1)  # no row of a group lies beyond one of the next
    top, low = np.maximum.accumulate(top + shift), np.minimum.accumulate((low + shift)[::-1])[::-1]
    starts = np.append(0, np.flatnonzero(top[:-1] < low[1:]) + 1)[: len(x)]
    return starts, np.append(starts[1:], len(x))[: len(starts)]


def exact_alike(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """The heaviest conflict-free subset of segments of equally many candidates, the smallest mask of equal ones: all such
    subsets are made, one candidate of all segments a step."""
    n, meets = x.shape[1], _clashes(x)
    seg, mask, got = np.arange(len(x)), np.zeros(len(x), dtype=np.int64), np.zeros(len(x), dtype=np.int64)
    for k in range(n):
        more = np.flatnonzero(mask & meets[seg, k] == 0)
        seg, mask, got = np.append(seg, seg[more]), np.append(mask, mask[more] | 1 << k), np.append(got, got[more] + w[seg[more], k])
    order = np.lexsort((mask, -got, seg))
    return _taken(mask[order[np.flatnonzero(np.diff(seg[order], prepend=-1))]], n)


def exact_bnb(x: np.ndarray, w: np.ndarray, limit: int = 2_000_000) -> list[int]:
    """Exact by branch and bound within independent segments; the bound is the weight still to come. Of equal weights the
    subset of smaller bit mask: the masks stand behind the weights, in bits of their own."""
    out: list[int] = []
    for lo, hi in segments_of(x):
        part, order = x[lo:hi], np.argsort(-w[lo:hi], kind="stable")
        weight = [(v << hi - lo) - (1 << k) for k, v in enumerate(w[lo:hi].tolist())]
        conf = [set(near.tolist()) for near in conflict_lists(part)]
        suffix = [0]
        for k in order[::-1].tolist():
            suffix.insert(0, suffix[0] + max(weight[k], 0))
        best, best_set, steps = -1, [], 0
        stack = [(0, 0, frozenset(), ())]
        while stack:
            steps += 1
            if steps > limit:
                raise RuntimeError("branch and bound limit reached: use an approximate composer")
            at, got, blocked, taken = stack.pop()
            if got > best:
                best, best_set = got, taken
            if at == hi - lo or got + suffix[at] <= best:
                continue
            k = int(order[at])
            stack.append((at + 1, got, blocked, taken))
            if k not in blocked:
                stack.append((at + 1, got + weight[k], blocked | conf[k], (*taken, k)))
        out += [lo + k for k in best_set]
    return out


# --- weighted set packing ----------------------------------------------------------------------------------------------


def packing_start(x: np.ndarray, w: np.ndarray) -> list[int]:
    """Heaviest first, skipping conflicts; equal weights in order."""
    used = [set() for _ in range(x.shape[1])] if len(x) else []
    out = []
    for k in np.argsort(-w, kind="stable").tolist():
        row = x[k].tolist()
        if not any(v in u for v, u in zip(row, used)):
            out.append(k)
            for v, u in zip(row, used):
                u.add(v)
    return sorted(out)


def _swaps(x: np.ndarray, w: np.ndarray, conf: list[np.ndarray], now: set[int], centre: int, most: int):
    """Conflict-free sets Q of neighbours of ``centre`` with what they push out of the result."""
    near = [int(k) for k in conf[centre] if int(k) not in now]
    for size in range(1, most + 1):
        for q in itertools.combinations(near, size):
            if all(not (x[a] == x[b]).any() for a, b in itertools.combinations(q, 2)):
                out = {int(i) for k in q for i in conf[k] if int(i) in now}
                yield q, out


def packing(x: np.ndarray, w: np.ndarray, max_branches: int = 4096, swap_size: int | None = None) -> list[list[list[int]]]:
    """Local search from the heaviest-first start: for each independent segment all branches' results, heaviest first.

    A swap replaces the members it hits when its weight is larger; the best ratio is taken (compared exactly, as
    integers), and swaps of equal best ratio are all followed. A segment with more than ``max_branches`` branches is an
    error. ``gate.by_weight`` combines the segments' results.
    """
    per_segment: list[list[list[int]]] = []
    for lo, hi in segments_of(x):
        part, weight = x[lo:hi], [int(v) for v in w[lo:hi]]
        conf = conflict_lists(part)
        start = frozenset(packing_start(part, w[lo:hi]))
        live, done, seen = [start], [], {start}
        while live:
            now = live.pop()
            moves = best_swaps(part, weight, conf, set(now), sorted(now), swap_size or part.shape[1])
            if not moves:
                done.append(now)
            for q, out in moves:
                nxt = frozenset((now - out) | set(q))
                if nxt not in seen:
                    if len(seen) == max_branches:
                        raise RuntimeError(f"more than {max_branches} branches of equal ratio in one segment: raise max_branches")
                    seen.add(nxt)
                    live.append(nxt)
        done.sort(key=lambda c: (-sum(weight[k] for k in c), sorted(c)))
        per_segment.append([sorted(lo + k for k in c) for c in done])
    return per_segment


def best_swaps(x: np.ndarray, weight: list[int], conf: list[np.ndarray], now: set[int], centres: list[int], most: int) -> list[tuple[tuple[int, ...], set[int]]]:
    """All swaps around some members that have the best ratio above 1."""
    best, moves = (1, 1), []
    for centre in centres:
        for q, out in _swaps(x, weight, conf, now, centre, most):
            a, b = sum(weight[k] for k in q), sum(weight[k] for k in out)
            if a > b:
                left, right = a * best[1], best[0] * b
                if left > right:
                    best, moves = (a, b), [(q, out)]
                elif left == right:
                    moves.append((q, out))
    return moves


def packing_parallel(x: np.ndarray, w: np.ndarray, swap_size: int | None = None) -> list[int]:
    """Local search in rounds: of each member's best improving swap all that don't touch one another are applied at once.

    Swaps are taken by ratio (compared exactly); one is held back when it shares a candidate, or a conflict, with one
    already taken in the round. Swaps have up to m candidates, as in the serial search. The weight rises every round,
    so it ends, and then no swap improves; which of several such ends is reached may differ from the serial search.
    """
    out: list[int] = []
    for lo, hi in segments_of(x):
        part, weight = x[lo:hi], [int(v) for v in w[lo:hi]]
        conf = conflict_lists(part)
        now = set(packing_start(part, w[lo:hi]))
        while True:
            moves = []
            for centre in sorted(now):
                moves += [(sum(weight[k] for k in q), sum(weight[k] for k in gone), q, gone) for q, gone in best_swaps(part, weight, conf, now, [centre], swap_size or part.shape[1])[:1]]
            if not moves:
                break
            touched: set[int] = set()
            for a, b, q, gone in sorted(moves, key=lambda mv: (-Fraction(mv[0], mv[1]), mv[2])):
                reach = {int(i) for k in q for i in conf[k]} | set(q) | gone
                if not reach & touched:
                    touched |= reach
                    now = (now - gone) | set(q)
        out += [lo + k for k in sorted(now)]
    return out


# --- audit ---------------------------------------------------------------------------------------------------------------


def cells(aligned: DataFrame) -> DataFrame:
    """(grp, pos, sid, idx) of every cell of a result."""
    return aligned.select("grp", "pos", F.posexplode("x").alias("s", "idx")).select("grp", "pos", (F.col("s") + 1).cast("int").alias("sid"), "idx")


def violations_unique(aligned: DataFrame) -> DataFrame:
    return cells(aligned).groupBy("grp", "sid", "idx").agg(F.count("*").alias("n")).where("n > 1")


def materialise(aligned: DataFrame, series: DataFrame) -> DataFrame:
    """(grp, pos, sid, idx, ts_us, val): the cells joined back late, only for tuples that were chosen."""
    return cells(aligned).join(series, ["grp", "sid", "idx"], "left").select("grp", "pos", "sid", "idx", "ts_us", "val")


def align_to_wide(aligned: DataFrame, series: DataFrame, m: int) -> DataFrame:
    wide = materialise(aligned, series).groupBy("grp", "pos").agg(
        *[F.max(F.when(F.col("sid") == j, F.col("idx"))).alias(f"i{j}") for j in range(1, m + 1)],
        *[F.max(F.when(F.col("sid") == j, F.col("ts_us"))).alias(f"t{j}") for j in range(1, m + 1)],
        *[F.max(F.when(F.col("sid") == j, F.col("val"))).alias(f"v{j}") for j in range(1, m + 1)])
    return wide


def validate(aligned: DataFrame, series: DataFrame, p: AlignParams, delta_df: DataFrame | None = None) -> DataFrame:
    """(grp, rule, n_bad) of a result against uniqueness, theta, beta and delta; empty where all hold."""
    full = materialise(aligned, series)
    spread = full.groupBy("grp", "pos").agg((F.max("ts_us") - F.min("ts_us")).alias("s"), (F.max("idx") - F.min("idx")).alias("f"))
    parts = [
        violations_unique(aligned).select("grp", F.lit("unique").alias("rule")),
        spread.where(F.coalesce("s", F.lit(0)) > p.theta).select("grp", F.lit("theta").alias("rule")),
        spread.where(F.col("f") > p.beta).select("grp", F.lit("beta").alias("rule")),
    ]
    if delta_df is not None and p.delta is not None:
        parts.append(delta_df.where(F.col("delta") > p.delta).select("grp", F.lit("delta").alias("rule")))
    bad = parts[0]
    for part in parts[1:]:
        bad = bad.unionByName(part)
    return bad.groupBy("grp", "rule").agg(F.count("*").alias("n_bad"))
