"""Candidate tuples under the time and position constraints, by seven strategies with one result.

CAND rows: grp, x (row number per series), lam, d, phi, spread_us, w, w_fp. The
default cuts each series into blocks of leads with a halo of beta rows, so that
few rows travel and every block makes its candidates in its own task. ``lead``
stays on the JVM: it sends every row to the leads it may follow, and one shuffle
by (grp, lead) brings together all cells of a candidate. In all of them prefixes
that break a constraint are dropped between the series and never extended.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from alignspark.functions import measures as M
from alignspark.params import AlignParams

COLUMNS = ["grp", "x", "lam", "d", "phi", "spread_us", "w", "w_fp"]


def present(series: DataFrame, p: AlignParams):
    """1 where a cell counts towards lambda."""
    seen = F.col("val").isNotNull()
    if p.lam_mode == "cell":
        seen = seen & F.col("ts_us").isNotNull()
    return seen.cast("int")


def _cell(series: DataFrame, p: AlignParams) -> DataFrame:
    return series.select("grp", "sid", "idx", "ts_us", present(series, p).alias("has"))


def finish(df: DataFrame, m: int, p: AlignParams) -> DataFrame:
    """Adds the measures to rows of (grp, x, lam, lo, hi)."""
    xs = [F.col("x")[j] for j in range(m)]
    d = sum((F.abs(xs[i] - xs[j]) for i in range(m) for j in range(i + 1, m)), F.lit(0)).cast("long") if m <= 4 else M.pairwise_distance(F.col("x"), m)
    df = df.withColumns({"d": d, "phi": M.phi_spread(F.col("x")), "spread_us": F.coalesce(F.col("hi") - F.col("lo"), F.lit(0)).cast("long")})
    df = df.withColumn("w", M.weight(F.col("lam"), F.col("d"), p))
    return df.withColumn("w_fp", M.fixed(F.col("w"))).select(*COLUMNS)


def _expand(df: DataFrame, m: int, p: AlignParams, anchored: bool = False) -> DataFrame:
    """From arrays a1..am of cells to candidates, one generator a series with pruning between."""
    keys = ["grp", "anchor"] if anchored else ["grp"]
    rest = [f"a{j}" for j in range(2, m + 1)]
    df = df.select(*keys, *rest, F.explode("a1").alias("c")).select(
        *keys, *rest, F.array("c.idx").alias("x"), F.col("c.idx").alias("i_lo"), F.col("c.idx").alias("i_hi"),
        F.col("c.ts_us").alias("lo"), F.col("c.ts_us").alias("hi"), F.col("c.has").alias("lam"),
    )
    for j in range(2, m + 1):
        rest = [f"a{k}" for k in range(j + 1, m + 1)]
        df = df.select("*", F.explode(f"a{j}").alias("c")).select(
            *keys, *rest, F.concat("x", F.array("c.idx")).alias("x"),
            F.least("i_lo", "c.idx").alias("i_lo"), F.greatest("i_hi", "c.idx").alias("i_hi"),
            F.least("lo", "c.ts_us").alias("lo"), F.greatest("hi", "c.ts_us").alias("hi"), (F.col("lam") + F.col("c.has")).alias("lam"),
        ).where((F.col("i_hi") - F.col("i_lo") <= p.beta) & (F.coalesce(F.col("hi") - F.col("lo"), F.lit(0)) <= p.theta))
    if anchored:
        df = df.where("i_lo = anchor")
    return finish(df, m, p)


def _arrays(sent: DataFrame, key: str, m: int) -> DataFrame:
    """Sorted cell arrays per series of each (grp, key)."""
    cell = F.struct("idx", "ts_us", "has")
    return sent.groupBy("grp", key).agg(*[F.array_sort(F.collect_list(F.when(F.col("sid") == j, cell))).alias(f"a{j}") for j in range(1, m + 1)])


def lead(series: DataFrame, m: int, p: AlignParams) -> DataFrame:
    cells = _cell(series, p)
    leads = F.when(F.col("sid") == 1, F.array("idx")).otherwise(F.sequence(F.col("idx") - p.beta, F.col("idx") + p.beta))
    return _expand(_arrays(cells.withColumn("lead", F.explode(leads)), "lead", m), m, p)


def prefix_counts(series: DataFrame, m: int, p: AlignParams) -> DataFrame:
    """(level, made, kept): prefixes of two and more series that the scan makes, and those that break no constraint.

    The difference is what the scan skips, with everything that would have followed.
    """
    cells = _cell(series, p)
    leads = F.when(F.col("sid") == 1, F.array("idx")).otherwise(F.sequence(F.col("idx") - p.beta, F.col("idx") + p.beta))
    rows = _arrays(cells.withColumn("lead", F.explode(leads)), "lead", m)
    part = rows.select(*[f"a{j}" for j in range(2, m + 1)], F.explode("a1").alias("c"))
    part = part.select(*[f"a{j}" for j in range(2, m + 1)], F.col("c.idx").alias("i_lo"), F.col("c.idx").alias("i_hi"), F.col("c.ts_us").alias("lo"), F.col("c.ts_us").alias("hi"))
    out = None
    for j in range(2, m + 1):
        part = part.select("*", F.explode(f"a{j}").alias("c")).select(
            *[f"a{k}" for k in range(j + 1, m + 1)], F.least("i_lo", "c.idx").alias("i_lo"), F.greatest("i_hi", "c.idx").alias("i_hi"),
            F.least("lo", "c.ts_us").alias("lo"), F.greatest("hi", "c.ts_us").alias("hi"))
        holds = (F.col("i_hi") - F.col("i_lo") <= p.beta) & (F.coalesce(F.col("hi") - F.col("lo"), F.lit(0)) <= p.theta)
        level = part.agg(F.lit(j).alias("level"), F.count("*").alias("made"), F.count_if(holds).alias("kept"))
        out = level if out is None else out.unionByName(level)
        part = part.where(holds)
    return out


def anchor(series: DataFrame, m: int, p: AlignParams) -> DataFrame:
    """Rows go to the anchors (smallest row number) they may belong to; a candidate is made at its own anchor only."""
    cells = _cell(series, p)
    sent = cells.withColumn("anchor", F.explode(F.sequence(F.col("idx") - p.beta, F.col("idx"))))
    return _expand(_arrays(sent, "anchor", m), m, p, anchored=True)


def join(series: DataFrame, m: int, p: AlignParams) -> DataFrame:
    """A chain of band joins on row number buckets of width beta + 1, with the band itself as residual."""
    cells = _cell(series, p)
    width = p.beta + 1
    one = cells.where("sid = 1")
    df = one.select("grp", F.array("idx").alias("x"), F.col("idx").alias("i1"), F.col("idx").alias("i_lo"), F.col("idx").alias("i_hi"),
                    F.col("ts_us").alias("lo"), F.col("ts_us").alias("hi"), F.col("has").alias("lam"))
    for j in range(2, m + 1):
        other = cells.where(F.col("sid") == j).select(F.col("grp").alias("g"), F.floor(F.col("idx") / width).alias("bk"), F.col("idx").alias("i"), F.col("ts_us").alias("t"), F.col("has").alias("h"))
        near = df.withColumn("bk", F.explode(F.array(*[F.floor(F.col("i1") / width) + k for k in (-1, 0, 1)])))
        met = near.join(other, (F.col("grp") == F.col("g")) & (near["bk"] == other["bk"]) & (F.abs(F.col("i") - F.col("i1")) <= p.beta))
        df = met.select("grp", F.concat("x", F.array("i")).alias("x"), "i1", F.least("i_lo", "i").alias("i_lo"), F.greatest("i_hi", "i").alias("i_hi"),
                        F.least("lo", "t").alias("lo"), F.greatest("hi", "t").alias("hi"), (F.col("lam") + F.col("h")).alias("lam"))
        df = df.where((F.col("i_hi") - F.col("i_lo") <= p.beta) & (F.coalesce(F.col("hi") - F.col("lo"), F.lit(0)) <= p.theta))
    return finish(df, m, p)


def naive(series: DataFrame, m: int, p: AlignParams, cap: int = 20_000) -> DataFrame:
    """Every combination, then the constraints: what pruning avoids. Refuses groups beyond ``cap`` combinations."""
    cells = _cell(series, p)
    sizes = cells.groupBy("grp").agg(*[F.count_if(F.col("sid") == j).cast("double").alias(f"n{j}") for j in range(1, m + 1)])
    total = sizes.agg(F.max(math.prod(F.col(f"n{j}") for j in range(1, m + 1)))).first()[0] or 0
    if total > cap:
        raise ValueError(f"{total:.0f} combinations; the naive strategy is for at most {cap}")
    cell = F.struct("idx", "ts_us", "has")
    arrays = cells.groupBy("grp").agg(*[F.array_sort(F.collect_list(F.when(F.col("sid") == j, cell))).alias(f"a{j}") for j in range(1, m + 1)])
    for j in range(1, m + 1):
        arrays = arrays.withColumn(f"c{j}", F.explode(f"a{j}"))
    c = [F.col(f"c{j}") for j in range(1, m + 1)]
    full = arrays.select("grp", F.array(*[k["idx"] for k in c]).alias("x"), F.least(*[k["ts_us"] for k in c]).alias("lo"), F.greatest(*[k["ts_us"] for k in c]).alias("hi"), sum((k["has"] for k in c[1:]), c[0]["has"]).alias("lam"))
    return finish(full, m, p).where((F.col("phi") <= p.beta) & (F.col("spread_us") <= p.theta))


# --- in one task ------------------------------------------------------------------------------------------------------


def expand_block(times: np.ndarray, has: np.ndarray, m: int, theta: int, beta: int, lo: int, hi: int, first: int = 1, cap: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Candidates led by rows lo..hi (row numbers), in lexicographic order: x, lambda, time spread.

    ``times`` (rows x series, NaN missing) and ``has`` (1 present, 0 missing, -1 no such row) hold rows first, first + 1, ...
    Prefix after prefix over all leads at once; a broken prefix goes no further.
    """
    rows = len(times)
    x = np.arange(lo, hi + 1, dtype=np.int64)[:, None]
    x = x[(x[:, 0] >= first) & (x[:, 0] < first + rows)]
    x = x[has[x[:, 0] - first, 0] >= 0]
    t = times[x[:, 0] - first, 0]
    low, high, lam = t.copy(), t.copy(), has[x[:, 0] - first, 0].astype(np.int64)
    i_lo, i_hi = x[:, 0].copy(), x[:, 0].copy()
    shift = np.arange(-beta, beta + 1)
    for j in range(1, m):
        n = len(x)
        i = (x[:, :1] + shift[None, :]).ravel()
        back = np.repeat(np.arange(n), len(shift))
        ok = (i >= first) & (i < first + rows)
        a, b = np.minimum(i_lo[back], i), np.maximum(i_hi[back], i)
        ok &= b - a <= beta
        ok[ok] = has[i[ok] - first, j] >= 0
        i, back, a, b = i[ok], back[ok], a[ok], b[ok]
        t = times[i - first, j]
        lo_t, hi_t = np.fmin(low[back], t), np.fmax(high[back], t)
        ok = ~(hi_t - lo_t > theta)
        i, back = i[ok], back[ok]
        x = np.concatenate([x[back], i[:, None]], axis=1)
        low, high, i_lo, i_hi = lo_t[ok], hi_t[ok], a[ok], b[ok]
        lam = lam[back] + has[i - first, j]
        if cap and len(x) > cap:
            raise ValueError(f"more than {cap} prefixes at series {j + 1}: lower beta (now {beta}) or the block size")
    return x, lam, np.nan_to_num(high - low, nan=0.0).astype(np.int64)


def matrices(pdf: pd.DataFrame, m: int, by_cell: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """times, values, presence (rows x m) and the first row number of one group's long rows."""
    if not len(pdf):
        return np.zeros((0, m)), np.zeros((0, m)), np.zeros((0, m), dtype=np.int8), 1
    first, last = int(pdf["idx"].min()), int(pdf["idx"].max())
    times = np.full((last - first + 1, m), np.nan)
    values = times.copy()
    r, c = pdf["idx"].to_numpy(dtype=np.int64) - first, pdf["sid"].to_numpy(dtype=np.int64) - 1
    times[r, c] = pd.to_numeric(pdf["ts_us"]).to_numpy(dtype=float, na_value=np.nan)
    values[r, c] = pd.to_numeric(pdf["val"]).to_numpy(dtype=float, na_value=np.nan)
    has = np.full(times.shape, -1, dtype=np.int8)
    seen = ~np.isnan(values[r, c])
    has[r, c] = seen & ~np.isnan(times[r, c]) if by_cell else seen
    return times, values, has, first


def spans(idx: np.ndarray, starts: np.ndarray, gap: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of groups side by side, with a place for each row number from their first to their last
    and ``gap`` places behind them: first number, size and
    first place of each group, and the place of each row."""
    first = np.minimum.reduceat(idx, starts)
    size = np.maximum.reduceat(idx, starts) - first + 1
    base = np.cumsum(size + gap) - size - gap
    return first, size, base, idx + np.repeat(base - first, np.diff(np.append(starts, len(idx))))


def numpy_weights(x: np.ndarray, lam: np.ndarray, p: AlignParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    m = x.shape[1]
    d = np.zeros(len(x), dtype=np.int64)
    for i in range(m):
        for j in range(i + 1, m):
            d += np.abs(x[:, i] - x[:, j])
    w = (p.k1 * lam * (lam - 1) / 2 + p.b) / (p.k2 * d + p.c)
    return d, w, np.floor(w * M.SCALE + 0.5).astype(np.int64)


def _frame(grp: str, x: np.ndarray, lam: np.ndarray, spread: np.ndarray, p: AlignParams) -> pd.DataFrame:
    d, w, w_fp = numpy_weights(x, lam, p)
    phi = x.max(axis=1) - x.min(axis=1) if len(x) else np.zeros(0, np.int64)
    return pd.DataFrame({"grp": grp, "x": pd.Series(list(x), dtype=object), "lam": lam.astype("int32"), "d": d, "phi": phi, "spread_us": spread, "w": w, "w_fp": w_fp})


CAND = "grp string, x array<long>, lam int, d long, phi long, spread_us long, w double, w_fp long"


def odometer(series: DataFrame, m: int, p: AlignParams, size: int = 2000) -> DataFrame:
    """The scan of one index per series, last fastest, that jumps over what a violated pair rules out; one task a block of leads."""

    def scan(key, pdf: pd.DataFrame) -> pd.DataFrame:
        grp, blk = key
        times, _, has, first = matrices(pdf, m, p.lam_mode == "cell")
        n, theta, beta = len(times), p.theta, p.beta
        clock, seen = times.T.tolist(), has.T.tolist()
        out, lam, spread = [], [], []
        nan = float("nan")
        cur, stop = [0] * m, [0] * m
        low, high = [nan] * m, [nan] * m
        level, cur[0], stop[0] = 0, max(0, blk * size + 1 - first) - 1, min(n, (blk + 1) * size + 1 - first)
        while level >= 0:
            k = cur[level] = cur[level] + 1
            if k >= stop[level]:
                level -= 1
                continue
            if seen[level][k] < 0:
                continue
            a = b = clock[level][k]
            if level:
                lo, hi = low[level - 1], high[level - 1]
                if a != a:
                    a, b = lo, hi
                elif lo == lo:
                    a, b = min(lo, a), max(hi, b)
                if b - a > theta:  # the pair breaks theta: no later series can mend it
                    continue
            low[level], high[level] = a, b
            if level == m - 1:
                out.append([c + first for c in cur])
                lam.append(sum(seen[j][c] for j, c in enumerate(cur)))
                spread.append(0 if a != a else int(b - a))
            else:
                level += 1
                top, least = max(cur[:level]), min(cur[:level])
                cur[level], stop[level] = max(0, top - beta) - 1, min(n, least + beta + 1)
        x = np.array(out, dtype=np.int64).reshape(-1, m)
        return _frame(grp, x, np.array(lam, dtype=np.int64), np.array(spread, dtype=np.int64), p)

    return with_blocks(series, size, p.beta).groupBy("grp", "blk").applyInPandas(scan, CAND)


def block(series: DataFrame, m: int, p: AlignParams, size: int = 2000) -> DataFrame:
    """Halo blocks: each block of leads gets beta more rows on either side and makes its candidates in its own task."""
    return by_block(series, m, p, lambda grp, x, lam, spread: _frame(grp, x, lam, spread, p), CAND, size)


def by_block(series: DataFrame, m: int, p: AlignParams, use, schema: str, size: int = 2000) -> DataFrame:
    """``use(grp, x, lam, spread)`` of every block's candidates: what only counts them returns no candidate."""

    def make(key, pdf: pd.DataFrame) -> pd.DataFrame:
        grp, blk = key
        times, _, has, first = matrices(pdf, m, p.lam_mode == "cell")
        return use(grp, *expand_block(times, has, m, p.theta, p.beta, blk * size + 1, (blk + 1) * size, first, p.cap))

    return with_blocks(series, size, p.beta).groupBy("grp", "blk").applyInPandas(make, schema)


def with_blocks(series: DataFrame, size: int, halo_before: int, halo_after: int | None = None) -> DataFrame:
    """Rows by block of ``size`` row numbers, each also sent to the neighbours whose halo holds it."""
    after = halo_before if halo_after is None else halo_after
    low, high = F.floor((F.col("idx") - 1 - after) / size), F.floor((F.col("idx") - 1 + halo_before) / size)
    return series.withColumn("blk", F.explode(F.sequence(F.greatest(low, F.lit(0)), high)))


STRATEGIES = {"lead": lead, "anchor": anchor, "join": join, "naive": naive, "odometer": odometer, "block": block}


def candidates(series: DataFrame, m: int, p: AlignParams, strategy: str = "block") -> DataFrame:
    """All tuples of one cell per series that satisfy theta and beta."""
    return STRATEGIES[strategy](series, m, p)


def flat(cand: DataFrame, m: int) -> DataFrame:
    """CAND with x as columns i1..im and the weight rounded, for comparison with SQL."""
    return cand.select("grp", *[F.col("x")[j].alias(f"i{j + 1}") for j in range(m)], F.col("lam").cast("long").alias("lam"), "d", "phi", "spread_us", F.round("w", 6).alias("w"), "w_fp")


def profile(cand: DataFrame) -> DataFrame:
    """Counts by lambda, distance and index spread."""
    return cand.groupBy("lam", "d", "phi").agg(F.count("*").alias("n"), F.sum("w_fp").alias("w_fp"))


def sql(m: int, p: AlignParams, source: str = "series") -> str:
    """CTE ``cand`` over ``series``, for DuckDB: the band join chain and the constraints as they are defined."""
    def prune(j: int) -> str:
        """With many series the pairs' constraints go into the joins."""
        return "" if m <= 4 else "".join(f" AND abs(s{j}.idx - s{k}.idx) <= {p.beta} AND coalesce(abs(s{j}.ts_us - s{k}.ts_us), 0) <= {p.theta}" for k in range(1, j))

    join_ = " ".join(f"JOIN {source} s{j} ON s{j}.grp = s1.grp AND s{j}.sid = {j} AND s{j}.idx BETWEEN s1.idx - {p.beta} AND s1.idx + {p.beta}{prune(j)}" for j in range(2, m + 1))
    i, t, v = ([f"s{j}.{c}" for j in range(1, m + 1)] for c in ("idx", "ts_us", "val"))
    d = " + ".join(f"abs(i{a} - i{b})" for a in range(1, m + 1) for b in range(a + 1, m + 1))
    return f"""raw AS (SELECT s1.grp AS grp, {', '.join(f'{c} AS i{k + 1}' for k, c in enumerate(i))},
  ({' + '.join(f'({c} IS NOT NULL)::INT' for c in v)})::BIGINT AS lam, coalesce(greatest({', '.join(t)}) - least({', '.join(t)}), 0)::BIGINT AS spread_us,
  (greatest({', '.join(i)}) - least({', '.join(i)}))::BIGINT AS phi FROM {source} s1 {join_} WHERE s1.sid = 1),
cand0 AS (SELECT *, ({d})::BIGINT AS d FROM raw WHERE phi <= {p.beta} AND spread_us <= {p.theta}),
cand AS (SELECT *, ({p.k1!r} * lam * (lam - 1) / 2 + {p.b!r}) / ({p.k2!r} * d + {p.c!r}) AS w,
  round(({p.k1!r}::DOUBLE * lam * (lam - 1) / 2 + {p.b!r}::DOUBLE) / ({p.k2!r}::DOUBLE * d + {p.c!r}::DOUBLE) * 1000000000.0)::BIGINT AS w_fp FROM cand0)"""
