"""Sharding by sampled splitters: size-weighted key samples, quantile boundaries, range partition.

Rows are ordered by a key (here: a digest of the text, the id, so equal
texts stand together, and a row number that is written down once and parts rows
which repeat each other; they can change places without changing the result). A size-weighted sample of keys gives quantile
boundaries; every row falls into one range by binary search over them; ranges
that turn out overfull are subdivided by a finer sample of their own keys.
Exact sums per range then give each row its position in the whole order, and
the position decides shard and slot. Only the bounded sample and one sum per
range ever reach the driver.

Laws
  ``bytes``  a row goes where the middle of its bytes falls: shard sizes differ
             from the mean by less than one row's size.
  ``rows``   a row goes by its rank: counts differ by one at most.

Null texts count as empty (size 1, checksum of no bytes); a null id comes before
others of its text. Repeated rows are placed like any others, and a boundary may
fall among them. A very long text takes a shard's share and more as one row. An
empty table gives an empty result. Columns other than id and text are ignored,
whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from alignspark.llm.common import stash, table

#: Rows in a range; fewest and most ranges (boundaries are part of the plan); sampled keys for each, and how much over
#: its share a range may be before it is cut.
RANGE_ROWS, FEWEST, MOST = 200_000, 64, 8192
SAMPLES, OVERFULL, ROUNDS = 24, 4.0, 3


def _unit(*cols: Column) -> Column:
    """A number in [0, 1) from a hash: the same for a row in every run and partitioning."""
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 40)).cast("double") / float(1 << 40)


def keyed(docs: DataFrame) -> DataFrame:
    """One slim row per document: id, size, checksum and the two parts of the order key."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        F.col("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.md5(text).alias("text_key"),
        F.monotonically_increasing_id().alias("turn"),
    )


KEY = ("text_key", "doc_id", "turn")


def _key(cols=KEY) -> Column:
    return F.struct(*[F.col(c) for c in cols])


def _literal(row) -> str:
    number = "CAST(NULL AS BIGINT)" if row[1] is None else f"{row[1]}L"
    return f"struct('{row[0]}' AS {KEY[0]}, {number} AS {KEY[1]}, {row[2]}L AS {KEY[2]})"


def _place(key: tuple) -> tuple:
    """A key's place in the order; nulls first."""
    return key[0], key[1] is not None, key[1], key[2]


def sample_keys(rows: DataFrame, total: int, wanted: int, seed: int) -> list[tuple]:
    """Keys drawn with a chance in proportion to size (about ``wanted`` of them), with the weight each stands for."""
    step = max(1.0, total / wanted)
    drawn = rows.where(_unit(*map(F.col, KEY), F.lit(seed)) < F.col("size") / F.lit(step))
    got = drawn.select(*KEY, F.greatest(F.col("size").cast("double"), F.lit(step)).alias("weight")).collect()
    return sorted(map(tuple, got), key=_place)


def quantiles(sample: list[tuple], parts: int) -> list[tuple]:
    """Boundaries that cut the sampled weight into ``parts`` equal shares."""
    total, run, cuts = sum(r[3] for r in sample), 0.0, []
    share = total / max(1, parts)
    for key in sample:
        before, run = run, run + key[3]
        if int(run / share) > int(before / share) and (not cuts or cuts[-1] != key[:3]):
            cuts.append(key[:3])
    return cuts


def range_of(splitters: list[tuple]) -> Column:
    """How many splitters are not above the row's key: a binary search written as nested halving."""
    if not splitters:
        return F.lit(0)
    array = F.expr(f"array({', '.join(map(_literal, splitters))})")
    steps = [1 << b for b in reversed(range(len(splitters).bit_length()))]
    found = F.lit(0)
    key = _key()
    return F.aggregate(
        F.array(*[F.lit(s) for s in steps]),
        found,
        lambda low, step: F.when(
            (low + step <= len(splitters)) & (F.get(array, low + step - 1) <= key), low + step
        ).otherwise(low),
    )


def ranged(rows: DataFrame, ranges: int | None = None) -> tuple[DataFrame, list[tuple[int, int, int]]]:
    """Rows with their range, and (range, rows, bytes) of each range in order."""
    n_rows, total = rows.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = ranges or min(MOST, max(FEWEST, n_rows // RANGE_ROWS))
    splitters = quantiles(sample_keys(rows, total, ranges * SAMPLES, 1), ranges) if total else []
    share = total / max(1, ranges)
    for turn in range(ROUNDS + 1):
        placed = rows.withColumn("part", range_of(splitters))
        sums = sorted(tuple(r) for r in placed.groupBy("part").agg(F.count("*"), F.sum("size")).collect())
        over = [p for p, n, b in sums if b > OVERFULL * share and n > 1]
        if not over or turn == ROUNDS or len(splitters) > 4 * ranges:
            return placed, sums
        finer: list[tuple] = []
        for part, _, size in [s for s in sums if s[0] in over]:
            inside = placed.where(F.col("part") == part).drop("part")
            parts = int(size / share) + 1
            finer += quantiles(sample_keys(inside, size, parts * SAMPLES, turn + 2), parts)
        known = set(splitters)
        splitters = sorted(known | set(finer), key=_place)


def shard(docs: DataFrame, shards: int = 8, law: str = "bytes") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of ``docs``."""
    if law not in ("bytes", "rows"):
        raise ValueError(f"unknown law {law!r}")
    rows = stash(keyed(docs), "shard-keys")
    placed, sums = ranged(rows)
    offsets, n, size = {}, 0, 0
    for part, count, volume in sums:
        offsets[part] = (n, size)
        n, size = n + count, size + volume
    starts = [offsets.get(p, (0, 0)) for p in range(max(offsets, default=0) + 1)]
    base = F.get(F.expr(f"array({', '.join(f'struct({a}L AS n, {b}L AS b)' for a, b in starts)})"), F.col("part"))
    order = Window.partitionBy("part").orderBy(*KEY)
    ranked = placed.withColumns({
        "rank": F.row_number().over(order) - 1 + base["n"],
        "above": F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size") + base["b"],
    })
    if law == "bytes":
        at = F.expr(f"((2 * above + size) * {shards}) div (2 * {max(size, 1)})")
    else:
        at = F.expr(f"(rank * {shards}) div {max(n, 1)}")
    ranked = stash(ranked.withColumn("shard", F.least(at, F.lit(shards - 1)).cast("int")), "shard-ranks")
    lows = {r[0]: r[1] for r in ranked.groupBy("shard").agg(F.min("rank")).collect()}
    low = F.get(F.array(*[F.lit(lows.get(s, 0)).cast("long") for s in range(shards)]), F.col("shard"))
    return ranked.select(
        "doc_id", "size", "text_crc32", F.lit(law).alias("law"), "shard",
        (F.col("rank") - low).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents into eight shards of near-equal bytes."""
    return shard(table(spark, sf_dir, "documents"), 8, "bytes")
