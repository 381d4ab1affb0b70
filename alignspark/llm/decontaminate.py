"""Benchmark decontamination by pigeonhole edit matching.

With an error budget of ``k`` edits an item is cut into ``k + 1`` pieces: a
passage within the budget holds at least one piece unchanged. All pieces of all
items go into one Aho-Corasick automaton, every document is streamed through it,
and the surroundings of each piece hit are verified with Myers' bit-parallel
edit distance (one machine-independent integer per column). Texts and items are
compared lower-cased with white space squeezed to single blanks.

Result: one row per (document, item) found, with the least distance and the
place in the squeezed text. Null or blank documents and items match nothing. Items with equal texts
are all reported. Repeated document rows give repeated result rows. Other
columns are ignored by ``matches`` and kept by ``remove``. Empty tables give
empty results (no items: nothing is found, nothing removed). A very long text is
streamed whole. Of equal distances the first place is taken.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import table, tidy

#: Edits allowed for each character of an item; most characters of items in one automaton (and one broadcast).
RATE, SHARD_CHARS = 0.08, 4_000_000


def squeeze(text: str) -> str:
    return " ".join(text.lower().split())


def budget(item: str, rate: float = RATE) -> int:
    return int(math.floor(rate * len(item)))


def cut(item: str, k: int) -> list[tuple[int, str]]:
    """``k + 1`` pieces of near-equal length with their offsets."""
    bounds = [i * len(item) // (k + 1) for i in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(bounds, bounds[1:]) if b > a]


def runs_of(values: list[int], gap: int) -> Iterator[tuple[int, int]]:
    """First and last of each run of ascending values that are at most ``gap`` apart."""
    first = last = values[0]
    for v in values[1:]:
        if v - last > gap:
            yield first, last
            first = v
        last = v
    yield first, last


class Pattern:
    """An item made ready for Myers' recurrence."""

    def __init__(self, text: str, k: int):
        self.text, self.k, self.m = text, k, len(text)
        self.peq: dict[str, int] = {}
        for i, c in enumerate(text):
            self.peq[c] = self.peq.get(c, 0) | 1 << i

    def best(self, window: str) -> tuple[int, int]:
        """Least distance of the item to any substring of ``window``, and where the first such ends."""
        full, top = (1 << self.m) - 1, 1 << self.m - 1
        plus, minus, score = full, 0, self.m
        best, end = self.m, 0
        peq = self.peq.get
        for j, c in enumerate(window):
            eq = peq(c, 0)
            down = eq | minus
            across = (((eq & plus) + plus) ^ plus) | eq
            up = minus | ~(across | plus) & full
            less = plus & across
            if up & top:
                score += 1
            elif less & top:
                score -= 1
            up, less = up << 1 & full, less << 1 & full
            plus, minus = less | ~(down | up) & full, up & down
            if score < best:
                best, end = score, j + 1
        return best, end


class Matcher:
    """The automaton over all pieces of a shard of items."""

    def __init__(self, items: list[tuple[int, str]], rate: float):
        import ahocorasick

        self.items: list[tuple[int, Pattern]] = []
        places: dict[str, list[tuple[int, int]]] = {}
        for number, raw in items:
            text = squeeze(raw)
            if not text:
                continue
            k = budget(text, rate)
            for offset, piece in cut(text, k):
                places.setdefault(piece, []).append((len(self.items), offset + len(piece) - 1))
            self.items.append((number, Pattern(text, k)))
        self.automaton = ahocorasick.Automaton()
        for piece, at in places.items():
            self.automaton.add_word(piece, at)
        if places:
            self.automaton.make_automaton()

    def search(self, raw: str) -> list[tuple[int, int, int, int]]:
        """(item, distance, start, end) of each item found, at its best place."""
        if not self.items:
            return []
        text = squeeze(raw)
        starts: dict[int, set[int]] = {}
        for end, places in self.automaton.iter(text):
            for i, offset in places:
                starts.setdefault(i, set()).add(end - offset)
        found = []
        for i, begins in starts.items():
            number, pattern = self.items[i]
            best = None
            for begin in sorted(begins):
                if begin >= 0 and text.startswith(pattern.text, begin):
                    best = (0, begin, begin + pattern.m)
                    break
            for first, last in () if best else runs_of(sorted(begins), 2 * pattern.k + 1):
                lo = max(0, first - pattern.k)
                distance, end = pattern.best(text[lo : last + pattern.m + pattern.k])
                if distance <= pattern.k and (best is None or distance < best[0]):
                    best = (distance, max(0, lo + end - pattern.m), lo + end)
            if best:
                found.append((number, *best))
        return sorted(found)


def _shards(items: DataFrame) -> list[list[tuple[int, str]]]:
    """The items in shards of a bounded size, one of which is held at a time."""
    items = items.where("item_id IS NOT NULL AND text IS NOT NULL").select("item_id", "text")
    total = items.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(1, -(-int(total) // SHARD_CHARS))
    for shard in range(n):
        yield [tuple(r) for r in items.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == shard).orderBy("item_id", "text").collect()]


def matches(docs: DataFrame, items: DataFrame, rate: float = RATE) -> DataFrame:
    """doc_id, item_id, distance, start, end of every item found in a document."""
    spark, out = docs.sparkSession, None
    for shard in _shards(items):
        held = spark.sparkContext.broadcast(shard)

        def search(parts: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(held.value, rate)
            for batch in parts:
                rows = []
                for doc, text in zip(batch.column(0), batch.column(1)):
                    value = text.as_py()
                    if value:
                        rows += [(doc.as_py(), *hit) for hit in matcher.search(value)]
                if rows:
                    columns = list(zip(*rows))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c, pa.int64() if i < 2 else pa.int32()) for i, c in enumerate(columns)], names=["doc_id", "item_id", "distance", "start", "end"]
                    )
            tidy()

        found = docs.select("doc_id", "text").mapInArrow(search, "doc_id long, item_id long, distance int, start int, end int")
        out = found if out is None else out.unionByName(found)
    return out


def remove(docs: DataFrame, items: DataFrame, rate: float = RATE) -> DataFrame:
    """``docs`` without the rows that hold an item: each row is searched where it stands, nothing is shuffled."""
    spark, schema = docs.sparkSession, docs.schema
    for shard in _shards(items):
        held = spark.sparkContext.broadcast(shard)

        def clean(parts: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(held.value, rate)
            for batch in parts:
                at = batch.schema.get_field_index("text")
                yield batch.filter(pa.array([not (t.as_py() and matcher.search(t.as_py())) for t in batch.column(at)], pa.bool_()))
            tidy()

        docs = docs.mapInArrow(clean, schema)
    return docs


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document against every benchmark item."""
    return matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
