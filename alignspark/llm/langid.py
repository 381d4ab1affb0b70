"""Language identification with bit-sliced Bloom filters over character n-grams.

One table of bytes stands for up to eight Bloom filters: bit ``l`` of a cell is
language ``l``'s filter; more than eight languages have further tables. One look-up of an n-gram (the AND of a few cells) gives
the bitmask of all of a table's languages that hold it. For a text the bits are counted by
language, corrected for each filter's false positives, and the largest count
decides; the score is its share of all corrected counts.

N-grams are four characters of the lower-cased text in which every run of
non-letters is one blank. A language holds an n-gram when its rate there is at
least ``SHARE`` of the n-gram's highest rate and it occurs ``LEAST`` times.
The filters are fitted on a bounded sample of training rows (about ``SAMPLE``
rows, chosen by a hash of the id; rows that repeat an id count once in a task);
every text is predicted, whole, however long.

Null texts and texts without a letter are ``und`` with score 0. If no n-gram is
known the commonest learned language is taken with score 0; equal counts go to
the language that sorts first. Repeated rows are predicted alike. Without
training rows everything is ``und``; an empty table gives an empty result. Other
columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import table, tidy
from alignspark.llm.hashing import U, mix

N, SAMPLE, SHARE, LEAST = 4, 20_000, 0.12, 3
CELL_BITS, PROBES = 22, 3
UNKNOWN = "und"
_LETTER: list[np.ndarray] = []


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string")), F.lit(3)) == 1, F.lit(False))


def letters() -> np.ndarray:
    """Which code points are letters."""
    if not _LETTER:
        flags = np.zeros(0x110000, dtype=bool)
        # the planes that hold letters; the rest has none
        for lo, hi in ((0, 0x32000), (0xE0000, 0xE0200)):
            flags[lo:hi] = [chr(c).isalpha() if not 0xD800 <= c < 0xE000 else False for c in range(lo, hi)]
        _LETTER.append(flags)
    return _LETTER[0]


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash of every n-gram of some texts, the text it is from, and whether a text has a letter."""
    marks = "\n\n".join(texts) + "\n"
    points = np.frombuffer(marks.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    # lower-casing may lengthen a text: find the joints again by their length
    sizes = np.array([len(t.lower()) for t in texts], dtype=np.int64)
    starts = np.r_[0, np.cumsum(sizes[:-1] + 2)] if len(texts) else np.zeros(0, np.int64)
    owner = np.repeat(np.arange(len(texts)), np.r_[np.diff(starts), len(points) - starts[-1]]) if len(texts) else np.zeros(0, np.int64)
    letter = letters()[points]
    any_letter = np.bincount(owner, weights=letter, minlength=len(texts)) > 0
    keep = letter.copy()
    keep[1:] |= letter[:-1]  # the first non-letter after letters stands for its run
    code = np.where(letter, points, 0).astype(U)[keep]
    owner = owner[keep]
    if len(code) < N:
        return np.zeros(0, U), np.zeros(0, np.int64), any_letter
    key = np.zeros(len(code) - N + 1, dtype=U)
    for j in range(N):
        key = key * U(0x110000) + code[j : len(code) - N + 1 + j]  # 21 bits each: the product wraps, the finisher mixes
    one = owner[: len(key)] == owner[N - 1 :]
    return mix(key)[one], owner[: len(key)][one], any_letter


def _runs(column: pa.Array, limit: int = 1 << 19) -> Iterator[list[str]]:
    out, size = [], 0
    for value in column:
        text = value.as_py() or ""
        out.append(text)
        size += len(text)
        if size >= limit:
            yield out
            out, size = [], 0
    if out:
        yield out


def cells(keys: np.ndarray, probe: int) -> np.ndarray:
    return ((keys >> U(probe * 21)) & U((1 << CELL_BITS) - 1)).astype(np.int64) if probe < 2 else (mix(keys + U(7)) & U((1 << CELL_BITS) - 1)).astype(np.int64)


class Filters:
    """The bit-sliced filters and each language's false-positive rate."""

    def __init__(self, names: list[str], keys: np.ndarray, masks: np.ndarray, common: int):
        self.names, self.common = names, common
        self.tables = [np.zeros(1 << CELL_BITS, dtype=np.uint8) for _ in range(0, len(names), 8)]
        for probe in range(PROBES):
            at = cells(keys, probe)
            for table_, mask in zip(self.tables, masks.T):
                np.bitwise_or.at(table_, at, mask)
        fill = [np.count_nonzero(self.tables[i // 8] & np.uint8(1 << i % 8)) / (1 << CELL_BITS) for i in range(len(names))]
        self.chance = np.array(fill) ** PROBES

    def masks(self, keys: np.ndarray) -> list[np.ndarray]:
        at = [cells(keys, probe) for probe in range(PROBES)]
        return [np.bitwise_and.reduce([table_[x] for x in at]) for table_ in self.tables]

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        keys, owner, lettered = grams(texts)
        n, k = len(texts), len(self.names)
        if not k:
            return [UNKNOWN] * n, np.zeros(n)
        masks = self.masks(keys)
        total = np.bincount(owner, minlength=n).astype(float)
        counts = np.stack([np.bincount(owner, weights=(masks[i // 8] >> (i % 8)) & 1, minlength=n) for i in range(k)], axis=1)
        right = np.maximum(0.0, (counts - total[:, None] * self.chance) / np.maximum(1e-9, 1.0 - self.chance))
        best = right.argmax(axis=1)
        whole = right.sum(axis=1)
        top = right[np.arange(n), best]
        best = np.where(top > 0, best, self.common)
        score = np.where(whole > 0, top / np.maximum(whole, 1e-12), 0.0)
        return [self.names[b] if has else UNKNOWN for b, has in zip(best, lettered)], np.where(lettered, score, 0.0)


def fit(rows: DataFrame, sample: int = SAMPLE) -> Filters:
    """Filters from a bounded sample of rows (doc_id, text, lang): n-gram counts are summed by Spark."""
    taught = rows.where("doc_id IS NOT NULL AND lang IS NOT NULL AND text IS NOT NULL").select("doc_id", "text", "lang")
    share = min(1.0, sample / max(1, taught.select("doc_id", "lang").count()))
    chosen = taught.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30)))

    def count(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in parts:
            batch = batch.filter(pa.array([not (i in seen or seen.add(i)) for i in batch.column(0).to_pylist()], pa.bool_()))
            for lang in sorted({x for x in batch.column(2).to_pylist() if x is not None}):
                own = batch.filter(pa.array([x == lang for x in batch.column(2).to_pylist()]))
                for run in _runs(own.column(1), 1 << 21):
                    keys, n = np.unique(grams(run)[0], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array([lang] * len(keys)), pa.array(n.astype(np.int64))], names=["gram", "lang", "n"])

    counted = chosen.mapInArrow(count, "gram long, lang string, n long")
    got = counted.groupBy("gram", "lang").agg(F.sum("n").alias("n")).where(F.col("n") >= LEAST).toArrow()
    langs, n, gram = np.array(got["lang"].to_pylist(), dtype=object), got["n"].to_numpy(), got["gram"].to_numpy()
    names = sorted(set(langs.tolist()))
    if not names:
        return Filters([], np.zeros(0, U), np.zeros((0, 0), np.uint8), 0)
    number = {name: i for i, name in enumerate(names)}
    of = np.array([number[x] for x in langs.tolist()])
    totals = np.bincount(of, weights=n)
    keys, at = np.unique(gram, return_inverse=True)
    rate, highest = n / totals[of], np.zeros(len(keys))
    np.maximum.at(highest, at, rate)
    held = rate >= SHARE * highest[at]
    masks = np.zeros((len(keys), -(-len(names) // 8)), dtype=np.uint8)
    np.bitwise_or.at(masks, (at[held], of[held] // 8), (1 << of[held] % 8).astype(np.uint8))
    return Filters(names, keys.view(U), masks, int(totals.argmax()))


def identify(docs: DataFrame, filters: Filters) -> DataFrame:
    """doc_id, lang_pred, score for every row; only the text is looked at."""
    held = docs.sparkSession.sparkContext.broadcast(filters)  # 4 MB for every eight languages, whatever the corpus

    def predict(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in parts:
            at = 0
            for run in _runs(batch.column(1)):
                names, score = model.predict(run)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, len(run)), pa.array(names, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "lang_pred", "score"]
                )
                at += len(run)
        tidy()

    return docs.select("doc_id", "text").mapInArrow(predict, "doc_id long, lang_pred string, score double")


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's language, learned from the rows that are not held out."""
    docs = table(spark, sf_dir, "documents")
    model = fit(docs.where(~held_out(F.col("doc_id"))))
    return identify(docs, model).withColumn("held_out", held_out(F.col("doc_id")))
