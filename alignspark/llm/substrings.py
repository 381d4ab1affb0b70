"""Substring dedup by repeated-phrase automata.

1. Confirm recurring phrases: every ``WINDOW``-word window has a smallest
   ``PHRASE``-word phrase (by hash). Equal windows have equal smallest phrases,
   so a window can recur only where a phrase that was smallest somewhere recurs.
   Those phrases (about one word in fourteen) are counted over the corpus by
   hash. What the count returns is the phrases that occur twice or more, as
   strings of symbols (two bytes of each word's hash), never their places.
2. Compile: documents are dealt to blocks of a bounded size, and the confirmed
   phrases to the blocks whose documents they may stand in. Each block compiles
   its phrases into one Aho-Corasick automaton, a shard of the whole phrase set:
   a phrase that no document of a block holds could only idle there, and sending
   every phrase to every document would cost the square of the corpus.
3. Stream: every document goes through the automaton of its block, which locates
   every occurrence of a confirmed phrase.
4. Verify: windows that hold a located phrase are counted over the corpus by
   hash; those found twice or more cover the words to remove.

A window is ``WINDOW`` consecutive words of one document, judged on the input.
Null and empty texts have no words and keep none. Repeated rows recur in each
other (rows of equal id and text travel as one row with a count). A document
with fewer words than a window keeps all. Equal hashes count as equal windows;
among equal smallest phrases all are taken, so ties change nothing. A very long
text stays in one block and is streamed whole; it needs about fifty times its
size in the worker. Empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import shares, stash, table, text_bytes, tidy
from alignspark.llm.hashing import U, Texts, batches, deal, undeal, windows
from alignspark.llm.recurrence import BLOB, KIND, Gather, block_of, places_of, settle

WINDOW, PHRASE = 35, 8
#: Bytes of text in a block; phrases that a task gathers before it deals them out.
BLOCK_BYTES, PHRASES = 4 << 20, 200_000
TOP = np.iinfo(np.uint64).max


def _slide(values: np.ndarray, width: int, best) -> np.ndarray:
    """``best`` (minimum or maximum) over each run of ``width`` values; n - width + 1 of them."""
    out, have = values, 1
    while 2 * have <= width:
        out = best(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return best(out[:-rest], out[rest:]) if rest else out


def seeds(hashes: np.ndarray, at: np.ndarray, window: int, phrase: int) -> tuple[np.ndarray, np.ndarray]:
    """Phrases that are smallest in some window: their hashes and the word numbers where they start."""
    n, span = len(hashes), window - phrase + 1
    if n < window:
        return np.zeros(0, U), np.zeros(0, np.int64)
    value = np.full(n - phrase + 1, TOP, dtype=U)
    own, starts = windows(hashes, at, phrase)
    value[starts] = np.maximum(own, U(1))
    least = _slide(value, span, np.minimum)  # by window start
    room = np.repeat(at[1:], np.diff(at))[: len(least)]
    least = np.where(np.arange(len(least)) + window <= room, least, U(0))
    padded = np.concatenate([np.zeros(span - 1, U), least, np.zeros(span - 1, U)])
    most = _slide(padded, span, np.maximum)  # by phrase start: the largest minimum of the windows around it
    chosen = np.flatnonzero((most == value) & (value < TOP))
    return value[chosen], chosen


def _keyed(docs: DataFrame) -> DataFrame:
    """A row key from id and text: rows of one id and different texts stay apart, repeated rows share it."""
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("row", F.xxhash64("doc_id", "text"))


# --- phrases ---------------------------------------------------------------------------------------------------------


def symbols(hashes: np.ndarray) -> np.ndarray:
    """Two bytes of every word's hash: the automata's alphabet. Words that share them only cause windows to be verified."""
    return (hashes & U(0xFFFF)).astype("<u2")


class Phrases:
    """Phrase entries (hash, block, symbols) of one map task.

    A phrase that occurs twice within a task is known to recur: it goes to its
    blocks at once, and one mark speaks for it in the count.
    """

    def __init__(self, blocks: int, phrase: int):
        self.blocks, self.kind = blocks, np.dtype(f"V{2 * phrase}")
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.n = 0

    def put(self, keys: np.ndarray, blocks: np.ndarray, words: np.ndarray) -> Iterator[pa.RecordBatch]:
        if len(keys):
            self.parts.append((keys, blocks.astype(np.int32), np.ascontiguousarray(words).view(self.kind).ravel()))
            self.n += len(keys)
            if self.n >= PHRASES:
                yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.parts:
            return
        keys, blocks, words = (np.concatenate(x) for x in zip(*self.parts))
        self.parts, self.n = [], 0
        order = np.lexsort((blocks, keys))
        keys, blocks, words = keys[order], blocks[order], words[order]
        head = np.r_[True, keys[1:] != keys[:-1]]
        size = np.diff(np.r_[np.flatnonzero(head), len(keys)])
        once = np.r_[True, ~head[1:] & (blocks[1:] != blocks[:-1])] | head  # a phrase once for each block
        known = np.repeat(size > 1, size) & once
        out = [(b % self.blocks, 1, np.int32(b).tobytes() + blob) for b, blob in deal(blocks[known], [words[known]])]
        bucket = (keys[head] % U(self.blocks)).astype(np.int64)
        out += [(b, 0, blob) for b, blob in deal(bucket, [keys[head], blocks[head], words[head], (size > 1).astype(np.uint8)])]
        yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t.type) for i, t in enumerate(KIND)], schema=KIND)


def recurring_phrases(keyed: DataFrame, n: int, window: int, phrase: int) -> DataFrame:
    """(block, blob) of the phrases that occur twice or more in the corpus, as symbols, for each block that may hold them."""

    def emit(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gather = Phrases(n, phrase)
        for batch in parts:
            blocks = block_of(batch.column(0).to_numpy(), n)
            for texts in batches(batch):
                hashes, at = texts.words()
                value, chosen = seeds(hashes, at, window, phrase)
                owner = np.searchsorted(at, chosen, side="right") - 1
                words = symbols(hashes)[chosen[:, None] + np.arange(phrase)[None, :]]
                yield from gather.put(value, blocks[texts.first + owner], words)
        yield from gather.flush()
        tidy()

    def confirm(group: pa.Table) -> pa.Table:
        kinds, blobs = group["kind"].to_pylist(), group["blob"].to_pylist()
        out = [(int(np.frombuffer(b, np.int32, 1)[0]), b[4:]) for k, b in zip(kinds, blobs) if k == 1]
        keys, blocks, words, known = undeal([b for k, b in zip(kinds, blobs) if k == 0], [U, np.int32, f"V{2 * phrase}", np.uint8])
        if len(keys):
            order = np.argsort(keys, kind="stable")
            keys, blocks, words, known = keys[order], blocks[order], words[order], known[order]
            start = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
            size = np.diff(np.r_[start, len(keys)])
            hit = np.repeat((size > 1) | (np.maximum.reduceat(known, start) > 0), size) & (known == 0)
            out += list(deal(blocks[hit], [words[hit]]))
        tidy()
        return pa.table({"block": pa.array([o[0] for o in out], pa.int32()), "blob": pa.array([o[1] for o in out], pa.binary())})

    return keyed.select("row", "text").mapInArrow(emit, BLOB).groupBy("bucket").applyInArrow(confirm, "block int, blob binary")


class Automaton:
    """The confirmed phrases of one block, compiled."""

    def __init__(self, blobs: list[bytes], phrase: int):
        import ahocorasick

        self.phrase, width = phrase, 2 * phrase
        found = {blob[i : i + width] for blob in blobs for i in range(0, len(blob), width)}
        self.machine = ahocorasick.Automaton(ahocorasick.STORE_LENGTH)
        for word in found:
            self.machine.add_word(word.decode("latin-1"))
        self.empty = not found
        if found:
            self.machine.make_automaton()

    def occurrences(self, hashes: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Word numbers at which a confirmed phrase starts, over all documents of a run."""
        if self.empty:
            return np.zeros(0, np.int64)
        stream = symbols(hashes).tobytes().decode("latin-1")
        found: list[int] = []
        for lo, hi in zip(at[:-1].tolist(), at[1:].tolist()):
            # a match that ends on the first byte of a word is none
            found += [lo + end // 2 - self.phrase + 1 for end, _ in self.machine.iter(stream[2 * lo : 2 * hi]) if end & 1]
        return np.array(found, dtype=np.int64)


# --- windows ---------------------------------------------------------------------------------------------------------

PACKED = "doc_id long, text string, row long, times int, block int"


def _packed(keyed: DataFrame, n: int) -> DataFrame:
    """Rows with their block; rows of one batch that repeat each other are one row with a count."""

    def pack(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts:
            rows, place, times = np.unique(batch.column(2).to_numpy(), return_index=True, return_counts=True)
            one = batch if len(rows) == batch.num_rows else batch.take(pa.array(place))
            if one is batch:
                rows, times = batch.column(2).to_numpy(), np.ones(len(rows), np.int64)
            yield one.append_column("times", pa.array(times.astype(np.int32))).append_column("block", pa.array(block_of(rows, n).astype(np.int32)))
        tidy()

    return keyed.mapInArrow(pack, PACKED)


def _one(table_: pa.Table) -> pa.RecordBatch:
    return table_.combine_chunks().to_batches()[0]


def _ranges(sorted_rows: np.ndarray, places: np.ndarray, rows: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Word numbers of the places of some rows, whose words start at ``at``."""
    lo, hi = np.searchsorted(sorted_rows, rows, "left"), np.searchsorted(sorted_rows, rows, "right")
    count = hi - lo
    pick = np.repeat(lo - np.r_[0, np.cumsum(count)[:-1]], count) + np.arange(count.sum())
    return places[pick] + np.repeat(at[:-1], count)


def repeated(packed: DataFrame, phrases: DataFrame, n: int, window: int, phrase: int) -> DataFrame:
    """(block, blob) of the places of windows that stand twice or more in the corpus."""

    def verify(texts_: pa.Table, blobs: pa.Table) -> pa.Table:
        made: list[pa.RecordBatch] = []
        if texts_.num_rows:
            gather, automaton = Gather(n, n), Automaton(blobs["blob"].to_pylist(), phrase)
            batch = _one(texts_)
            rows, times = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("row", "times"))
            for texts in batches(batch):
                hashes, at = texts.words()
                hits = automaton.occurrences(hashes, at)
                if not len(hits):
                    continue
                # windows that hold a hit: a start at most window - phrase words before it
                mark = np.zeros(len(hashes) + 1, dtype=np.int32)
                np.add.at(mark, np.maximum(hits - (window - phrase), 0), 1)
                np.add.at(mark, hits + 1, -1)
                near = np.cumsum(mark)[:-1] > 0
                keys, start = windows(hashes, at, window)
                keys, start = keys[near[start]], start[near[start]]
                doc = np.searchsorted(at, start, side="right") - 1
                # rows that repeat each other count twice: that is enough to recur
                often = 1 + (times[texts.first + doc] > 1)
                made += gather.put(np.repeat(keys, often), np.repeat(rows[texts.first + doc], often), np.repeat(start - at[doc], often))
            made += gather.flush()
            tidy()
        return pa.Table.from_batches(made, schema=KIND)

    gathered = packed.groupBy("block").cogroup(phrases.groupBy("block")).applyInArrow(verify, BLOB)
    return settle(gathered, n)


def _kept(texts: Texts, removed: np.ndarray | None) -> tuple[list[int], list[int], list[str]]:
    """Per text: words, words removed, and the digest of the words kept."""
    raw = texts.data.tobytes()
    n, gone, sha = [], [], []
    base = 0
    for a, b in zip(texts.offsets[:-1].tolist(), texts.offsets[1:].tolist()):
        words = raw[a:b].split()
        k = len(words)
        n.append(k)
        lost = 0
        if removed is not None:
            out = removed[base : base + k]
            lost = int(out.sum())
            if lost:
                words = [w for w, x in zip(words, out.tolist()) if not x]
        gone.append(lost)
        base += k
        sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
    return n, gone, sha


RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"
_RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])


def dedup(docs: DataFrame, window: int = WINDOW, phrase: int = PHRASE) -> DataFrame:
    """doc_id, n_words, n_removed and the digest of what is kept, for every row."""
    n = shares(docs.sparkSession, text_bytes(docs), BLOCK_BYTES)
    keyed = _keyed(docs)
    phrases = stash(recurring_phrases(keyed, n, window, phrase), "phrases")
    packed = _packed(keyed, n)
    spans = repeated(packed, phrases, n, window, phrase)

    def cut(texts_: pa.Table, blobs: pa.Table) -> pa.Table:
        made = []
        if texts_.num_rows:
            span_rows, places = places_of(blobs["blob"].to_pylist())
            batch = _one(texts_)
            rows, times = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("row", "times"))
            for texts in batches(batch):
                own = slice(texts.first, texts.first + texts.n)
                _, at = texts.words()
                starts = _ranges(span_rows, places, rows[own], at)
                removed = None
                if len(starts):
                    mark = np.zeros(at[-1] + window + 1, dtype=np.int32)
                    np.add.at(mark, starts, 1)
                    np.add.at(mark, starts + window, -1)
                    removed = np.cumsum(mark)[: at[-1]] > 0
                ids = batch.column(batch.schema.get_field_index("doc_id")).slice(texts.first, texts.n)
                part = pa.RecordBatch.from_arrays([ids, *(pa.array(x, t.type) for x, t in zip(_kept(texts, removed), list(_RESULT)[1:]))], schema=_RESULT)
                if (times[own] > 1).any():
                    part = part.take(pa.array(np.repeat(np.arange(texts.n), times[own])))
                made.append(part)
            tidy()
        return pa.Table.from_batches(made, schema=_RESULT)

    return packed.groupBy("block").cogroup(spans.groupBy("block")).applyInArrow(cut, RESULT)


def op10_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the windows that stand elsewhere too."""
    return dedup(table(spark, sf_dir, "documents"))
