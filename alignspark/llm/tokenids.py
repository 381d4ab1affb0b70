"""Token files with directly addressable codes.

A segment holds the ids of consecutive documents. Each id is cut into chunks of
eight bits; level 0 keeps the low chunk of every id, level ``l`` the next chunk
of those ids that go on. A bitmap per level says which ids go on, and a rank
directory (running count of set bits every 512 bits) lets a reader find the
place of an id's chunk in the next level by one directory look-up and one
popcount, so any token is read without decoding its neighbours.

Layout of a segment (little-endian): ``DACS``, u32 version, u32 documents, u64
tokens, u32 levels; then documents+1 u64 token offsets; then for each level:
u64 chunks, the chunks, the bitmap bytes (padded to 64), the u64 rank directory.
Segments are rows of a Parquet data set, so any store that Spark writes will do.

Encoding applies the vocabulary's text rules to each distinct white-space
delimited piece and the tokenizers library's BPE model to each distinct word;
the vocabulary drops white space and no rule of it spans white space, so the
pieces' ids joined are the text's ids. Tests compare them with the library's own
encoding of whole texts.

A null text gives the end id only; an empty table gives an empty result. A null
doc_id comes first. Documents with equal ids keep the order of their texts, so
repeated rows follow one another. A very long text is one document of one
segment, which then is larger than the others. Other columns are ignored,
whatever their names.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from alignspark.llm.bpe import MergeTable, byte_alphabet
from alignspark.llm.common import stash_path, table, tidy
from alignspark.llm.hashing import Texts, batches
from alignspark.llm.vocabulary import vocabulary_path
from alignspark.llm.wordtable import Ragged, WordTable, entries

MAGIC, VERSION, STRIDE = b"DACS", 1, 512
#: Tokens in a segment; bits of a worker's word table.
SEGMENT_TOKENS, BITS = 1 << 20, 20
END_ID = 1


# --- the code -------------------------------------------------------------------------------------------------------


def pack(offsets: np.ndarray, ids: np.ndarray) -> bytes:
    """A segment from token offsets per document and all their ids (uint32)."""
    levels, left = [], ids.astype(np.uint32)
    while True:
        on = left > 0xFF
        bits = np.packbits(on, bitorder="little")
        bits = np.concatenate([bits, np.zeros(-len(bits) % 64, dtype=np.uint8)])
        counts = np.unpackbits(bits).reshape(-1, STRIDE).sum(axis=1, dtype=np.uint64) if len(bits) else np.zeros(0, np.uint64)
        ranks = np.concatenate([[np.uint64(0)], np.cumsum(counts)]).astype("<u8")
        levels.append(struct.pack("<Q", len(left)) + (left & 0xFF).astype(np.uint8).tobytes() + bits.tobytes() + ranks.tobytes())
        if not on.any():
            break
        left = left[on] >> 8
    head = MAGIC + struct.pack("<IIQI", VERSION, len(offsets) - 1, len(ids), len(levels))
    return head + offsets.astype("<u8").tobytes() + b"".join(levels)


class Segment:
    """Reads a packed segment: whole documents, or single tokens by position."""

    def __init__(self, blob: bytes):
        if blob[:4] != MAGIC:
            raise ValueError("not a token segment")
        version, docs, self.tokens, levels = struct.unpack_from("<IIQI", blob, 4)
        if version != VERSION:
            raise ValueError(f"segment version {version}")
        at = 24
        self.offsets = np.frombuffer(blob, "<u8", docs + 1, at)
        at += 8 * (docs + 1)
        self.levels = []
        for _ in range(levels):
            (n,) = struct.unpack_from("<Q", blob, at)
            chunks = np.frombuffer(blob, np.uint8, n, at + 8)
            at += 8 + n
            padded = -(-((n + 7) // 8) // 64) * 64
            bits = np.frombuffer(blob, np.uint8, padded, at)
            at += padded
            ranks = np.frombuffer(blob, "<u8", padded // 64 + 1, at)
            at += ranks.nbytes
            self.levels.append((chunks, bits, ranks))

    def __getitem__(self, i: int) -> int:
        """The i-th id: one directory look-up and one popcount a level."""
        value, shift = 0, 0
        for chunks, bits, ranks in self.levels:
            value |= int(chunks[i]) << shift
            if not bits[i >> 3] >> (i & 7) & 1:
                return value
            i, shift = self._rank(bits, ranks, i), shift + 8
        return value

    def ids(self) -> np.ndarray:
        """All ids, level by level from the top."""
        out = np.zeros(0, dtype=np.uint32)
        for chunks, bits, _ in reversed(self.levels):
            level = chunks.astype(np.uint32)
            on = np.unpackbits(bits, bitorder="little")[: len(chunks)].astype(bool)
            level[on] |= out << 8
            out = level
        return out

    def span(self, lo: int, hi: int) -> np.ndarray:
        """Ids ``lo`` to ``hi`` (not included): of every level only their own chunks are read."""
        out, places, shift = np.zeros(hi - lo, dtype=np.uint32), np.arange(hi - lo), 0
        for chunks, bits, ranks in self.levels:
            out[places] |= chunks[lo:hi].astype(np.uint32) << np.uint32(shift)
            on = np.unpackbits(bits[lo >> 3 : (hi + 7) >> 3], bitorder="little")[lo & 7 : (lo & 7) + hi - lo].astype(bool)
            places, shift = places[on], shift + 8
            if not len(places):
                break
            lo = self._rank(bits, ranks, lo)
            hi = lo + len(places)
        return out

    @staticmethod
    def _rank(bits: np.ndarray, ranks: np.ndarray, i: int) -> int:
        """How many of the ids before ``i`` go on: a directory entry and the bits since."""
        block = i // STRIDE
        return int(ranks[block]) + int(np.unpackbits(bits[block * 64 : (i + 7) >> 3], bitorder="little")[: i - block * STRIDE].sum())

    def document(self, k: int) -> np.ndarray:
        return self.span(int(self.offsets[k]), int(self.offsets[k + 1]))


# --- encoding -------------------------------------------------------------------------------------------------------


class PieceEncoder:
    """Ids of whole runs of texts: the vocabulary's own text rules, then the library's BPE model for each new word."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.rules, self.letters = MergeTable(path), byte_alphabet()
        self.model = Tokenizer.from_file(path).model
        self.table, self.ids = WordTable(BITS), Ragged()

    def words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        spell, tokenize, flat, sizes = self.letters, self.model.tokenize, [], []
        for word in words:
            if not (word.isascii() and word.isprintable()):
                word = "".join([spell[b] for b in word.encode("utf-8")])
            got = [t.id for t in tokenize(word)]
            flat += got
            sizes.append(len(got))
        return np.array(flat, dtype=np.int64), np.array(sizes, dtype=np.int64)

    def learn(self, pieces: list[bytes]) -> None:
        self.ids.extend(*self.rules.assemble(pieces, self.words))

    def encode(self, texts: Texts, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """All ids of some texts, each text's closed by the end id, and the id offsets of the texts."""
        rows, at = entries(self.table, texts, self.learn, self.ids.clear)
        ids, off = self.ids.take(rows)
        bounds = off[at]
        out = np.full(len(ids) + texts.n, end_id, dtype=np.uint32)
        out[np.arange(len(ids)) + np.repeat(np.arange(texts.n), np.diff(bounds))] = ids
        return out, bounds + np.arange(texts.n + 1)


_ENCODERS: dict[str, PieceEncoder] = {}


def encoder_of(path: str) -> PieceEncoder:
    """One encoder for each worker process: tasks share what it remembers."""
    if path not in _ENCODERS:
        _ENCODERS[path] = PieceEncoder(path)
    return _ENCODERS[path]


def write_segments(docs: DataFrame, path: str, tokenizer: str | None = None, end_id: int = END_ID) -> None:
    """Encode ``docs`` in ascending doc_id order and write the segments to ``path``."""
    tokenizer = tokenizer or vocabulary_path()

    def segments(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, part, turn = encoder_of(tokenizer), TaskContext.get().partitionId(), 0
        ids, sizes, held, total = [], [], [], 0

        def flush():
            blob = pack(np.r_[0, np.cumsum(np.concatenate(sizes))], np.concatenate(held))
            return pa.RecordBatch.from_pydict(
                {"part": [part], "turn": [turn], "n_tokens": [total], "doc_ids": [pa.concat_arrays(ids)], "segment": [blob]}, schema=kind
            )

        for batch in parts:
            for texts in batches(batch):
                codes, off = encoder.encode(texts, end_id)
                held.append(codes)
                sizes.append(np.diff(off))
                ids.append(batch.column(0).slice(texts.first, texts.n))
                total += len(codes)
                if total >= SEGMENT_TOKENS:
                    yield flush()
                    turn += 1
                    ids, sizes, held, total = [], [], [], 0
        if ids:
            yield flush()
        tidy()

    kind = pa.schema([("part", pa.int32()), ("turn", pa.int32()), ("n_tokens", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("segment", pa.binary())])
    ordered = docs.select("doc_id", "text").repartitionByRange(F.col("doc_id")).sortWithinPartitions("doc_id", "text")
    ordered.mapInArrow(segments, "part int, turn int, n_tokens long, doc_ids array<long>, segment binary").write.parquet(path)


SEGMENTS = "part int, turn int, n_tokens long, doc_ids array<long>, segment binary"


def read_index(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    files = spark.read.schema(SEGMENTS).parquet(path)
    order = Window.orderBy("part", "turn").rowsBetween(Window.unboundedPreceding, -1)
    starts = files.select("part", "turn", F.coalesce(F.sum("n_tokens").over(order), F.lit(0)).alias("base"))

    def unpack(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts:
            for part, turn, ids, blob in zip(*(batch.column(i) for i in range(4))):
                seg = Segment(blob.as_py())
                codes, off = seg.ids().astype("<u4"), seg.offsets.astype(np.int64)
                raw = memoryview(codes.tobytes())
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(off[:-1], off[1:])]
                n = len(crc)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([part.as_py()] * n, pa.int32()), pa.array([turn.as_py()] * n, pa.int32()), pa.array(ids.as_py(), pa.int64()),
                     pa.array(off[:-1]), pa.array(np.diff(off)), pa.array(crc, pa.int64())],
                    names=["part", "turn", "doc_id", "local", "n_tokens", "ids_crc32"],
                )

    rows = files.select("part", "turn", "doc_ids", "segment").mapInArrow(
        unpack, "part int, turn int, doc_id long, local long, n_tokens long, ids_crc32 long"
    )
    return rows.join(starts, ["part", "turn"]).select(
        "doc_id", (F.col("local") + F.col("base")).cast("long").alias("start"), "n_tokens", "ids_crc32"
    )


def op6_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded, written as segments and read back."""
    path = stash_path(spark, "token-segments")
    write_segments(table(spark, sf_dir, "documents"), path)
    return read_index(spark, path)
