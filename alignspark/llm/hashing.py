"""Vectorised word and n-gram hashing over the raw bytes of Arrow string columns.

Everything works on whole batches: word bounds come from byte comparisons, and
hashes of words and of word windows from prefix sums of a polynomial modulo
2**64, so no Python object is made for a word. Hashes are 64-bit and finished
with a bijective mixer; two different word sequences collide with a chance of
about 2**-64.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_BYTES = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.int64).astype(U) * U(2) + U(1)
_FOLDED = _BYTES.copy()
_FOLDED[ord("A") : ord("Z") + 1] = _BYTES[ord("a") : ord("z") + 1]
_POWERS: list[np.ndarray] = []
BLOCK = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finisher (shift-multiply rounds) over uint64."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(n, BLOCK + (1 << 16))
        made = []
        for base in (_BASE, _INVERSE):
            p = np.full(size, base, dtype=U)
            p[0] = 1
            made.append(np.multiply.accumulate(p))
        _POWERS[:] = made
    return _POWERS[0][:n], _POWERS[1][:n]


def segment_hash(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of ``values[s:e]`` for every segment; starts and ends ascend, values are uint64 or bytes with a table."""
    out = np.empty(len(starts), dtype=U)
    at = 0
    while at < len(starts):
        lo = int(starts[at])
        upto = max(at + 1, int(np.searchsorted(ends, lo + BLOCK, side="right")))
        hi = int(ends[upto - 1])
        part = values[lo:hi]
        power, inverse = _powers(hi - lo + 1)
        sums = np.zeros(hi - lo + 1, dtype=U)
        np.cumsum(part * power[:-1], out=sums[1:])
        s, e = starts[at:upto] - lo, ends[at:upto] - lo
        out[at:upto] = (sums[e] - sums[s]) * inverse[s]
        at = upto
    out += (ends - starts).astype(U) * U(0xD6E8FEB86659FD93)
    return mix(out)


class Texts:
    """Some documents of a batch: their bytes, byte offsets and row numbers."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, first: int):
        self.data, self.offsets, self.first = data, offsets, first
        self.n = len(offsets) - 1

    def words(self, fold: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """Hash of each word, and for each document the index of its first word (one more at the end)."""
        hashes, at, _, _ = self.words_at(fold)
        return hashes, at

    def words_at(self, fold: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """As ``words``, with the byte bounds of each word."""
        data, off = self.data, self.offsets
        if not len(data):
            z = np.zeros(0, dtype=np.int64)
            return z.astype(U), np.zeros(self.n + 1, dtype=np.int64), z, z
        space = _SPACE[data]
        edge = np.empty(len(data) + 1, dtype=bool)
        edge[0] = edge[-1] = True
        edge[1:-1] = space[:-1]
        edge[off] = True
        starts = np.flatnonzero(~space & edge[:-1])
        edge[1:-1] = space[1:]
        edge[off] = True
        ends = np.flatnonzero(~space & edge[1:]) + 1
        at = np.searchsorted(starts, off)
        hashes = segment_hash_bytes(data, starts, ends, _FOLDED if fold else _BYTES)
        return hashes, at, starts, ends


def segment_hash_bytes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lut: np.ndarray) -> np.ndarray:
    out = np.empty(len(starts), dtype=U)
    at = 0
    while at < len(starts):
        lo = int(starts[at])
        upto = max(at + 1, int(np.searchsorted(ends, lo + BLOCK, side="right")))
        hi = int(ends[upto - 1])
        out[at:upto] = segment_hash(lut[data[lo:hi]], starts[at:upto] - lo, ends[at:upto] - lo)
        at = upto
    return out


def windows(hashes: np.ndarray, at: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each k-word window that lies within one document, and the word index at which it starts."""
    if len(hashes) < k:
        return np.zeros(0, dtype=U), np.zeros(0, dtype=np.int64)
    room = np.repeat(at[1:], np.diff(at))
    starts = np.flatnonzero(np.arange(len(hashes)) + k <= room)
    return segment_hash(hashes, starts, starts + k), starts


def batches(batch: pa.RecordBatch, column: str = "text", limit: int = 1 << 20) -> Iterator[Texts]:
    """The documents of an Arrow batch in runs of about ``limit`` bytes; null texts are empty."""
    col = batch.column(batch.schema.get_field_index(column))
    if isinstance(col, pa.ChunkedArray):
        col = pa.concat_arrays(col.chunks)
    if col.null_count:
        col = col.fill_null("")
    wide = pa.types.is_large_string(col.type)
    kind = np.int64 if wide else np.int32
    buffers = col.buffers()
    n = len(col)
    if not n:
        return
    off = np.frombuffer(buffers[1], dtype=kind, count=n + 1, offset=col.offset * kind().itemsize).astype(np.int64)
    raw = np.frombuffer(buffers[2], dtype=np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, np.uint8)
    row = 0
    while row < n:
        stop = max(row + 1, int(np.searchsorted(off, off[row] + limit, side="right")) - 1)
        yield Texts(raw[off[row] : off[stop]], off[row : stop + 1] - off[row], row)
        row = stop


def deal(bucket: np.ndarray, columns: list[np.ndarray]) -> Iterator[tuple[int, bytes]]:
    """Rows of equal-width columns by bucket: (bucket, bytes of the columns one after the other)."""
    order = np.argsort(bucket, kind="stable")
    sorted_bucket = bucket[order]
    cuts = np.flatnonzero(np.diff(sorted_bucket)) + 1
    columns = [c[order] for c in columns]
    for lo, hi in zip(np.r_[0, cuts], np.r_[cuts, len(order)]):
        if hi > lo:
            yield int(sorted_bucket[lo]), b"".join(np.ascontiguousarray(c[lo:hi]).tobytes() for c in columns)


def undeal(blobs: list[bytes], kinds: list) -> list[np.ndarray]:
    """The columns of many blobs made by ``deal``, joined."""
    width = sum(np.dtype(k).itemsize for k in kinds)
    parts: list[list[np.ndarray]] = [[] for _ in kinds]
    for blob in blobs:
        n, at = len(blob) // width, 0
        for i, kind in enumerate(kinds):
            parts[i].append(np.frombuffer(blob, dtype=kind, count=n, offset=at))
            at += n * np.dtype(kind).itemsize
    return [np.concatenate(p) if p else np.zeros(0, dtype=k) for p, k in zip(parts, kinds)]
