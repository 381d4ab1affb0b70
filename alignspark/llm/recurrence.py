"""Which 64-bit keys occur twice or more over a corpus, and where: shared by the phrase operators.

Map tasks gather (key, row, place) entries in numpy. A key that occurs twice
within a task is known to recur there: its places are passed on at once and one
entry speaks for it, so a key that a third of all rows hold costs an entry for
each task, not for each row. Entries are dealt to buckets by key as packed
blobs; a bucket is sorted once and returns the places of recurring keys, dealt
to blocks of rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from alignspark.llm.common import tidy
from alignspark.llm.hashing import U, deal, mix, undeal

#: Entries that a task gathers before it deals them out.
FLUSH = 500_000
BLOB = "bucket int, kind int, blob binary"
KIND = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])


def block_of(rows: np.ndarray, blocks: int) -> np.ndarray:
    """Block of each row key (int64)."""
    return (mix(rows.astype(np.int64).view(U) + U(11)) % U(blocks)).astype(np.int64)


class Gather:
    """Entries of one map task."""

    def __init__(self, buckets: int, blocks: int):
        self.buckets, self.blocks = buckets, blocks
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.n = 0

    def put(self, keys: np.ndarray, rows: np.ndarray, places: np.ndarray) -> Iterator[pa.RecordBatch]:
        if len(keys):
            self.parts.append((keys, rows, places.astype(np.uint32)))
            self.n += len(keys)
            if self.n >= FLUSH:
                yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.parts:
            return
        keys, rows, places = (np.concatenate(x) for x in zip(*self.parts))
        self.parts, self.n = [], 0
        order = np.argsort(keys, kind="stable")
        keys, rows, places = keys[order], rows[order], places[order]
        head = np.r_[True, keys[1:] != keys[:-1]]
        size = np.diff(np.r_[np.flatnonzero(head), len(keys)])
        again = np.repeat(size > 1, size)
        out: list[tuple[int, int, bytes]] = []
        # places of keys known to recur; they travel by block
        if again.any():
            r, p = rows[again], places[again]
            block = block_of(r, self.blocks)
            out += [(b % self.buckets, 1, np.int32(b).tobytes() + blob) for b, blob in deal(block, [r, p])]
        # an entry for every key: its place where it occurs once, a bare mark where it is known
        k, known = keys[head], (size > 1).astype(np.uint8)
        bucket = (k % U(self.buckets)).astype(np.int64)
        out += [(b, 0, blob) for b, blob in deal(bucket, [k, rows[head], places[head], known])]
        yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t.type) for i, t in enumerate(KIND)], schema=KIND)


def settle(gathered: DataFrame, blocks: int) -> DataFrame:
    """(block, blob) of the places of recurring keys: rows int64, places uint32."""

    def reduce(group: pa.Table) -> pa.Table:
        kinds, blobs = group["kind"].to_pylist(), group["blob"].to_pylist()
        out = [(int(np.frombuffer(b, np.int32, 1)[0]), b[4:]) for k, b in zip(kinds, blobs) if k == 1]
        keys, rows, places, known = undeal([b for k, b in zip(kinds, blobs) if k == 0], [U, np.int64, np.uint32, np.uint8])
        if len(keys):
            order = np.argsort(keys, kind="stable")
            keys, rows, places, known = keys[order], rows[order], places[order], known[order]
            head = np.r_[True, keys[1:] != keys[:-1]]
            start = np.flatnonzero(head)
            size = np.diff(np.r_[start, len(keys)])
            marked = np.maximum.reduceat(known, start)
            hit = np.repeat((size > 1) | (marked > 0), size) & (known == 0)
            r, p = rows[hit], places[hit]
            out += list(deal(block_of(r, blocks), [r, p]))
        tidy()
        return pa.table({"block": pa.array([o[0] for o in out], pa.int32()), "blob": pa.array([o[1] for o in out], pa.binary())})

    return gathered.groupBy("bucket").applyInArrow(reduce, "block int, blob binary")


def places_of(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Rows and places of some blobs, ordered by row and place, without repetitions."""
    rows, places = undeal(blobs, [np.int64, np.uint32])
    order = np.lexsort((places, rows))
    rows, places = rows[order], places[order].astype(np.int64)
    keep = np.r_[True, (rows[1:] != rows[:-1]) | (places[1:] != places[:-1])] if len(rows) else np.zeros(0, bool)
    return rows[keep], places[keep]
