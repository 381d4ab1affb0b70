"""A bounded memo of words for whole batches: 64-bit word hashes to entry numbers, in numpy.

Open addressing with linear probing over a table of fixed size; look-ups and
insertions take all words of a run at once. A full table is emptied. Two words
of one hash would be taken for one, with a chance of 2**-64 for each pair.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from alignspark.llm.hashing import U, Texts


class WordTable:
    def __init__(self, bits: int = 20):
        self.mask = (1 << bits) - 1
        self.limit = int(0.45 * (1 << bits))
        self.clear()

    def clear(self) -> None:
        self.keys = np.zeros(self.mask + 1, dtype=U)
        self.entry = np.zeros(self.mask + 1, dtype=np.int32)
        self.n = 0

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """Entry number of each hash, -1 where unknown."""
        at = (hashes & U(self.mask)).astype(np.int64)
        key = self.keys[at]
        out = np.where(key == hashes, self.entry[at], np.int32(-1))
        left = np.flatnonzero((key != hashes) & (key != 0))
        while len(left):
            at = (at[left] + 1) & self.mask if len(at) == len(hashes) else (at + 1) & self.mask
            key = self.keys[at]
            hit = key == hashes[left]
            out[left[hit]] = self.entry[at[hit]]
            go = ~hit & (key != 0)
            left, at = left[go], at[go]
        return out

    def add(self, hashes: np.ndarray) -> None:
        """New distinct hashes get the next entry numbers, in order."""
        entry = np.arange(self.n, self.n + len(hashes), dtype=np.int32)
        self.n += len(hashes)
        at = (hashes & U(self.mask)).astype(np.int64)
        while len(hashes):
            free = self.keys[at] == 0
            where = np.flatnonzero(free)
            _, first = np.unique(at[where], return_index=True)
            won = where[first]
            self.keys[at[won]], self.entry[at[won]] = hashes[won], entry[won]
            lost = np.ones(len(hashes), dtype=bool)
            lost[won] = False
            hashes, entry, at = hashes[lost], entry[lost], (at[lost] + 1) & self.mask


def entries(table: WordTable, texts: Texts, learn: Callable[[list[bytes]], None], forget: Callable[[], None]) -> tuple[np.ndarray, np.ndarray]:
    """Entry number of every word of some texts, and each text's first word.

    ``learn`` is given new words in entry order; ``forget`` is called when the table is emptied.
    """
    hashes, at, starts, ends = texts.words_at()
    hashes = np.maximum(hashes, U(1))
    found = table.find(hashes)
    lost = np.flatnonzero(found < 0)
    if len(lost):
        fresh, first = np.unique(hashes[lost], return_index=True)
        if table.n and table.n + len(fresh) > table.limit:
            table.clear()
            forget()
            lost = np.arange(len(hashes))
            fresh, first = np.unique(hashes, return_index=True)
        while len(fresh) > table.limit:  # a single long text with very many words
            table.mask, table.limit = table.mask * 2 + 1, table.limit * 2
            table.clear()
        raw = texts.data.tobytes()
        pick = lost[first]
        learn([raw[a:b] for a, b in zip(starts[pick].tolist(), ends[pick].tolist())])
        table.add(fresh)
        found[lost] = table.find(hashes[lost])
    return found, at


class Ragged:
    """Rows of int32 of any length in one growing array."""

    def __init__(self):
        self.clear()

    def clear(self) -> None:
        self.values, self.starts, self.sizes = np.zeros(1 << 16, dtype=np.int32), np.zeros(1 << 16, dtype=np.int64), np.zeros(1 << 16, dtype=np.int64)
        self.n = self.used = 0

    def extend(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        while self.used + len(flat) > len(self.values):
            self.values = np.concatenate([self.values, np.zeros_like(self.values)])
        while self.n + len(sizes) > len(self.starts):
            self.starts, self.sizes = (np.concatenate([x, np.zeros_like(x)]) for x in (self.starts, self.sizes))
        self.values[self.used : self.used + len(flat)] = flat
        self.starts[self.n : self.n + len(sizes)] = self.used + np.r_[0, np.cumsum(sizes)[:-1]]
        self.sizes[self.n : self.n + len(sizes)] = sizes
        self.used, self.n = self.used + len(flat), self.n + len(sizes)

    def take(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The chosen rows one after the other, and the offset of each (one more at the end)."""
        sizes = self.sizes[rows]
        off = np.r_[0, np.cumsum(sizes)]
        at = np.repeat(self.starts[rows] - off[:-1], sizes) + np.arange(off[-1])
        return self.values[at], off
