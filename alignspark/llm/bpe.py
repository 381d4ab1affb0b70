"""BPE encoding and decoding by batched numpy merge rounds.

The symbols of many words stand in one flat array. Each round finds, for every
adjacent pair within a word, its rank by binary search over the sorted pair keys
of the merge table, takes the lowest-ranked pair of each word (leftmost first,
all its non-overlapping occurrences), merges, and compacts the array; it ends
when no word has a pair left to merge. A word of over ``LONG`` bytes, for which
every round would pass over the whole word again, takes its merges one by one in
the same order (rank, then place) from a queue. Text first goes through the vocabulary's
own rules: special strings apart, NFC, white space, lower case by single
characters, the split pattern, and the byte alphabet. Distinct white-space
delimited pieces are encoded once and remembered up to a bound.

A null text is empty: no ids, empty decoded text. Texts of any length are encoded
whole. Ranks are distinct, so the only ties are places, and the left one goes
first. Repeated rows give repeated results. An empty table gives an empty
result. Other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from alignspark.llm.common import table, tidy
from alignspark.llm.hashing import Texts, batches
from alignspark.llm.vocabulary import vocabulary_path
from alignspark.llm.wordtable import Ragged, WordTable, entries

#: Bits of a worker's word table; bytes from which a word is merged from a queue.
BITS, LONG = 20, 1000


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte: printable Latin-1 bytes are themselves, the rest follow from U+0100."""
    own = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


class MergeTable:
    """Vocabulary and merges as arrays."""

    def __init__(self, path: str):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab: dict[str, int] = model["vocab"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = [""] * (max([*vocab.values(), *self.special.values()]) + 1)
        for text, i in {**vocab, **self.special}.items():
            self.tokens[i] = text
        self.size = len(self.tokens)
        letters = byte_alphabet()
        self.plain = np.array([vocab.get(c, -1) for c in letters], dtype=np.int64)
        self.final = np.array([vocab.get(c + self.suffix, -1) for c in letters], dtype=np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        left = np.array([vocab[a] for a, _ in pairs], dtype=np.int64)
        right = np.array([vocab[b] for _, b in pairs], dtype=np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], dtype=np.int64)
        keys = left * self.size + right
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.made = keys[order], order, made[order]
        self.pairs: dict[int, tuple[int, int]] = {}
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")["pattern"]["Regex"]
        self.pattern = regex.compile(split + r"|\n")
        self.specials = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None

    # one word is the UTF-8 bytes of a pre-token

    def words(self, text: str) -> list[str]:
        """Pre-tokens (and line feeds) of a text without special strings."""
        if not text.isascii():
            # only the capital sigma has a lower case that depends on its place; the vocabulary's rules know none
            text = unicodedata.normalize("NFC", text).replace("\u03a3", "\u03c3")
        return self.pattern.findall(text.lower())

    def parts(self, pieces: list[bytes]) -> tuple[list[str | int], np.ndarray, np.ndarray]:
        """The distinct pre-tokens (and ids of special strings) of some pieces; all of them by number, and each one's piece."""
        whole = b"\n".join(pieces).decode("utf-8")
        found: list[str | int] = []
        at = 0
        if self.specials is not None and "<|" in whole:
            for m in self.specials.finditer(whole):
                found += self.words(whole[at : m.start()])
                found.append(self.special[m.group()])
                at = m.end()
        found += self.words(whole[at:])
        distinct = [*(set(found) - {"\n"})]
        place: dict[str | int, int] = dict(zip(distinct, range(len(distinct))))
        place["\n"] = -1
        numbers = np.array(list(map(place.__getitem__, found)), dtype=np.int64)
        cut = numbers < 0
        return distinct, numbers[~cut], np.cumsum(cut)[~cut]

    def assemble(self, pieces: list[bytes], encode: Callable[[list[str]], tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces one after the other and their counts, from ids (and counts) of distinct words."""
        distinct, numbers, owner = self.parts(pieces)
        plain = [w for w in distinct if isinstance(w, str)]
        ids, sizes = encode(plain)
        if len(plain) < len(distinct):
            is_word = np.array([isinstance(w, str) for w in distinct])
            order = np.r_[np.flatnonzero(is_word), np.flatnonzero(~is_word)]
            ids = np.r_[ids, [w for w in distinct if not isinstance(w, str)]]
            sizes = np.r_[sizes, np.ones(len(distinct) - len(plain), dtype=np.int64)]
            numbers = np.argsort(order)[numbers]
        words = Ragged()
        words.extend(ids.astype(np.int32), sizes)
        flat, off = words.take(numbers)
        return flat, np.bincount(owner, weights=np.diff(off), minlength=len(pieces)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row in the pair table (or -1) and rank (or a large number) of each pair."""
        key = left * self.size + right
        row = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[row] == key
        return np.where(hit, row, -1), np.where(hit, self.rank[row], 1 << 40)

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in one array, and the offset of each word (one more at the end)."""
        sizes = np.array([len(w) for w in words], dtype=np.int64)
        raw = np.frombuffer(b"".join(words), dtype=np.uint8)
        symbols = self.plain[raw]
        last = np.cumsum(sizes) - 1
        symbols[last] = self.final[raw[last]]
        owner = np.repeat(np.arange(len(words)), sizes)
        done_ids, done_owner = [], []
        for w in np.flatnonzero(sizes > LONG).tolist():
            done_ids.append(self.merge_long(symbols[last[w] + 1 - sizes[w] : last[w] + 1]))
            done_owner.append(np.full(len(done_ids[-1]), w))
        short = np.repeat(sizes <= LONG, sizes)
        symbols, owner = symbols[short], owner[short]
        while len(symbols):
            inner = owner[1:] == owner[:-1]
            row, rank = self.ranks(symbols[:-1], symbols[1:])
            rank = np.where(inner, rank, 1 << 40)
            first = np.flatnonzero(np.r_[True, ~inner])
            # lowest rank of each word; words of one symbol have no pair of their own
            best = np.minimum.reduceat(np.r_[rank, 1 << 40], first)
            length = np.diff(np.r_[first, len(symbols)])
            best_each = np.repeat(best, length)
            live = best_each < 1 << 40
            if not live.all():
                done_ids.append(symbols[~live])
                done_owner.append(owner[~live])
                symbols, owner, best_each = symbols[live], owner[live], best_each[live]
                row, rank = np.r_[row, -1][live], np.r_[rank, 1 << 40][live]
            else:
                row, rank = np.r_[row, -1], np.r_[rank, 1 << 40]
            if not len(symbols):
                break
            take = rank == best_each
            # overlapping hits (a pair of equal symbols in a run): every second one from the left
            at = np.flatnonzero(take)
            if len(at) > 1:
                close = np.r_[False, np.diff(at) == 1]
                if close.any():
                    head = np.maximum.accumulate(np.where(~close, np.arange(len(at)), 0))
                    take[at[(np.arange(len(at)) - head) % 2 == 1]] = False
                    at = np.flatnonzero(take)
            symbols[at] = self.made[row[at]]
            keep = np.ones(len(symbols), dtype=bool)
            keep[at + 1] = False
            symbols, owner = symbols[keep], owner[keep]
        ids = np.concatenate(done_ids) if done_ids else np.zeros(0, np.int64)
        who = np.concatenate(done_owner) if done_owner else np.zeros(0, np.int64)
        order = np.argsort(who, kind="stable")
        return ids[order], np.r_[0, np.cumsum(np.bincount(who, minlength=len(words)))]

    def merge_long(self, symbols: np.ndarray) -> np.ndarray:
        """Ids of one long word: its merges by rank and place, those it starts with in sorted order, new ones from a heap."""
        if not self.pairs:
            self.pairs = dict(zip(self.keys.tolist(), zip(self.rank.tolist(), self.made.tolist())))
        n, size, known = len(symbols), self.size, self.pairs.get
        _, rank = self.ranks(symbols[:-1], symbols[1:])
        order = np.argsort(rank, kind="stable")
        order = order[: int((rank < 1 << 40).sum())]
        sym, after, before = (array("i", x.astype("i4").tobytes()) for x in (symbols, np.arange(1, n + 1), np.arange(-1, n - 1)))
        sorted_ones = ((r, i) for lo in range(0, len(order), 1 << 16) for r, i in zip(rank[order[lo : lo + (1 << 16)]].tolist(), order[lo : lo + (1 << 16)].tolist()))
        head, fresh = next(sorted_ones, None), []
        while head or fresh:
            if fresh and (head is None or fresh[0] < head):
                r, i = heapq.heappop(fresh)
            else:
                (r, i), head = head, next(sorted_ones, None)
            j = after[i]
            if sym[i] < 0 or j >= n:
                continue
            pair = known(sym[i] * size + sym[j])
            if pair is None or pair[0] != r:
                continue
            sym[i], sym[j] = pair[1], -1
            k, h = after[j], before[i]
            after[i] = k
            if k < n:
                before[k] = i
                if pair := known(sym[i] * size + sym[k]):
                    heapq.heappush(fresh, (pair[0], i))
            if h >= 0 and (pair := known(sym[h] * size + sym[i])):
                heapq.heappush(fresh, (pair[0], h))
        out = np.frombuffer(sym, dtype="i4")
        return out[out >= 0].astype(np.int64)

    def decode(self, ids) -> str:
        """No decoder is set in the vocabulary: its tokens joined by spaces."""
        return " ".join([self.tokens[i] for i in ids])


class Spelling:
    """Byte strings by id, for joining whole runs at once: each is followed by a blank."""

    def __init__(self, texts: list[bytes]):
        self.rows = Ragged()
        sizes = np.array([len(t) + 1 for t in texts], dtype=np.int64)
        self.rows.extend(np.frombuffer(b" ".join(texts) + b" ", dtype=np.uint8), sizes)
        self.rows.values = self.rows.values.astype(np.uint8)

    def join(self, ids: np.ndarray, off: np.ndarray) -> list[memoryview]:
        """For each run ``ids[off[i]:off[i+1]]`` its strings joined by single blanks."""
        out = []
        for lo in range(0, len(off) - 1, 256):  # a few hundred texts at a time bound the memory
            part = off[lo : lo + 257]
            flat, at = self.rows.take(ids[part[0] : part[-1]])
            raw, cut = memoryview(flat), at[part - part[0]].tolist()
            out += [raw[a : max(a, b - 1)] for a, b in zip(cut[:-1], cut[1:])]
        return out


class PieceCoder:
    """Ids of whole runs of texts, remembering those of distinct pieces."""

    def __init__(self, path: str):
        self.rules = MergeTable(path)
        self.table, self.ids = WordTable(BITS), Ragged()
        self.decimal = Spelling([str(i).encode() for i in range(self.rules.size)])
        self.tokens = Spelling([t.encode("utf-8") for t in self.rules.tokens])

    def words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids, at = self.rules.merge([w.encode("utf-8") for w in words]) if words else (np.zeros(0, np.int64), np.zeros(1, np.int64))
        return ids, np.diff(at)

    def learn(self, pieces: list[bytes]) -> None:
        self.ids.extend(*self.rules.assemble(pieces, self.words))

    def encode(self, texts: Texts) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and the id offsets of the texts."""
        rows, at = entries(self.table, texts, self.learn, self.ids.clear)
        ids, off = self.ids.take(rows)
        return ids, off[at]


_CODERS: dict[str, PieceCoder] = {}


def coder_of(path: str) -> PieceCoder:
    """One coder for each worker process: tasks share what it remembers."""
    if path not in _CODERS:
        _CODERS[path] = PieceCoder(path)
    return _CODERS[path]


def encode(docs: DataFrame, tokenizer: str | None = None, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and (unless switched off) ids of every document."""
    tokenizer = tokenizer or vocabulary_path()

    def coded(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_of(tokenizer)
        for batch in parts:
            for texts in batches(batch):
                ids, off = coder.encode(texts)
                out = [
                    batch.column(0).slice(texts.first, texts.n), pa.array(np.diff(off)),
                    pa.array([hashlib.sha256(x).hexdigest() for x in coder.decimal.join(ids, off)], pa.string()),
                    pa.array([hashlib.sha256(x).hexdigest() for x in coder.tokens.join(ids, off)], pa.string()),
                ]
                if with_ids:
                    out.append(pa.ListArray.from_arrays(pa.array(off.astype(np.int32)), pa.array(ids)))
                yield pa.RecordBatch.from_arrays(out, names=names)
        tidy()

    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * with_ids
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return docs.select("doc_id", "text").mapInArrow(coded, schema)


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded and decoded; digests of both."""
    return encode(table(spark, sf_dir, "documents"), with_ids=False)
