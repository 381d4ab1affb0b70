"""N-gram Jaccard join by a token-group matrix.

A document's tokens are its distinct five-word shingles as 64-bit hashes; equal
sets are one class. Two classes link when 100 * |A n B| >= 80 * |A u B|.

1. Groups: classes with the same smallest token, in one of a few token orders,
   are likely alike (their chance is the similarity itself). Large ones are split into chunks, each
   with the whole group's first class as a common member. Within a chunk all
   pairs are compared by one product of the token-incidence matrix; the links
   give first components: the groups. A class without a link is a group of one.
2. Token-group matrix: of each class the first tokens, in an order that puts
   tokens of many classes last (counted over all of them), count: |A| - ceil(0.8 |A|) + L of them, so
   that linked classes share L of them (fewer only when a class has fewer). A group stores their
   union over its members, one entry for each token, with its range of set sizes
   and a ball in the space of parity bitmaps (its root's bitmap and the largest
   distance of a member from it). A group queries all groups not smaller than
   itself: the unions' overlap bounds the overlap of their members, and so do
   sizes and balls, the latter before a pair is even counted. Tokens that very
   many classes hold are dealt to the cells of a triangle, so no task compares all their groups.
3. Only groups whose bound is met are opened: the query group's classes that
   pass the bounds by themselves are compared with the members, in chunks of
   both. All links join the first ones, and components follow.

No pair within a group is emitted, and no link between different components is
lost: a pair in different first components shares L matrix tokens, so one's
group opens the other's.

Null and empty texts and texts without words have no tokens and link with
nothing, not even each other. Fewer than five words: the whole sequence is the one
token. Repeated rows are one class; equal tokens and sizes are no special case. A very long text
is one set, held whole by the task that makes or compares it. A null doc_id takes part and keeps a null
doc_id; component_id is the smallest doc_id that is not null (null if there is
none). Empty tables give empty results. Other columns are ignored by ``join`` and kept by ``representatives``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import IdFilter, discard, passes, shares, stash, table, tidy
from alignspark.llm.components import components
from alignspark.llm.hashing import U, Texts, batches, deal, mix, segment_hash, undeal, windows

WORDS, SHARE = 5, 80
#: Classes in a chunk and query classes that meet it in a task; matrix tokens that linked classes share; token
#: orders, each of which groups all classes.
CHUNK, ASKERS, OVERLAP, ORDERS = 64, 128, 3, 2
#: How many classes make a token frequent, most tokens in the order's list; tokens that a task counts at a time.
FREQUENT, LISTED, COUNTED = 3, 1 << 20, 1_000_000
#: Classes that make a token hot, most tokens in the list of hot ones; bytes of entries in a bucket.
HOT, HOT_LISTED, BUCKET_BYTES = 4096, 1 << 20, 16 << 20
#: Bits of a set's parity bitmap.
BITS = 512


def token_sets(texts: Texts, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct tokens of every text, sorted, one text after the other, and the offsets of the texts."""
    hashes, at = texts.words(fold=True)
    keys, starts = windows(hashes, at, words)
    count = np.diff(at)
    owner = np.searchsorted(at, starts, side="right") - 1
    short = np.flatnonzero((count > 0) & (count < words))
    if len(short):
        keys = np.r_[keys, segment_hash(hashes, at[short], at[short + 1])]
        owner = np.r_[owner, short]
    order = np.lexsort((keys, owner))
    keys, owner = keys[order], owner[order]
    if len(keys):
        new = np.r_[True, (keys[1:] != keys[:-1]) | (owner[1:] != owner[:-1])]
        keys, owner = keys[new], owner[new]
    return keys, np.searchsorted(owner, np.arange(texts.n + 1))


def class_of(keys: np.ndarray, off: np.ndarray) -> np.ndarray:
    """A 64-bit digest of each token set (as int64); 0 for an empty one."""
    size = np.diff(off)
    out = np.zeros(len(size), dtype=U)
    some = size > 0
    if some.any():
        out[some] = np.add.reduceat(mix(keys + U(3)), off[:-1][some])
        out[some] = np.maximum(mix(out[some] ^ size[some].astype(U)), U(1))
    return out.view(np.int64)


def first_tokens(keys: np.ndarray, off: np.ndarray) -> np.ndarray:
    """The smallest token of each set in each of ``ORDERS`` orders (0 for an empty set): sets x orders."""
    size = np.diff(off)
    out = np.zeros((len(size), ORDERS), dtype=U)
    some = size > 0
    if some.any():
        for h in range(ORDERS):
            out[some, h] = np.minimum.reduceat(mix(keys + U(5 + 2 * h)), off[:-1][some])
    return out.view(np.int64)


def bitmaps(keys: np.ndarray, off: np.ndarray) -> np.ndarray:
    """A parity bitmap of each set: every token flips one of ``BITS`` bits; sets x words of 64 bits.

    Two bitmaps differ in at most as many bits as the sets differ in tokens, which bounds what the sets share.
    """
    n = len(off) - 1
    owner = np.repeat(np.arange(n), np.diff(off))
    bit = (mix(keys + U(21)) % U(BITS)).astype(np.int64)
    parity = np.bincount(owner * BITS + bit, minlength=n * BITS) & 1
    return np.packbits(parity.astype(np.uint8).reshape(n, BITS), axis=1, bitorder="little").view(U)


def rows(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """doc_id, digest of the text, n, cls, firsts and bits of every document."""

    def make(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts:
            for texts in batches(batch):
                keys, off = token_sets(texts, words)
                firsts = pa.ListArray.from_arrays(pa.array(np.arange(texts.n + 1, dtype=np.int32) * ORDERS), pa.array(first_tokens(keys, off).ravel()))
                width = BITS // 64
                bits = pa.ListArray.from_arrays(pa.array(np.arange(texts.n + 1, dtype=np.int32) * width), pa.array(bitmaps(keys, off).view(np.int64).ravel()))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(texts.first, texts.n), batch.column(2).slice(texts.first, texts.n), pa.array(np.diff(off)), pa.array(class_of(keys, off)), firsts, bits],
                    names=["doc_id", "digest", "n", "cls", "firsts", "bits"],
                )
        tidy()

    texts = docs.select("doc_id", "text", _digest(F.col("text")).alias("digest"))
    return texts.mapInArrow(make, "doc_id long, digest long, n long, cls long, firsts array<long>, bits array<long>")


def _sets(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """(spoke, cls, tokens) of documents whose id may be in ``wanted`` (id): to be joined with the ids that speak for classes.

    A task gives each of them once, so rows that repeat a text without an id do not pile up.
    """
    bits = IdFilter.bits(wanted.count())
    held = docs.sparkSession.sparkContext.broadcast(IdFilter.of(wanted, "id", bits).words)

    def make(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for batch in parts:
            if not batch.num_rows:
                continue
            at = np.array(batch.column(2).flatten()).reshape(batch.num_rows, -1)
            batch = batch.filter(pa.array(passes(held.value, at)))
            for texts in batches(batch):
                keys, off = token_sets(texts, words)
                raw = keys.tobytes()
                cut = (off * 8).tolist()
                spoke, cls = batch.column(0).slice(texts.first, texts.n).to_pylist(), class_of(keys, off).tolist()
                new = [i for i, x in enumerate(zip(spoke, cls)) if not (x in seen or seen.add(x))]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([spoke[i] for i in new], pa.int64()), pa.array([cls[i] for i in new], pa.int64()), pa.array([raw[cut[i] : cut[i + 1]] for i in new], pa.binary())],
                    names=["spoke", "cls", "tokens"],
                )
        tidy()

    ids = docs.select(_speaker(F.col("doc_id"), F.col("text")).alias("id"), "text").withColumn("_at", IdFilter.positions(F.col("id"), bits))
    return ids.mapInArrow(make, "spoke long, cls long, tokens binary")


def _digest(text):
    return F.xxhash64(F.coalesce(text, F.lit("")))


def _speaker(doc_id, text):
    """A number for every row, its id where it has one."""
    return F.coalesce(doc_id, _digest(text))


# --- comparing -------------------------------------------------------------------------------------------------------


def linked(sizes_a: np.ndarray, sizes_b: np.ndarray, shared: np.ndarray, share: int) -> np.ndarray:
    return 100 * shared >= share * (sizes_a + sizes_b - shared)


def incidence(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Column numbers of all tokens that two or more of the sets hold, in order, and the set of each."""
    keys = np.concatenate(sets) if sets else np.zeros(0, U)
    order = np.argsort(keys).astype(np.int32)
    keys = keys[order]
    same = keys[1:] == keys[:-1]
    often = np.zeros(len(keys), dtype=bool)
    often[1:] = same
    often[:-1] |= same
    keys, order = keys[often], order[often]
    ends = np.cumsum([len(s) for s in sets])
    owner = np.searchsorted(ends, order, side="right").astype(np.int32)
    new = np.r_[True, keys[1:] != keys[:-1]] if len(keys) else np.zeros(0, bool)
    return np.cumsum(new, dtype=np.int32) - 1, owner


def overlaps(sets: list[np.ndarray], left: int | None = None) -> np.ndarray:
    """|A n B| of all sets with each other, or of the first ``left`` with the rest, by products of bounded blocks."""
    column, owner = incidence(sets)
    n = len(sets)
    out = np.zeros((n if left is None else left, n if left is None else n - left), dtype=np.float32)
    width = max(1, (1 << 20) // max(1, n))
    top = int(column[-1]) + 1 if len(column) else 0
    for lo in range(0, top, width):
        a, b = np.searchsorted(column, [lo, lo + width])
        block = np.zeros((n, min(width, top - lo)), dtype=np.float32)
        block[owner[a:b], column[a:b] - lo] = 1
        out += block @ block.T if left is None else block[:left] @ block[left:].T
    return out.astype(np.int64)


def _forest(n: int, a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Of some links among n sets, enough to hold together what they hold together."""
    up = list(range(n))

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    kept = []
    for x, y in zip(a.tolist(), b.tolist()):
        rx, ry = root(x), root(y)
        if rx != ry:
            up[rx] = ry
            kept.append((x, y))
    return kept


def _tokens(column) -> list[np.ndarray]:
    return [np.frombuffer(x.as_py(), dtype=U) for x in column]


LINKS = "a long, b long"


def _links(pairs: list[tuple[int, int]]) -> pa.Table:
    return pa.table({"a": pa.array([p[0] for p in pairs], pa.int64()), "b": pa.array([p[1] for p in pairs], pa.int64())})


def _chunk_links(share: int):
    def compare(chunk: pa.Table) -> pa.Table:
        ids, place = np.unique(chunk["cls"].to_numpy(), return_index=True)
        sets = _tokens(chunk["tokens"].take(pa.array(place)))
        if len(sets) < 2:
            return _links([])
        size = np.array([len(s) for s in sets])
        a, b = np.nonzero(np.triu(linked(size[:, None], size[None, :], overlaps(sets), share), 1))
        return _links([(int(ids[x]), int(ids[y])) for x, y in _forest(len(sets), a, b)])

    return compare


def _query_links(share: int):
    def compare(chunk: pa.Table) -> pa.Table:
        asks = chunk["asks"].to_numpy()
        ids = chunk["cls"].to_numpy()
        sets = _tokens(chunk["tokens"])
        left, right = np.flatnonzero(asks == 1), np.flatnonzero(asks == 0)
        found: list[tuple[int, int]] = []
        for lo in range(0, len(left), 256):
            part = left[lo : lo + 256]
            for ro in range(0, len(right), 256):
                rest = right[ro : ro + 256]
                shared = overlaps([sets[i] for i in part] + [sets[i] for i in rest], len(part))
                size = np.array([len(s) for s in sets])
                hit = linked(size[part][:, None], size[rest][None, :], shared, share)
                for x in np.flatnonzero(hit.any(axis=1)):  # one link to a group's chunk is enough: its members are together already
                    found.append((int(ids[part[x]]), int(ids[rest[int(hit[x].argmax())]])))
        return _links(found)

    return compare


# --- the join --------------------------------------------------------------------------------------------------------


def frequent_tokens(docs: DataFrame, classes: DataFrame, words: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Tokens that ``FREQUENT`` or more of all classes hold, sorted, and how many do; they only come last in an order.

    Every class counts once in a task: of its texts those speak whose id passes a filter of the classes' ids, so that
    hardly any other is counted. Above ``LISTED`` the commonest are listed. Tokens travel in ``n`` buckets.
    """
    bits = IdFilter.bits(classes.count())
    held = docs.sparkSession.sparkContext.broadcast(IdFilter.of(classes, "id", bits).words)

    def count(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        waiting: list[np.ndarray] = []

        def flush() -> pa.RecordBatch:
            keys, times = np.unique(np.concatenate(waiting), return_counts=True)
            out = list(deal((keys % U(n)).astype(np.int64), [keys, times.astype(np.uint32)]))
            return pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int32()), pa.array([o[1] for o in out], pa.binary())], names=["bucket", "blob"])

        for batch in parts:
            if not batch.num_rows:
                continue
            at = np.array(batch.column(2).flatten()).reshape(batch.num_rows, -1)
            batch = batch.filter(pa.array(passes(held.value, at)))
            for texts in batches(batch):
                keys, off = token_sets(texts, words)
                fresh = np.array([not (c in seen or seen.add(c)) for c in class_of(keys, off).tolist()], dtype=bool)
                waiting.append(keys[np.repeat(fresh, np.diff(off))])
                if sum(map(len, waiting)) > COUNTED:
                    yield flush()
                    waiting = []
        if waiting:
            yield flush()
        tidy()

    def meet(group: pa.Table) -> pa.Table:
        keys, times = undeal(group["blob"].to_pylist(), [U, np.uint32])
        order = np.argsort(keys)
        keys, times = keys[order], times[order].astype(np.int64)
        head = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
        total = np.add.reduceat(times, head) if len(head) else times
        often = total >= FREQUENT
        got = pa.table({"t": pa.array(keys[head][often].view(np.int64)), "n": pa.array(total[often])})
        tidy()
        return got

    ids = docs.select(_speaker(F.col("doc_id"), F.col("text")).alias("id"), "text").withColumn("_at", IdFilter.positions(F.col("id"), bits))
    counted = ids.mapInArrow(count, "bucket int, blob binary").groupBy("bucket").applyInArrow(meet, "t long, n long")
    counted = stash(counted, "frequent")
    # the list's bound: the least count above which it has room for all
    least, listed = FREQUENT, 0
    for times, k in sorted(counted.groupBy("n").agg(F.count("*").alias("k")).collect(), reverse=True):
        listed += k
        if listed > LISTED:
            least = times + 1
            break
    got = counted.where(F.col("n") >= least).toArrow()
    discard(counted)
    token, many = got["t"].to_numpy().view(U), got["n"].to_numpy()
    order = np.argsort(token)
    return token[order], many[order].astype(np.int32)


def _block(cls: np.ndarray, n: int) -> np.ndarray:
    return np.mod(cls, n)


_DEALT = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])


def _blobs(out: list[tuple[int, bytes]], name: str) -> pa.Table:
    return pa.table({name: pa.array([o[0] for o in out], pa.int32()), "blob": pa.array([o[1] for o in out], pa.binary())})


def _shared_tokens(docs: DataFrame, frequent: tuple[np.ndarray, np.ndarray], words: int, share: int, n: int) -> DataFrame:
    """(block, blob) of matrix entries (token, class) whose token two or more classes hold, by block of classes.

    A token that recurs within a task needs no look elsewhere: its entries pass through, and one entry with their
    number speaks for it. Tokens that ``HOT`` or more classes hold are listed too, with that number, in blocks below
    0 (-1 less the number's power of two).
    """
    held = docs.sparkSession.sparkContext.broadcast(frequent)
    hot_from = HOT

    def prefix(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        known, times = held.value
        waiting: list[tuple[np.ndarray, np.ndarray]] = []
        count = 0

        def flush():
            token, cls = (np.concatenate(x) for x in zip(*waiting))
            order = np.argsort(token, kind="stable")
            token, cls = token[order], cls[order]
            head = np.r_[True, token[1:] != token[:-1]]
            size = np.diff(np.r_[np.flatnonzero(head), len(token)])
            again = np.repeat(size > 1, size)
            out = [(b % n, 1, np.int32(b).tobytes() + x) for b, x in deal(_block(cls[again], n), [token[again], cls[again]])]
            t = token[head]
            out += [(b, 0, x) for b, x in deal((t % U(n)).astype(np.int64), [t, cls[head], size.astype(np.uint32)])]
            return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(_DEALT)], schema=_DEALT)

        for batch in parts:
            for texts in batches(batch):
                keys, off = token_sets(texts, words)
                cls = class_of(keys, off)
                late = np.zeros(len(keys), dtype=np.int32)
                if len(known):
                    at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
                    late = np.where(known[at] == keys, times[at], 0)
                size = np.diff(off)
                owner = np.repeat(np.arange(texts.n), size)
                order = np.lexsort((mix(keys + U(9)), late, owner))
                take = np.minimum(size, size - (share * size + 99) // 100 + OVERLAP)
                fresh = np.array([c != 0 and not (c in seen or seen.add(c)) for c in cls.tolist()], dtype=bool)
                place = np.arange(len(keys)) - np.repeat(off[:-1], size)
                keep = (place < np.repeat(take, size)) & np.repeat(fresh, size)
                waiting.append((keys[order][keep], np.repeat(cls, size)[keep]))
                count += int(keep.sum())
                if count > 400_000:
                    yield flush()
                    waiting, count = [], 0
        if count:
            yield flush()
        tidy()

    def meet(group: pa.Table) -> pa.Table:
        kinds, blobs = group["kind"].to_pylist(), group["blob"].to_pylist()
        out = [(int(np.frombuffer(b, np.int32, 1)[0]), b[4:]) for k, b in zip(kinds, blobs) if k == 1]
        token, cls, times = undeal([b for k, b in zip(kinds, blobs) if k == 0], [U, np.int64, np.uint32])
        if len(token):
            order = np.lexsort((cls, token))
            token, cls, times = token[order], cls[order], times[order]
            start = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
            size = np.diff(np.r_[start, len(token)])
            lowest, highest = np.minimum.reduceat(cls, start), np.maximum.reduceat(cls, start)
            hit = np.repeat((lowest != highest) | (np.maximum.reduceat(times, start) > 1), size) & (times == 1)
            out += list(deal(_block(cls[hit], n), [token[hit], cls[hit]]))
            held_by = np.add.reduceat(times.astype(np.int64), start)
            hot = held_by >= hot_from
            power = np.log2(np.maximum(held_by[hot], 1)).astype(np.int64)
            out += [(-1 - b, x) for b, x in deal(power, [token[start][hot], held_by[hot]])]
        tidy()
        return _blobs(out, "block")

    return docs.mapInArrow(prefix, "bucket int, kind int, blob binary").groupBy("bucket").applyInArrow(meet, "block int, blob binary")


def _hot_tokens(shared: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hot tokens, sorted, and how many classes hold each: the hottest, up to ``HOT_LISTED`` of them."""
    sizes = shared.where("block < 0").groupBy("block").agg(F.sum(F.octet_length("blob") / 16).alias("k")).collect()
    least, listed = 0, 0
    for block, k in sorted(sizes):
        listed += k
        if listed > HOT_LISTED:
            break
        least = block
    blobs = [r.blob for r in shared.where(f"block < 0 AND block <= {least}").select("blob").collect()] if least else []
    token, held_by = undeal([bytes(b) for b in blobs], [U, np.int64])
    order = np.argsort(token)
    return token[order], held_by[order]


_ENTRY = [U, np.int64, np.int32, np.int32, np.int32, np.int32, np.uint8, f"V{BITS // 8}"]


def _matrix(shared: DataFrame, speakers: DataFrame, hot: tuple[np.ndarray, np.ndarray], n: int) -> DataFrame:
    """(bucket, blob) of matrix entries: key, group, members, least and largest set, radius, side, centre.

    A group has one entry for each token of its union (made once for each block of classes). The key is the token,
    or a cell of a hot token's triangle: groups are dealt to parts, and the groups of two parts meet in one cell,
    where ``side`` tells the parts apart (0: the cell of one part with itself).
    """
    held = shared.sparkSession.sparkContext.broadcast(hot)
    part = HOT

    def spread(entries: pa.Table, own: pa.Table) -> pa.Table:
        token, cls = undeal(entries["blob"].to_pylist(), [U, np.int64])
        if not len(token):
            return _blobs([], "bucket")
        ids = own["cls"].to_numpy()
        order = np.argsort(ids)
        place = np.minimum(np.searchsorted(ids[order], cls), max(0, len(ids) - 1))
        if not len(ids) or (ids[order][place] != cls).any():
            raise ValueError("a class of the matrix is missing from the classes: the documents changed between two passes")
        at = order[place]
        group = own["group"].to_numpy()[at]
        order = np.lexsort((group, token))
        token, group, at = token[order], group[order], at[order]
        new = np.r_[True, (token[1:] != token[:-1]) | (group[1:] != group[:-1])]
        token, group, at = token[new], group[new], at[new]
        hot_token, held_by = held.value
        parts = np.ones(len(token), np.int64)
        if len(hot_token):
            where = np.minimum(np.searchsorted(hot_token, token), len(hot_token) - 1)
            parts = np.where(hot_token[where] == token, -(-held_by[where] // part), 1)
        # every entry once, those of hot tokens once for each part that they have to meet
        own_part = (mix(group.view(U) + U(31)) % parts.astype(U)).astype(np.int64)
        entry = np.repeat(np.arange(len(token)), parts)
        other = np.arange(len(entry)) - np.repeat(np.cumsum(parts) - parts, parts)
        mine, many = own_part[entry], parts[entry]
        cell = np.minimum(mine, other) * many + np.maximum(mine, other)
        key = np.where(many > 1, mix(token[entry] ^ mix(cell.astype(U) + U(1))), token[entry])
        side = np.where(mine == other, 0, np.where(mine < other, 1, 2)).astype(np.uint8)
        at = at[entry]
        centre = np.ascontiguousarray(own["centre"].combine_chunks().flatten().to_numpy().reshape(-1, BITS // 64)).view(f"V{BITS // 8}").ravel()
        columns = [key, group[entry], *(own[c].to_numpy()[at].astype(np.int32) for c in ("members", "lo", "hi", "radius")), side, centre[at]]
        made = list(deal((key % U(n)).astype(np.int64), columns))
        tidy()
        return _blobs(made, "bucket")

    placed = speakers.select("cls", "group", "members", "lo", "hi", "radius", "centre", F.pmod("cls", F.lit(n)).cast("int").alias("block"))
    return shared.where("block >= 0").groupBy("block").cogroup(placed.groupBy("block")).applyInArrow(spread, "bucket int, blob binary")


PAIRS = 1 << 17


def _pairs(later: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Every entry with each of the ``later`` entries that follow it, in bounded blocks."""
    cost = np.r_[0, np.cumsum(later)]
    at = 0
    while at < len(later):
        upto = max(at + 1, int(np.searchsorted(cost, cost[at] + PAIRS, side="right")) - 1)
        left = np.repeat(np.arange(at, upto), later[at:upto])
        if len(left):
            yield left, left + 1 + np.arange(len(left)) - (cost[left] - cost[at])
        at = upto


def _tally(left: np.ndarray, right: np.ndarray, n: np.ndarray, need: np.ndarray) -> tuple[np.ndarray, ...]:
    """Sums ``n`` by (left, right), which have one ``need``."""
    order = np.lexsort((right, left))
    left, right, n, need = left[order], right[order], n[order], need[order]
    head = np.flatnonzero(np.r_[True, (left[1:] != left[:-1]) | (right[1:] != right[:-1])]) if len(left) else np.zeros(0, np.int64)
    return left[head], right[head], np.add.reduceat(n, head) if len(head) else n, need[head]


def _openings(entries: DataFrame, share: int) -> DataFrame:
    """(asker, group): groups whose unions share as many matrix tokens as a link between members would.

    A shared token counts where the sizes and the balls of the two groups allow a link.
    """

    def meet(bucket: pa.Table) -> pa.Table:
        key, group, members, lo, hi, radius, side, centre = undeal(bucket["blob"].to_pylist(), _ENTRY)
        order = np.lexsort((group, members, key))
        key, group = key[order], group[order]
        new = np.r_[True, (key[1:] != key[:-1]) | (group[1:] != group[:-1])] if len(key) else np.zeros(0, bool)
        key, group, order = key[new], group[new], order[new]
        lo, hi, radius, side = lo[order].astype(np.int64), hi[order].astype(np.int64), radius[order], side[order]
        centre = np.frombuffer(centre[order].tobytes(), dtype=U).reshape(-1, BITS // 64)
        need = np.minimum(OVERLAP, (lo * share + 99) // 100)
        empty = np.zeros(0, np.int64)
        got = [(empty, empty, empty, empty)]
        held = 0
        if len(key):
            stop = np.r_[np.flatnonzero(key[1:] != key[:-1]) + 1, len(key)]
            size = np.diff(np.r_[0, stop])
            # entries stand by size of group: an entry asks those that follow
            for a, b in _pairs(np.repeat(stop, size) - 1 - np.arange(len(key))):
                fits = (100 * hi[a] >= share * lo[b]) & (100 * hi[b] >= share * lo[a]) & ((side[a] == 0) | (side[a] != side[b]))
                a, b = a[fits], b[fits]
                # what two sets share is at most half of their sizes less the bits in which they differ
                apart = np.bitwise_count(centre[a] ^ centre[b]).sum(axis=1, dtype=np.int64) - radius[a] - radius[b]
                open_ = (100 - share) * (hi[a] + hi[b]) >= (100 + share) * apart
                a, b = a[open_], b[open_]
                got.append(_tally(group[a], group[b], np.ones(len(a), np.int64), np.minimum(need[a], need[b])))
                held += len(got[-1][0])
                if held > 4 * PAIRS:
                    got = [_tally(*(np.concatenate(x) for x in zip(*got)))]
                    held = 0
        asker, asked, shared, need = _tally(*(np.concatenate(x) for x in zip(*got)))
        tidy()
        return pa.table({"asker": asker, "group": asked, "shared": shared, "need": need})

    met = entries.groupBy("bucket").applyInArrow(meet, "asker long, group long, shared long, need long")
    return met.groupBy("asker", "group").agg(F.sum("shared").alias("shared"), F.min("need").alias("need")).where("shared >= need").select("asker", "group")


def _apart(a: str, b: str):
    """Bits in which two bitmaps (arrays of longs) differ."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, k: s + k)


def _first_links(docs: DataFrame, classes: DataFrame, words: int, share: int) -> DataFrame:
    """Links found within the chunks of classes that have a first token in common."""
    spoken = classes.select("cls", "id", F.posexplode("firsts").alias("h", "first"))
    sizes = spoken.groupBy("h", "first").agg(F.count("*").alias("k"), F.min("cls").alias("lead"), F.bit_xor("cls").alias("a"), F.bit_xor(F.xxhash64("cls")).alias("b")).where("k > 1")
    # groups of the same members under another order are compared once
    sizes = sizes.groupBy("k", "a", "b", "lead").agg(F.min(F.struct("h", "first")).alias("g")).select("k", "lead", "g.h", "g.first")
    grouped = stash(spoken.join(sizes, ["h", "first"]).select("cls", "id", "h", "first", "k", "lead"), "first-groups")
    sets = _sets(docs, grouped, words)
    chunks = F.ceil(F.col("k") / F.lit(CHUNK)).cast("int")
    member = grouped.select("cls", "id", "h", "first", F.when(F.col("cls") == F.col("lead"), F.sequence(F.lit(0), chunks - 1)).otherwise(F.array(F.pmod(F.xxhash64("cls", "h"), chunks).cast("int"))).alias("c"))
    member = member.select("cls", "id", "h", "first", F.explode("c").alias("c"))
    near = member.join(sets, "cls").where("spoke = id").groupBy("h", "first", "c").applyInArrow(_chunk_links(share), LINKS)
    near = stash(near, "links")
    discard(grouped)
    return near


def _far_links(docs: DataFrame, speakers: DataFrame, opened: DataFrame, words: int, share: int) -> DataFrame:
    """Links between the classes of querying groups and the members of the groups that they open."""
    groups = speakers.where("cls = group").select("group", "members", "lo", "hi", "radius", F.col("centre"))
    asking = opened.join(speakers.select(F.col("group").alias("asker"), "cls", "id", "n", "bits"), "asker").join(groups, "group")
    possible = (
        (100 * F.col("n") >= share * F.col("lo")) & (100 * F.col("hi") >= share * F.col("n"))
        & ((100 - share) * (F.col("n") + F.col("hi")) >= (100 + share) * (_apart("bits", "centre") - F.col("radius")))
    )
    asks = stash(asking.where(possible).select("cls", "id", "group", "members"), "asks")
    slots = F.ceil(F.count("*") / F.lit(ASKERS)).cast("int")
    asked = asks.groupBy("group").agg(slots.alias("slots"))
    inside = stash(speakers.select("cls", "id", "group", "members").join(asked, "group"), "asked")
    wanted = stash(asks.select("cls", "id").unionByName(inside.select("cls", "id")).distinct(), "wanted")
    sets = _sets(docs, wanted, words)
    pieces = F.ceil(F.col("members") / F.lit(CHUNK)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    of = lambda n: F.pmod(F.xxhash64("cls"), n).cast("int")
    right = inside.select("cls", "id", "group", of(pieces).alias("c"), every(F.col("slots")).alias("s"), F.lit(0).alias("asks"))
    left = asks.join(asked, "group").select("cls", "id", "group", every(pieces).alias("c"), of(F.col("slots")).alias("s"), F.lit(1).alias("asks"))
    far = left.unionByName(right).join(sets, "cls").where("spoke = id").groupBy("group", "c", "s").applyInArrow(_query_links(share), LINKS)
    far = stash(far, "links")
    discard(asks, inside, wanted)
    return far


def _named(docs: DataFrame, words: int, share: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, digest, n, cls) of every row of ``docs``, and (cls, root, component_id) of every class; no tokens: cls 0."""
    listed = stash(rows(docs, words), "token-rows")
    texts = docs.select("doc_id", "text")
    speaker = F.coalesce("doc_id", "digest")
    classes = listed.where("cls <> 0").groupBy("cls").agg(
        F.min(speaker).alias("id"), F.min("doc_id").alias("least"), F.first("n").alias("n"), F.first("firsts").alias("firsts"), F.first("bits").alias("bits"))
    classes = stash(classes, "classes")
    # 1. groups
    near = _first_links(texts, classes, words, share)
    first = components(near)
    centres = classes.select(F.col("cls").alias("group"), F.col("bits").alias("centre"))
    several = classes.join(first.select(F.col("node").alias("cls"), F.col("root").alias("group")), "cls").select("cls", "n", "bits", "group")
    balls = several.join(centres, "group").groupBy("group").agg(
        F.count("*").alias("members"), F.min("n").alias("lo"), F.max("n").alias("hi"), F.max(_apart("bits", "centre")).alias("radius"))
    placed = several.select("cls", "group").join(balls.join(centres, "group"), "group")
    alone = lambda name, other: F.coalesce(name, other).alias(name)
    speakers = stash(classes.join(placed, "cls", "left").select(
        "cls", "id", "n", "bits", alone("group", F.col("cls")), alone("members", F.lit(1)), alone("lo", F.col("n")), alone("hi", F.col("n")),
        alone("radius", F.lit(0)), alone("centre", F.col("bits"))), "speakers")
    # 2. the matrix
    tokens, n_classes = classes.agg(F.sum("n"), F.count("*")).first()
    entries = (100 - share) * (tokens or 0) // 100 + OVERLAP * n_classes
    n = shares(docs.sparkSession, entries * sum(np.dtype(k).itemsize for k in _ENTRY) // 4, BUCKET_BYTES)
    # a token and its count in 12 bytes
    often = frequent_tokens(texts, classes, words, shares(docs.sparkSession, 12 * (tokens or 0), BUCKET_BYTES))
    shared = stash(_shared_tokens(texts, often, words, share, n), "matrix-tokens")
    opened = stash(_openings(_matrix(shared, speakers, _hot_tokens(shared), n), share), "opened")
    discard(shared)
    # 3. open the groups
    far = _far_links(texts, speakers, opened, words, share)
    last = components(near.unionByName(far))
    ids = classes.select("cls", "least").join(last.withColumnRenamed("node", "cls"), "cls", "left").select("cls", "least", F.coalesce("root", "cls").alias("root"))
    lowest = ids.groupBy("root").agg(F.min("least").alias("component_id"))
    named = stash(ids.select("cls", "root").join(lowest, "root").select("cls", "root", "component_id"), "named")
    discard(first, speakers, opened, near, far, last, classes)
    return listed.select("doc_id", "digest", "n", "cls"), named


def join(docs: DataFrame, words: int = WORDS, share: int = SHARE) -> DataFrame:
    """doc_id, n_shingles, component_id and links' class of every row of ``docs``."""
    listed, named = _named(docs, words, share)
    return listed.join(named, "cls", "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("cls") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "cls"
    )


def representatives(docs: DataFrame, words: int = WORDS, share: int = SHARE) -> DataFrame:
    """One row of each component (of the id that names it; any one if no row has an id), and all without tokens; columns as in ``docs``.

    A row's key is its id, which may be null, and its text's digest. Rows that
    repeat the key of a component's row are counted, and one of them is kept.
    """
    listed, named = _named(docs, words, share)
    rooted = listed.join(named.select("cls", "root"), "cls", "left").select("doc_id", "digest", F.coalesce("root", F.lit(0)).alias("root"))
    copies = rooted.groupBy("root", "doc_id", "digest").agg(F.count("*").alias("copies"))
    # a row without tokens is a component of its own
    own = [F.when(F.col("root") == 0, F.col(name)).alias(f"own_{name}") for name in ("doc_id", "digest")]
    key = F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "digest", "copies")).alias("key")
    chosen = copies.groupBy("root", *own).agg(key)
    several = ((F.col("root") != 0) & (F.col("key.copies") > 1)).alias("several")
    keep = stash(chosen.select(F.col("key.doc_id").alias("kept_id"), F.col("key.digest").alias("kept_digest"), several), "kept")

    def rows_of(keys: DataFrame) -> DataFrame:
        return docs.join(keys, docs["doc_id"].eqNullSafe(keys["kept_id"]) & (_digest(docs["text"]) == keys["kept_digest"]), "left_semi")

    repeated = keep.where("several")
    if repeated.isEmpty():
        return rows_of(keep)
    return rows_of(keep.where("NOT several")).union(rows_of(repeated).dropDuplicates(["doc_id", "text"]))


def op1_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its component of near copies."""
    return join(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")
