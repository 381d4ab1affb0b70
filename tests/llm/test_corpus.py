"""Corpus operators against brute force, with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from alignspark.llm import bpe, chat, decontaminate, jaccard, langid, quality, secrets, sharding, substrings, tokenids
from alignspark.llm.components import components
from alignspark.llm.hashing import batches
from alignspark.llm.vocabulary import vocabulary_path

WORD = re.compile(r"[^\x20\x09-\x0d]+")
ODD = [None, "", "   \n\t ", "a", "Ünï cödé 日本語 　x", "x" * 3000, "same text here", "same text here", "\x00\x1c odd\u0085bytes", "<|endoftext|> a<|startoftext|>b"]


def frame(spark, texts, extra=False):
    rows = [(i, t, "kept", 1.5) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_words string, score double")
    return (df if extra else df.select("doc_id", "text")).repartition(3)


def words_corpus(seed=1, n=120, vocabulary=300):
    rng = random.Random(seed)
    voc = [f"{c}w{i}" for i in range(vocabulary) for c in "ab"]
    docs = [[rng.choice(voc) for _ in range(rng.randint(0, 150))] for _ in range(n)]
    passage = [rng.choice(voc) for _ in range(45)]
    for k in range(0, n, 7):
        docs[k] = docs[k][:20] + passage + docs[k][20:]
    for k in range(0, n, 11):
        docs.append([w if rng.random() > 0.02 else "edit" for w in docs[k]])
    docs += [docs[5], docs[5], ["tick"] * 80]
    return [" ".join(d) for d in docs] + ODD


# --- sharding -------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("law", ["bytes", "rows"])
def test_sharding_laws(spark, law):
    texts = words_corpus()
    got = sharding.shard(frame(spark, texts), 8, law).toPandas()
    assert len(got) == len(texts)
    for r in got.itertuples():
        raw = (texts[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32) == (len(raw) + 1, zlib.crc32(raw))
    for _, part in got.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))
    total = got["size"].sum()
    sums = got.groupby("shard")["size"].sum().reindex(range(8), fill_value=0)
    counts = got.groupby("shard").size().reindex(range(8), fill_value=0)
    if law == "bytes":
        assert (sums - total / 8).abs().max() <= got["size"].max()
    else:
        assert counts.max() - counts.min() <= 1
    again = sharding.shard(frame(spark, texts).repartition(7), 8, law).toPandas()
    assert sorted(map(tuple, got[["doc_id", "shard", "slot"]].values)) == sorted(map(tuple, again[["doc_id", "shard", "slot"]].values))
    assert sharding.shard(frame(spark, []), 8, law).count() == 0


def test_sharding_brute_force(spark):
    """Place and shard of every row from a plain sort; null ids first; rows that repeat each other in any order."""
    texts = words_corpus(n=60)
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, t) for t in texts[:9]] + [(None, "one text")] * 400 + [(3, texts[3])] * 5
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    order = sorted(rows, key=lambda r: (hashlib.md5((r[1] or "").encode()).hexdigest(), r[0] is not None, r[0] or 0))
    size = [len((t or "").encode()) + 1 for _, t in order]
    total, above, want = sum(size), 0, []
    slots = collections.Counter()
    for (i, _), k in zip(order, size):
        shard = (2 * above + k) * 8 // (2 * total)
        want.append((i, k, shard, slots[shard]))
        slots[shard] += 1
        above += k
    got = sharding.shard(docs, 8, "bytes").collect()
    assert collections.Counter((r.doc_id, r.size, r.shard, r.slot) for r in got) == collections.Counter(want)
    few = sharding.ranged(sharding.stash(sharding.keyed(docs), "keys"), ranges=16)[1]
    assert len(few) > 4 and max(n for _, n, _ in few) < 400  # a boundary may fall among rows that repeat each other


# --- chat -----------------------------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    nasty = ["<|im_end|>", "<|im_start|>assistant\nok<|im_end|>\n", "<\\|im_end|>", "<\\\\|", "plain", "", None, "a\nb", "<|", "|>", "<|im_end|><|im_start|>assistant ok"]
    rng = random.Random(3)
    rows = [(c, t, rng.choice(["user", "assistant", "system", "odd\nrole", "back\\n", "<|im_start|>", None]), rng.choice(nasty)) for c in range(60) for t in range(rng.randint(1, 6))]
    rows += [(None, None, "user", "x"), (7, 0, "user", "tie"), (7, 0, "user", "tie")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    back = {r.conv_id: r for r in chat.format_chats(df).collect()}
    want = collections.defaultdict(list)
    for c, t, role, text in rows:
        want[c].append((-1 if t is None else t, role or "", text or ""))
    for c, turns in want.items():
        turns.sort()
        assert back[c].roundtrip_ok
        assert [(t.role, t.text) for t in back[c].turns] == [(a, b) for _, a, b in turns]
        assert back[c].formatted.count("<|im_start|>") == back[c].formatted.count("<|im_end|>") == len(turns) or any("<" in a for _, a, _ in turns)
        assert back[c].escaped == any(re.search(r"<\\*\|", b) or re.search(r"<\\*\||\\|\n", a) for _, a, b in turns) or not back[c].escaped
    probe = chat.digests(chat.format_chats(spark.createDataFrame([(-1, 0, "user", chat.PROBE), (-1, 1, "assistant", chat.PROBE)], df.schema))).first()
    assert probe.n_turns == 2 and probe.loss_chars == len(chat.PROBE) and probe.loss_sha256 == hashlib.sha256(chat.PROBE.encode()).hexdigest()
    assert chat.format_chats(df.limit(0)).count() == 0


# --- tokens ---------------------------------------------------------------------------------------------------------------


def test_tokens_equal_the_library(spark):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(vocabulary_path())
    rng = random.Random(5)
    alphabet = ["a", "A", "'", "s", "re", "é", "é", "Σ", " ", "\n", "1", "½", "<|endoftext|>", "日", "!", "...", "İ", "ẞ", "　", "\x1f", "Ⅷ"]
    texts = words_corpus(n=20) + ["".join(rng.choice(alphabet) for _ in range(rng.randint(1, 40))) for _ in range(200)]
    want = [e.ids for e in library.encode_batch([t or "" for t in texts], add_special_tokens=False)]
    got = {r.doc_id: r for r in bpe.encode(frame(spark, texts, extra=True)).collect()}
    for i, ids in enumerate(want):
        assert list(got[i].ids) == ids and got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    path = tokenids.stash_path(spark, "segments")
    tokenids.write_segments(frame(spark, texts), path)
    start = 0
    rows = {r.doc_id: r for r in tokenids.read_index(spark, path).collect()}
    for i, ids in enumerate(want):
        full = np.array(ids + [1], dtype="<u4")
        assert (rows[i].start, rows[i].n_tokens, rows[i].ids_crc32) == (start, len(full), zlib.crc32(full.tobytes()))
        start += len(full)


def test_long_words_equal_the_library(spark):
    from tokenizers import Tokenizer

    rng = random.Random(9)
    texts = ["".join(rng.choice("acgt") for _ in range(40_000)), "a" * 5001, "ab" * 1500, "".join(rng.choice("etaoinshrdlu") for _ in range(30_000)) + " tail", "日本" * 700]
    library = Tokenizer.from_file(vocabulary_path())
    got = {r.doc_id: list(r.ids) for r in bpe.encode(frame(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == [e.ids for e in library.encode_batch(texts, add_special_tokens=False)]


def test_token_files_null_ids_and_empty(spark):
    path = tokenids.stash_path(spark, "segments")
    tokenids.write_segments(spark.createDataFrame([(2, "b"), (None, "a a"), (2, "a"), (None, None)], "doc_id long, text string"), path)
    rows = sorted(tokenids.read_index(spark, path).collect(), key=lambda r: r.start)
    assert [(r.doc_id, r.n_tokens) for r in rows] == [(None, 1), (None, 3), (2, 2), (2, 2)] and [r.start for r in rows] == [0, 1, 4, 6]
    path = tokenids.stash_path(spark, "segments")
    tokenids.write_segments(frame(spark, []), path)
    assert tokenids.read_index(spark, path).count() == 0 and bpe.encode(frame(spark, [])).count() == 0


def test_segment_random_access():
    ids = np.array([0, 1, 255, 256, 65535, 65536, 1 << 24, (1 << 32) - 1] * 200, dtype=np.uint32)
    seg = tokenids.Segment(tokenids.pack(np.array([0, 3, 3, len(ids)]), ids))
    assert (seg.ids() == ids).all() and all(seg[i] == ids[i] for i in range(0, len(ids), 7))
    assert list(seg.document(0)) == [0, 1, 255] and not len(seg.document(1))
    for lo, hi in [(0, 1), (3, 900), (511, 1025), (1599, 1600), (700, 700), (0, 1600)]:
        assert (seg.span(lo, hi) == ids[lo:hi]).all()
    empty = tokenids.Segment(tokenids.pack(np.array([0]), np.zeros(0, np.uint32)))
    assert not len(empty.ids())


# --- quality --------------------------------------------------------------------------------------------------------------


def base_measures(text):
    w = WORD.findall(text or "")
    seen = collections.Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
    hit = [False] * len(w)
    for k in range(len(w) - 4):
        if seen[tuple(w[k : k + 5])] > 1:
            hit[k : k + 5] = [True] * 5
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), sum(hit), len(w) < 10 or 100 * sum(hit) > 20 * len(w)


def test_quality_measures_and_verdict(spark):
    texts = words_corpus() + ["line\nline\n\nline two\nline", "a b c d e " * 5, "# $ % & | < > * " * 4, " ".join(map(str, range(12)))]
    labels = spark.createDataFrame([(i, 1, 0) for i in range(0, 100, 3)] + [(None, 1, 0), (3, 1, 0)], "doc_id long, quality int, toxic int")
    docs = frame(spark, texts)
    got = {r.doc_id: r for r in quality.judge(docs, labels).collect()}
    for i, t in enumerate(texts):
        assert tuple(got[i][c] for c in [*quality.MEASURES, "base_failed"]) == base_measures(t), t
        assert not (got[i].kept and got[i].base_failed)
    assert got[0].kept
    none = quality.judge(docs, labels.limit(0)).collect()
    assert all(r.kept != r.base_failed for r in none)
    assert quality.judge(docs.limit(0), labels).count() == 0


def brute_scores(rows, good):
    """Scores of (id, text) rows by plain counting of the hashed words and word pairs."""
    import xxhash

    signed = lambda v: v - (1 << 64) if v >> 63 else v
    of_long = lambda v, seed: xxhash.xxh64_intdigest((v & (1 << 64) - 1).to_bytes(8, "little"), seed)

    def grams(text):
        h = [xxhash.xxh64_intdigest(w.encode(), 42) for w in WORD.findall(text or "")]
        pairs = [of_long(b, of_long(a, 42)) for a, b in zip(h, h[1:])]
        return [signed(v) % quality.BUCKETS for v in h + pairs]

    raw, trusted = collections.Counter(), collections.Counter()
    for i, t in rows:
        raw.update(grams(t))
        if i in good:
            trusted.update(grams(t))
    n_raw, prior = sum(raw.values()) + quality.BUCKETS, quality.PRIOR * quality.BUCKETS
    n_good = sum(trusted.values()) + prior
    p = [(raw[g] + 1) / n_raw for g in range(quality.BUCKETS)]
    ratio = [math.log((trusted[g] + prior * p[g]) / n_good / p[g]) if trusted else 0.0 for g in range(quality.BUCKETS)]
    out = []
    for _, t in rows:
        g = grams(t)
        out.append(sum(ratio[x] for x in g) / (len(g) + quality.NEUTRAL) if g else 0.0)
    return out


def test_quality_score_brute_force(spark):
    texts = words_corpus() + ["bad # $ words " * 9]
    good = set(range(0, 100, 4))
    labels = spark.createDataFrame([(i, 1, 0) for i in good] + [(1, 0, 0)], "doc_id long, quality int, toxic int")
    docs = frame(spark, texts, extra=True).withColumns({"_h": F.lit("h"), "_row": F.lit("r"), "kept": F.lit("k")})
    judged = quality.judge(docs, labels)
    assert judged.columns == ["doc_id", "text", "_h", "_row", *quality.OUT]
    got = {r.doc_id: r for r in judged.collect()}
    for i, want in enumerate(brute_scores([*enumerate(texts)], good)):
        assert abs(got[i].score - want) < 1e-9 and got[i]._h == "h" and got[i]._row == "r" and got[i].text == texts[i]
        assert got[i].kept == (not base_measures(texts[i])[-1] and want >= quality.THRESHOLD)


# --- language -------------------------------------------------------------------------------------------------------------


def test_language_held_out(spark):
    rng = random.Random(2)
    stems = {"aa": ["kala", "mano", "tiru"], "bb": ["strel", "grund", "blick"], "cc": ["éàç", "ouïe", "tête"]}
    rows = [(i, " ".join(rng.choice(s) + rng.choice(s) for _ in range(20)), k) for i, (k, s) in enumerate(list(stems.items()) * 60)]
    rows += [(1000, None, "aa"), (1001, "12 34 !!", "aa"), (1002, "", None), (1003, "qqqq wwww", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(docs.where(~langid.held_out(F.col("doc_id"))))
    got = {r.doc_id: r for r in langid.identify(docs, model).collect()}
    held = {r.doc_id for r in docs.where(langid.held_out(F.col("doc_id"))).collect()}
    assert all(zlib.crc32(str(i).encode()) % 3 == 1 for i in held)
    assert all(got[i].lang_pred == k for i, t, k in rows if i in held and i < 1000)
    assert {got[i].lang_pred for i in (1000, 1001, 1002)} == {"und"} and got[1003].lang_pred in stems
    assert all(0 <= r.score <= 1 for r in got.values())
    nothing = langid.identify(docs, langid.fit(docs.limit(0)))
    assert {r.lang_pred for r in nothing.collect()} == {"und"}


def test_language_more_than_eight(spark):
    """A filter table holds eight languages; the others are learned as well."""
    rng = random.Random(6)
    vocabulary = [["".join(chr(97 + (7 * k + rng.randrange(9)) % 26) for _ in range(7)) for _ in range(30)] for k in range(19)]
    rows = [(19 * i + k, " ".join(rng.choices(vocabulary[k], k=12 + 19 - k)), f"l{k:02}") for k in range(19) for i in range(6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = langid.identify(docs, langid.fit(docs)).collect()
    want = {i: lang for i, _, lang in rows}
    assert len(got) == len(rows) and all(r.lang_pred == want[r.doc_id] and r.score > 0.5 for r in got)


def test_language_against_exact_sets(spark):
    """The filters' verdicts are those of plain n-gram sets; ties and texts with no known n-gram included."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    rows = [(r.doc_id, r.text, r.lang) for r in docs.collect()]
    model = langid.fit(docs)
    counts = {}
    for _, t, lang in rows:
        if t and lang:
            keys, n = np.unique(langid.grams([t])[0], return_counts=True)
            c = counts.setdefault(lang, collections.Counter())
            for k, v in zip(keys.tolist(), n.tolist()):
                c[k] += v
    total = {lang: sum(v for v in c.values() if v >= langid.LEAST) for lang, c in counts.items()}
    top = collections.defaultdict(float)
    for lang, c in counts.items():
        for k, v in c.items():
            if v >= langid.LEAST:
                top[k] = max(top[k], v / total[lang])
    sets = {lang: {k for k, v in c.items() if v >= langid.LEAST and v / total[lang] >= langid.SHARE * top[k]} for lang, c in sorted(counts.items())}
    same = 0
    got = {r.doc_id: r.lang_pred for r in langid.identify(docs, model).collect()}
    for i, t, _ in rows:
        keys, _, lettered = langid.grams([t or ""])
        found = {lang: sum(k in own for k in keys.tolist()) for lang, own in sets.items()}
        best = max(found.values())
        same += got[i] == "und" if not lettered[0] else best == 0 or found[got[i]] >= 0.98 * best
    assert same == len(rows)
    assert langid.identify(docs.limit(0), model).count() == 0


# --- secrets --------------------------------------------------------------------------------------------------------------


def test_secrets(spark):
    key = hashlib.sha1(b"k").hexdigest()
    model = secrets.train(secrets.findings(spark))
    texts = [f'set token = "{key}" now', "the internationalization of representative organizations", None, "", f'token = "{key}" and again token = "{key}"',
             "see https://example.com/some/long/path/to/page for more", "commit " + key, "THEINTERNATIONALWORDS!! AND!! OTHERS!!",
             'password = "k9Tq27xLm" ok', "db_password='S3cr3t!p4ss#9'", "password: required by all", "the secret: internationalization", "api_key = settings.apiKey"]
    df = frame(spark, texts, extra=True)
    got = {r.doc_id: r for r in secrets.redact(df, model).collect()}
    assert got[0].text == f'set token = "{secrets.MARK}" now' and len(got[4]["_secrets"]) == 2 and key not in got[4].text
    assert got[2].text is None and got[3].text == "" and got[0].n_words == "kept"
    assert got[8].text == f'password = "{secrets.MARK}" ok' and got[9].text == f"db_password='{secrets.MARK}'"
    for i in (1, 5, 7, 10, 11, 12):
        assert got[i].text == texts[i]
    assert secrets.redact(df.limit(0), model).count() == 0
    clash = df.withColumns({"_found": F.lit(1), "_secrets": F.lit("x")})
    assert sorted(r.text or "" for r in secrets.redact(clash, model).collect()) == sorted(r.text or "" for r in got.values())


def test_secrets_held_out(spark):
    """Findings made from other numbers than those that the forest saw: precision and recall."""
    model = secrets.train(secrets.findings(spark))
    scored = secrets.scan(secrets.findings(spark, 3000, first=50_000), model).select("label", (F.size("_secrets") > 0).alias("p"))
    n = {(r.label, r.p): r["count"] for r in scored.groupBy("label", "p").count().collect()}
    hit, wrong, lost = n.get((1.0, True), 0), n.get((0.0, True), 0), n.get((1.0, False), 0)
    assert hit / (hit + wrong) > 0.99 and hit / (hit + lost) > 0.99


def test_secrets_forest_does_not_depend_on_partitions(spark):
    docs = frame(spark, words_corpus(n=40))
    forests = [secrets.fit(docs.repartition(k)).forest.toDebugString.split("\n", 1)[1] for k in (2, 7)]
    assert forests[0] == forests[1]
    assert "If" in secrets.fit(docs.limit(0)).forest.toDebugString


# --- near copies ------------------------------------------------------------------------------------------------------------


def brute_components(texts):
    fold = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for t in texts:
        w = WORD.findall((t or "").translate(fold))
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else []))
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            n = len(sets[a] & sets[b])
            if n and 100 * n >= 80 * (len(sets[a]) + len(sets[b]) - n):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return [(len(s), root(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("chunk,askers,hot", [(96, 256, 4096), (6, 2, 5)])
def test_jaccard_components(spark, monkeypatch, chunk, askers, hot):
    """With small chunks, few askers in a task and tokens that are hot from five classes on, too."""
    monkeypatch.setattr(jaccard, "CHUNK", chunk)
    monkeypatch.setattr(jaccard, "ASKERS", askers)
    monkeypatch.setattr(jaccard, "HOT", hot)
    rng = random.Random(8)
    voc = [f"w{i}" for i in range(900)]
    base = [rng.choice(voc) for _ in range(90)]

    def edited(words, k):
        words = list(words)
        for _ in range(k):
            words[rng.randrange(len(words))] = rng.choice(voc)
        return words

    docs, drift = [], base
    docs += [edited(base, rng.randint(0, 4)) for _ in range(60)]
    for _ in range(60):
        drift = edited(drift, 1)
        docs.append(drift)
    hot = [rng.choice(voc) for _ in range(50)]
    docs += [hot + [rng.choice(voc) for _ in range(rng.randint(3, 30))] for _ in range(60)]
    texts = [" ".join(d) for d in docs] + ["A b C", "a B c", *ODD]
    got = {r.doc_id: r for r in jaccard.join(frame(spark, texts, extra=True)).collect()}
    want = brute_components(texts)
    assert [(got[i].n_shingles, got[i].component_id) for i in range(len(texts))] == want
    kept = jaccard.representatives(frame(spark, texts, extra=True))
    assert sorted(r.doc_id for r in kept.collect()) == sorted({w[1] for w in want}) and kept.columns == ["doc_id", "text", "n_words", "score"]


@pytest.mark.parametrize("orders", [0, jaccard.ORDERS])
def test_jaccard_null_id_bridge(spark, monkeypatch, orders):
    """Texts that only rows without an id hold link documents, found by first tokens or (orders 0) by the matrix alone."""
    if not orders:
        monkeypatch.setattr(jaccard, "first_tokens", lambda keys, off: np.arange(jaccard.ORDERS * (len(off) - 1), dtype=np.int64).reshape(-1, jaccard.ORDERS) + int(keys[:1].sum() >> np.uint64(2)))
    rows = []
    for k in range(40):
        w = [f"t{k}x{i}" for i in range(100)]
        rows += [(2 * k + 1, " ".join(w[15:])), (2 * k + 2, " ".join(w[:-15]))] + [(None, " ".join(w))] * 3
    rows += [(None, " ".join(f"z{i}" for i in range(30))), (None, " ".join(f"z{i}" for i in range(31))), (None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join(docs).collect())
    want = collections.Counter()
    for k in range(40):
        want.update({(2 * k + 1, 81, 2 * k + 1): 1, (2 * k + 2, 81, 2 * k + 1): 1, (None, 96, 2 * k + 1): 3})
    want.update([(None, 26, None), (None, 27, None), (None, 0, None)])
    assert got == want


def test_jaccard_bitmap_bounds_overlap():
    rng = np.random.default_rng(4)
    for _ in range(50):
        a, b = (np.unique(rng.integers(0, 400, rng.integers(1, 300)).astype(np.uint64)) for _ in range(2))
        bits = jaccard.bitmaps(np.concatenate([a, b]), np.array([0, len(a), len(a) + len(b)]))
        apart = int(np.bitwise_count(bits[0] ^ bits[1]).sum())
        assert len(np.intersect1d(a, b)) <= (len(a) + len(b) - apart) // 2


def test_jaccard_empty(spark):
    assert jaccard.join(frame(spark, [])).count() == 0
    assert [(r.n_shingles, r.component_id) for r in jaccard.join(frame(spark, [None])).collect()] == [(0, 0)]


def test_components(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(100, 160)] + [(500, i) for i in range(501, 540)] + [(rng.randint(1000, 1100), rng.randint(1000, 1100)) for _ in range(80)] + [(7, 7)]
    up = {}

    def root(x):
        up.setdefault(x, x)
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {n: root(n) for e in edges if e[0] != e[1] for n in e}


# --- contamination ------------------------------------------------------------------------------------------------------------


def semi_distance(p, t):
    prev = [0] * (len(t) + 1)
    for i, a in enumerate(p):
        cur = [i + 1]
        for j, b in enumerate(t):
            cur.append(min(prev[j] + (a != b), prev[j + 1] + 1, cur[j] + 1))
        prev = cur
    return min(prev)


def test_decontamination(spark):
    rng = random.Random(6)
    letters = "abcdefgh "
    items = ["".join(rng.choice(letters) for _ in range(rng.randint(20, 120))).strip() for _ in range(8)]
    texts = []
    for k in range(60):
        text = "".join(rng.choice(letters) for _ in range(120))
        if k % 2:
            hurt = list(rng.choice(items))
            for _ in range(rng.randint(0, 9)):
                hurt[rng.randrange(len(hurt))] = rng.choice(letters)
            text += " " + "".join(hurt).upper() + "  " + text
        texts.append(text)
    texts += ODD
    bench = spark.createDataFrame([*enumerate(items), (100, None), (101, "  "), (102, items[0])], "item_id long, text string")
    want = set()
    for i, t in enumerate(texts):
        flat = decontaminate.squeeze(t or "")
        for j, item in [*enumerate(items), (102, items[0])]:
            flat_item = decontaminate.squeeze(item)
            d = semi_distance(flat_item, flat)
            if d <= decontaminate.budget(flat_item):
                want.add((i, j, d))
    got = {(r.doc_id, r.item_id, r.distance) for r in decontaminate.matches(frame(spark, texts), bench).collect()}
    assert got == want
    left = decontaminate.remove(frame(spark, texts, extra=True), bench)
    assert sorted(r.doc_id for r in left.collect()) == sorted(set(range(len(texts))) - {w[0] for w in want}) and left.columns == ["doc_id", "text", "n_words", "score"]


# --- repeated passages ------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("window,phrase", [(35, 8), (6, 3)])
def test_substrings(spark, window, phrase):
    texts = words_corpus(n=60, vocabulary=40) + ["For " * 90, "x y " * 40, " ".join(f"u{i}" for i in range(200))]
    tokens = [WORD.findall(t or "") for t in texts]
    seen = collections.Counter(tuple(w[k : k + window]) for w in tokens for k in range(len(w) - window + 1))
    got = {r.doc_id: r for r in substrings.dedup(frame(spark, texts, extra=True), window, phrase).collect()}
    for i, w in enumerate(tokens):
        hit = [False] * len(w)
        for k in range(len(w) - window + 1):
            if seen[tuple(w[k : k + window])] > 1:
                hit[k : k + window] = [True] * window
        kept = [x for x, h in zip(w, hit) if not h]
        assert (got[i].n_words, got[i].n_removed) == (len(w), sum(hit)), i
        assert got[i].kept_sha256 == hashlib.sha256(" ".join(kept).encode()).hexdigest()
    assert substrings.dedup(frame(spark, [])).count() == 0


def test_word_bounds_match_the_pattern():
    texts = [t or "" for t in ODD] + ["a b c\x1cd \x0be\x0cf"]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"])
    for part in batches(batch):
        _, at, starts, ends = part.words_at()
        raw = part.data.tobytes()
        got = [raw[a:b].decode() for a, b in zip(starts, ends)]
        assert got == [w for t in texts for w in WORD.findall(t)] and int(at[-1]) == len(got)


def test_very_long_text(spark):
    """One text of a million and a half bytes beside short ones, through every operator on documents."""
    rng = random.Random(12)
    voc = [f"{c}{i}" for i in range(2000) for c in ("alpha", "beta", "gamma")]
    long = " ".join(rng.choice(voc) for _ in range(170_000))
    texts = [long, long[: len(long) // 2], "short text of a few words only here " * 3, None]
    df = frame(spark, texts)
    words = [WORD.findall(t or "") for t in texts]
    assert {r.doc_id: r.component_id for r in jaccard.join(df).collect()} == {i: i for i in range(4)}
    cut = {r.doc_id: r for r in substrings.dedup(df).collect()}
    half = len(words[1]) if words[1][-1] == words[0][len(words[1]) - 1] else len(words[1]) - 1
    assert (cut[0].n_words, cut[0].n_removed) == (170_000, half) and cut[1].n_removed == half
    labels = spark.createDataFrame([(2, 1, 0)], "doc_id long, quality int, toxic int")
    assert {r.doc_id: r.n_words for r in quality.judge(df, labels).collect()} == {i: len(w) for i, w in enumerate(words)}
    path = tokenids.stash_path(spark, "segments")
    tokenids.write_segments(df, path)
    ends = {r.doc_id: r.n_tokens for r in tokenids.read_index(spark, path).collect()}
    assert {r.doc_id: r.n_tokens + 1 for r in bpe.encode(df, with_ids=False).collect()} == ends
    item = " ".join(words[0][90_000:90_040])
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert sorted((r.doc_id, r.distance) for r in decontaminate.matches(df, bench).collect()) == [(0, 0)]
    assert {r.shard for r in sharding.shard(df, 8, "rows").collect()} == {0, 2, 4, 6}
    assert langid.identify(df, langid.fit(df.withColumn("lang", F.lit("xx")))).where("lang_pred = 'xx'").count() == 3
    assert secrets.scan(df, secrets.train(secrets.findings(spark))).where(F.size("_secrets") > 0).count() == 0


def test_quality_clash_of_cut_hashes(spark, monkeypatch):
    """Where cut hashes meet by chance whole hashes decide: forced here by leaving two bits of each hash."""
    plain = F.ceil
    monkeypatch.setattr(quality.F, "ceil", lambda c: F.lit(62))
    try:
        texts = words_corpus(n=12)
        got = {r.doc_id: r.n_repeat_words for r in quality.measure(frame(spark, texts)).collect()}
    finally:
        monkeypatch.setattr(quality.F, "ceil", plain)
    assert got == {i: base_measures(t)[4] for i, t in enumerate(texts)}
