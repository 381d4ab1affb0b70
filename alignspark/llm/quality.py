"""Quality rules and a hashed n-gram likelihood ratio, in DataFrame functions only.

Two multinomials over hashed words and word pairs are counted: one over all
documents (raw), one over trusted documents (all that are labelled good). A
document's score is the mean over its n-grams of
log(trusted/raw) smoothed towards the raw shares; it is kept when the base rules pass and
the score is at least ``threshold``. The decision depends on the counts and the
text alone.

Null and empty texts have no words and fail the base rules. A very long text is
one row, measured whole. Repeated rows are counted and judged like others; a
score equal to the threshold is kept. Without any trusted document the base rules
decide alone. Empty tables give empty results. All columns are carried by
``judge``; where a name clashes with a measure (``OUT``), the measure replaces it.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import WORD, constants, table

#: Hash buckets of the multinomials; prior n-grams of raw shape a bucket, which keep a small trusted set from
#: condemning what it has not seen; neutral n-grams added to a text's length; lowest score kept.
BUCKETS, PRIOR, NEUTRAL, THRESHOLD = 16384, 8, 16, -0.1
#: Words of 64 ids that are broadcast at most.
WORDS = 1 << 20
SPACE = r"[\x20\x09-\x0D]"
MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
OUT = [*MEASURES, "base_failed", "score", "kept"]


def _words(docs: DataFrame) -> DataFrame:
    """Adds the words' hashes ``_h`` (and the words' total length) to every row."""
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.regexp_extract_all(text, F.lit(WORD), F.lit(0))
    lines = F.filter(F.split(text, "\n", -1), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))
    return (
        docs.withColumns({"_w": words, "_l": lines})
        .withColumns({"_h": F.transform("_w", lambda w: F.xxhash64(w)), "word_chars": F.length(F.array_join("_w", "")).cast("long")})
    )


def _grams() -> str:
    """Buckets of a row's words and word pairs, from ``_h``."""
    return (
        f"concat(transform(_h, x -> CAST(pmod(x, {BUCKETS}) AS INT)), IF(size(_h) < 2, CAST(array() AS ARRAY<INT>), "
        f"transform(slice(_h, 1, greatest(size(_h) - 1, 0)), (x, i) -> CAST(pmod(xxhash64(x, _h[i + 1]), {BUCKETS}) AS INT))))"
    )


def trusted_ids(labels: DataFrame) -> DataFrame:
    """Ids of all documents labelled good."""
    return labels.where("quality = 1 AND doc_id IS NOT NULL").select("doc_id").distinct()


def _marked(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Texts and whether their documents are trusted (``t``, 1 or 0).

    Trusted ids are set bits in words of 64 ids. Up to ``WORDS`` of these, which hold 67 million dense ids, are broadcast and no
    text is shuffled; with more, ids meet ids and the texts are shuffled once. Both mark the same documents.
    """
    block, bit = F.shiftright(F.col("doc_id").cast("long"), 6), F.expr("shiftleft(1L, CAST(CAST(doc_id AS LONG) & 63 AS INT))")
    ids = trusted_ids(labels)
    words = ids.groupBy(block.alias("_block")).agg(F.bit_or(bit).alias("_bits"))
    if words.count() <= WORDS:
        near = docs.select(block.alias("_block"), bit.alias("_bit"), "text").join(F.broadcast(words), "_block", "left")
        return near.select(F.coalesce((F.col("_bits").bitwiseAND(F.col("_bit")) != 0).cast("int"), F.lit(0)).alias("t"), "text")
    # rows without an id meet nothing, and stand under their texts' hashes instead of in one task
    named = F.col("doc_id").isNotNull()
    keyed = docs.select(F.coalesce("doc_id", F.xxhash64("text")).alias("_id"), named.alias("_named"), "text")
    good = ids.select(F.col("doc_id").alias("_id"), F.lit(True).alias("_named"), F.lit(1).alias("_t"))
    return keyed.join(good.hint("merge"), ["_id", "_named"], "left").select(F.coalesce("_t", F.lit(0)).alias("t"), "text")


def ratios(docs: DataFrame, labels: DataFrame) -> list[float]:
    """log(trusted/raw) of each bucket, from counts over all documents."""
    text = F.coalesce(F.col("text"), F.lit(""))
    grams = _marked(docs, labels).select(
        "t", F.transform(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), lambda w: F.xxhash64(w)).alias("_h")
    ).select("t", F.explode(F.expr(_grams())).alias("g"))
    counts = grams.groupBy("g").agg(F.count("*").alias("raw"), F.sum("t").alias("good")).collect()
    raw, good = [0] * BUCKETS, [0] * BUCKETS
    for g, r, t in counts:
        raw[g], good[g] = r, t
    if not sum(good):
        return [0.0] * BUCKETS
    prior = PRIOR * BUCKETS
    n_raw, n_good = sum(raw) + BUCKETS, sum(good) + prior
    shares = [(r + 1) / n_raw for r in raw]
    return [math.log((t + prior * p) / n_good / p) for p, t in zip(shares, good)]


def measure(docs: DataFrame) -> DataFrame:
    """Adds the base measures, the verdict on them and the word hashes ``_h``."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = _words(docs).withColumns({
        "n_words": F.size("_w").cast("long"),
        "n_symbols": F.length(F.regexp_replace(text, r"[^#*$%&|<>]+", "")).cast("long"),
        "n_dup_lines": (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"),
        "_v": F.expr(
            "IF(size(_h) < 5, CAST(array() AS ARRAY<BIGINT>), transform(slice(_h, 1, greatest(size(_h) - 4, 0)),"
            " (x, i) -> xxhash64(x, _h[i + 1], _h[i + 2], _h[i + 3], _h[i + 4])))"
        ),
        "_b": F.ceil(F.log2(F.size("_h") + 2)).cast("int"),
    }).drop("_w", "_l")
    # window hash (high bits) and position (low bits) in one long: equal windows stand together once sorted
    keys = base.withColumn("_k", F.expr(
        "sort_array(transform(_v, (x, i) -> shiftleft(shiftright(x, _b), _b) | CAST(i AS BIGINT)))"
    ))
    same = "shiftright(k, _b) = shiftright(_k[j {0} 1], _b)"
    low = "CAST(k & (shiftleft(1L, _b) - 1) AS INT)"
    marked = keys.withColumns({
        "_clash": F.expr(f"exists(transform(_k, (k, j) -> j > 0 AND shiftright(k, _b) = shiftright(_k[greatest(j - 1, 0)], _b)"
                         f" AND _v[{low}] != _v[CAST(_k[greatest(j - 1, 0)] & (shiftleft(1L, _b) - 1) AS INT)]), x -> x)"),
        "_p": F.expr(f"sort_array(transform(filter(_k, (k, j) -> IF(j > 0, {same.format('-').replace('_k[j - 1]', '_k[greatest(j - 1, 0)]')}, false)"
                     f" OR IF(j + 1 < size(_k), {same.format('+').replace('_k[j + 1]', '_k[least(j + 1, size(_k) - 1)]')}, false)), k -> {low}))"),
    })
    # cut hashes that meet by chance, as they do in texts of some million words: whole hashes with their places, sorted
    whole = (
        "flatten(transform(array(sort_array(transform(_v, (x, i) -> named_struct('x', x, 'i', i)))), s -> sort_array(transform(filter(s, (k, j) ->"
        " (j > 0 AND s[greatest(j - 1, 0)].x = k.x) OR (j + 1 < size(s) AND s[least(j + 1, size(s) - 1)].x = k.x)), k -> k.i))))"
    )
    marked = marked.withColumn("_p", F.expr(f"IF(_clash, {whole}, _p)"))
    covered = "aggregate(transform(_p, (p, i) -> IF(i + 1 < size(_p), least(5, _p[least(i + 1, size(_p) - 1)] - p), 5)), 0L, (a, x) -> a + x)"
    return marked.withColumn("n_repeat_words", F.expr(covered)).withColumn(
        "base_failed", F.expr("n_words < 10 OR 100 * n_repeat_words > 20 * n_words")
    )


def judge(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """All columns of ``docs`` with the measures, base_failed, score and kept."""
    model = ratios(docs, labels)
    ratio = constants(model)
    # the whole row beside its text, so that no column of ours can clash with the input's
    packed = docs.select("text", F.struct(*[docs[c] for c in docs.columns]).alias("_row"))
    total = F.aggregate("_g", F.lit(0.0), lambda a, g: a + F.get(ratio, g))
    scored = measure(packed).withColumn("_g", F.expr(_grams())).withColumn("score", F.when(F.size("_g") == 0, 0.0).otherwise(total / (F.size("_g") + NEUTRAL)))
    carried = [F.col("_row").getField(c).alias(c) for c in docs.columns if c not in OUT]
    return scored.withColumn("kept", F.expr(f"NOT base_failed AND score >= {threshold}D")).select(*carried, *OUT)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document judged."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return judge(docs, table(spark, sf_dir, "labels")).select("doc_id", *MEASURES, "base_failed", "kept", F.round("score", 6).alias("score"))
