"""The pipeline's stages: columns, decisions that take effect, the whole run at the smallest scale and against brute force."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F

corpus_pipeline = pytest.importorskip("corpus_pipeline")
SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    docs = docs.withColumns({"kept": F.lit("x"), "row": F.lit(3), "score": F.lit(None).cast("string")})
    before = None
    for number, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, SF)
        rows = out.toPandas()
        if number < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns, name
            assert set(rows.kept) == {"x"}
            if before is not None:
                assert set(rows.doc_id) <= before
        else:
            assert set(rows.doc_id) == before and (rows.ids.map(len) == rows.n_tokens).all()
        before = set(rows.doc_id)
        docs = spark.createDataFrame(rows, out.schema)


def test_empty_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0


def test_one_row_of_each_component(spark):
    """Rows without an id, repeated rows and two texts under one id: one row stays of each component, and all without tokens."""
    prose = {k: " ".join(f"{k}{i}" for i in range(60)) for k in "abcde"}
    rows = [(None, prose["a"], "lone"), (1, prose["b"], "once"), (1, prose["b"], "once"), (2, prose["c"], "c"), (2, prose["c"] + " end", "c"), (2, prose["d"], "d")]
    rows += [(None, prose["d"] + " end", "d"), (None, prose["e"], "e"), (None, prose["e"], "e"), (None, prose["e"] + " end", "e"), (None, None, "bare"), (3, "", "bare"), (3, "", "bare")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, kept_id string").repartition(3)
    out = corpus_pipeline.near_duplicate_stage(spark, docs, SF)
    assert out.columns == docs.columns
    got = [tuple(r) for r in out.collect()]
    assert sorted(r[2] for r in got) == ["bare"] * 3 + ["c", "d", "e", "lone", "once"]
    assert (2, prose["d"], "d") in got and (None, prose["a"], "lone") in got


def test_run_against_brute_force(spark, tmp_path):
    """The whole run on a small corpus: each stage's verdict by plain counting, token ids by the library."""
    from tokenizers import Tokenizer

    from alignspark.llm import decontaminate, quality, secrets
    from alignspark.llm.vocabulary import vocabulary_path
    from tests.llm.test_corpus import base_measures, brute_components, brute_scores, semi_distance

    rng = random.Random(21)
    voc = ["the", "and", "river", "stone", "of", "light", "walks", "under", "bridge", "slow", "green", "hill", "was", "small", "boat", "over", "wind", "from", "old", "door"]
    prose = lambda n: " ".join(rng.choice(voc) for _ in range(n))
    items = [prose(14) + f" quiz {k}" for k in range(3)]
    keys = [hashlib.sha1(bytes([k])).hexdigest() for k in range(4)]
    texts = [prose(rng.randint(40, 90)) for _ in range(30)]
    texts += [texts[0], texts[1] + " end", texts[2]] + [prose(20) + " " + item + " " + prose(20) for item in items]
    texts += [f'{prose(25)} token = "{key}" {prose(25)}' for key in keys] + ["too short", None, "a b c d e " * 9, "#$% junk ** " * 30]
    rows = [*enumerate(texts)]
    good = {i for i in range(0, 30, 3)}
    n = lambda t: None if t is None else len(t)
    spark.createDataFrame([(i, t, "en", "web", n(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in good], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([*enumerate(items)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    scores = brute_scores(rows, good)
    left = [(i, t) for i, t in rows if not base_measures(t)[-1] and scores[i] >= quality.THRESHOLD]
    root = brute_components([t for _, t in left])
    left = [left[k] for k in range(len(left)) if root[k][1] == k]
    flat = [decontaminate.squeeze(x) for x in items]
    left = [(i, t) for i, t in left if all(semi_distance(x, decontaminate.squeeze(t)) > decontaminate.budget(x) for x in flat)]
    for key in keys:
        left = [(i, t.replace(key, secrets.MARK)) for i, t in left]
    library = Tokenizer.from_file(vocabulary_path())
    want = {i: e.ids for (i, _), e in zip(left, library.encode_batch([t for _, t in left], add_special_tokens=False))}
    got = {r.doc_id: list(r.ids) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == want and len(want) > 20
