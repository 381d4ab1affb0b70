"""A training-data pipeline over ``documents``: five stages, each one of the corpus operators.

Quality rules drop rejected documents; the n-gram Jaccard join leaves one
document of each group of near copies; decontamination drops documents that hold
a benchmark item; secret scans redact what the forest calls a secret (and set
n_chars anew); BPE turns what is left into token ids.

Stages 1 to 4 return exactly the columns they were given, so extra columns pass
through whatever their names. Nulls, empty texts, repeated rows and empty tables
follow the operators' own rules; texts that are null or too short fail the
quality rules. A row with a null doc_id takes part in every stage; stage 2 keeps
one row of each component, one without an id only where no row there has one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm import bpe, decontaminate, jaccard, quality, secrets
from alignspark.llm.common import stash, table


def _packed(docs: DataFrame) -> DataFrame:
    """Id and text beside the whole row, so that no column of ours can clash with the input's."""
    return docs.select("doc_id", "text", F.struct(*[docs[c] for c in docs.columns]).alias("_row"))


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    judged = quality.judge(_packed(docs), table(spark, sf_dir, "labels"))
    # the row number keeps the optimiser from moving the filter below the measures, which would copy them many times over
    fenced = judged.select("_row", "kept", F.monotonically_increasing_id().alias("_fence"))
    return fenced.where("kept AND _fence >= 0").select("_row.*")


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard.representatives(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove(docs, table(spark, sf_dir, "benchmark"))


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    clean = secrets.redact(_packed(docs), secrets.fit(docs))
    changed = F.size("_secrets") > 0
    fields = []
    for name in docs.columns:
        value = F.col("_row").getField(name)
        if name == "text":
            value = F.col("text")
        elif name == "n_chars":
            value = F.when(changed & value.isNotNull(), F.length("text").cast(docs.schema[name].dataType)).otherwise(value)
        fields.append(value.alias(name))
    return clean.select(*fields)


def bpe_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.encode(docs)


STAGES = [
    ("quality rules", quality_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("benchmark decontamination", decontamination_stage),
    ("secret scans", secret_stage),
    ("BPE encoding and decoding", bpe_stage),
]

#: Hashing, learning and token merges have no counterpart in SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table; every stage's rows are written and read again."""
    docs = table(spark, sf_dir, "documents")
    for number, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number + 1 < len(STAGES):
            docs = stash(docs, "stage")
    return docs
