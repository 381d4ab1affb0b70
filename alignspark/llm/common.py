"""Shared plumbing of the corpus operators: tables, shared scratch space, fixed-size id filters."""

from __future__ import annotations

import ctypes
import math
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are runs of anything but the six ASCII white-space characters (fixed by the query contracts).
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, named by spark.checkpoint.dir.

    A session that names none gets a folder of its own only where driver and
    executors are one process; on a cluster that is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    own = tempfile.mkdtemp(prefix="alignspark-")
    spark.sparkContext.setCheckpointDir(own)
    return own


def stash_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def stash(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = stash_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stashed_at = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete stashes that nothing reads any more: what was made of them must have been stashed itself."""
    for df in frames:
        jvm, spark = df.sparkSession._jvm, df.sparkSession
        at = jvm.org.apache.hadoop.fs.Path(df.stashed_at)
        at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def constants(values: list, kind: str = "double") -> Column:
    """A constant array from one string, folded before anything runs: thousands of literals weigh on the driver in every rule of the planner."""
    return F.from_json(F.lit("[" + ",".join(map(repr, values)) + "]"), f"array<{kind}>")


def text_bytes(docs: DataFrame, column: str = "text") -> int:
    """Bytes of all texts: one pass over one column."""
    return int(docs.agg(F.sum(F.octet_length(column))).first()[0] or 0)


def shares(spark: SparkSession, n_bytes: int, each: int) -> int:
    """Into how many hash shares to deal ``n_bytes``, so that one holds about ``each``; the session's shuffle width at least."""
    return max(16, int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(n_bytes / each))


def tidy() -> None:
    """Give memory that a Python worker no longer uses back to the system; workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library: nothing to give back
        pass


class IdFilter:
    """A Bloom filter over ids, eight bits an id up to 32 MB: what is broadcast has a bound whatever the data.

    It only ever lets too much through, so a join behind it stays exact; at sizes
    where it saturates it stops saving work and nothing else changes.
    """

    LEAST, MOST, PROBES = 20, 28, 3

    def __init__(self, words: np.ndarray):
        self.words = words

    @staticmethod
    def bits(n: int) -> int:
        return 1 << min(IdFilter.MOST, max(IdFilter.LEAST, (8 * n).bit_length()))

    @staticmethod
    def positions(col: Column, bits: int) -> Column:
        """The Bloom positions of an id, for use by Python code that holds the words."""
        return F.array(*[F.pmod(F.xxhash64(col, F.lit(seed)), F.lit(bits)) for seed in range(IdFilter.PROBES)])

    @classmethod
    def of(cls, ids: DataFrame, column: str, bits: int) -> IdFilter:
        """Built by an aggregate over 64-bit words: at most bits/64 rows reach the driver."""
        hits = ids.select(F.explode(cls.positions(F.col(column), bits)).alias("p"))
        rows = hits.groupBy((F.col("p") / 64).cast("int").alias("w")).agg(
            F.bit_or(F.expr("shiftleft(1L, CAST(p % 64 AS INT))")).alias("m")
        )
        words = np.zeros(bits // 64, dtype=np.int64)
        got = rows.toArrow()
        words[got["w"].to_numpy()] = got["m"].to_numpy()
        return cls(words)


def passes(words: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """Which rows' positions (rows x probes) are all set in the filter's words."""
    bits = (words[pos >> 6] >> (pos & 63)) & 1
    return bits.all(axis=1)
