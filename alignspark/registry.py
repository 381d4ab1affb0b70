"""Queries of the alignment engine and their SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from alignspark import queries as own
from alignspark.operators.relational import OPS


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tuples aligned by the look-ahead composer, with values."""
    return own.QUERIES["expectation_ev4"][0](spark, sf_dir)


def _generic(f) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: f(lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, (f, _) in own.QUERIES.items()} | {name: _generic(f) for name, (f, _) in OPS.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for table in (own.QUERIES, OPS) for name, (_, sql) in table.items() if sql}
