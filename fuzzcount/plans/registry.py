"""All queries of the library's own operators and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fuzzcount.plans import core_queries, relational


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many individuals the panel's released filters hold, by sampled decoys."""
    return core_queries.private_count_b(spark, sf_dir)


def _all() -> dict[str, tuple]:
    return core_queries.FOUND | relational.FOUND


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: query for name, (query, _) in _all().items()}


def oracles() -> dict[str, str]:
    return {name: statement for name, (_, statement) in _all().items() if statement}
