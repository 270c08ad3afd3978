"""All queries of the library with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphweld.workloads import kg_queries, more_queries  # noqa: F401


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(kg_queries.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(kg_queries.ORACLE)
