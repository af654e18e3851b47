"""Registry of queries and helpers for their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: The key of every registered query's noise: public, for tests only.
KEY = "k0"


def query(name: str, sql: str | None = None):
    """Register a query, with the DuckDB SQL that gives the same rows."""

    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def both(name: str, spark_sql: str, duck_sql: str | None = None) -> None:
    """Register a query that is the same SQL text in both engines, or nearly."""
    from privgrove.sources.io import register

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        register(spark, sf_dir)
        return spark.sql(spark_sql)

    QUERIES[name], SQL[name] = run, duck_sql or spark_sql
