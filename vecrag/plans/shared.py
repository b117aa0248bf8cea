"""The registry of queries and a shared place for tables that a query writes and reads again."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from vecrag.session import shared_folder

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None):
    """Register a query under its function's name, with DuckDB SQL of the same rows if there is any."""

    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return register


def folder(spark: SparkSession) -> str:
    """A new folder in the one that spark.checkpoint.dir names."""
    return shared_folder(spark)
