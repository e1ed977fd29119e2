"""Named queries and, where SQL can express them, their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .sources.catalog import longs

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    """Register a function of (spark, sf_dir); integer columns leave as BIGINT."""

    def add(make: Query) -> Query:
        QUERIES[name] = lambda spark, sf_dir: longs(make(spark, sf_dir))
        if sql:
            ORACLES[name] = sql
        return make

    return add
