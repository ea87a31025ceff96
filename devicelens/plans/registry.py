"""The registered queries, each with the DuckDB text it is compared with where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from devicelens.plans.oracle import oracle

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(key: str, sql: str | None = None) -> Callable[[Query], Query]:
    """Registers a query; the oracle text may name derived relations, which are defined in front of it."""

    def add(f: Query) -> Query:
        QUERIES[key] = f
        if sql:
            ORACLE_SQL[key] = oracle(sql)
        return f

    return add
