"""Queries by name, each with the SQL that must give the same rows (or none, with a reason)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import rounded

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: Why a query has no SQL.
WITHOUT_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, because: str = "") -> Callable[[Query], Query]:
    """Registers a query; its doubles are rounded to six digits."""

    def add(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = lambda spark, sf: rounded(f(spark, sf))
        if sql is None:
            WITHOUT_SQL[name] = because
        else:
            ORACLES[name] = sql
        return f

    return add
