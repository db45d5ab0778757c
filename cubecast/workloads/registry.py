"""Names to queries and oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is there twice")
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def query(name: str, sql: str | None = None):
    def keep(f):
        add(name, f, sql)
        return f

    return keep
