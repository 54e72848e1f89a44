"""The queries of the library by key, each with its SQL twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, key: str | None = None):
    def add(f):
        name = key or f.__name__
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add
