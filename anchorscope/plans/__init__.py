"""Registered plans: queries over the given tables, their SQL twins, and the experiments."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
#: Called when a query begins: what it may not take over from the queries before it.
BEFORE: list[Callable[[], None]] = []


def query(sql: str | None = None, name: str | None = None):
    """Registers a function (spark, sf_dir) -> DataFrame with its DuckDB twin."""

    def put(f):
        @wraps(f)
        def run(spark, d):
            for begin in BEFORE:
                begin()
            return f(spark, d)

        QUERIES[name or f.__name__] = run
        if sql is not None:
            ORACLES[name or f.__name__] = sql
        return f

    return put
