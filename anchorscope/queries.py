"""The registered queries of the library and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import plans
from .plans import compare, experiments, method, relational, stream  # noqa: F401  (they register themselves)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return method.flagship(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(plans.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(plans.ORACLES)
