"""All queries of the engine itself."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from walkrank.plans import methods, relational


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return methods.Q | relational.Q


def oracle_sql() -> dict[str, str]:
    return methods.O | relational.O


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return methods.flagship(spark, sf_dir)
