"""All queries of the engine and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from stagefilter.queries import families, method, operators


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return method.staged_end_to_end(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return method.Q | families.Q | operators.Q


def oracle_sql() -> dict[str, str]:
    return method.SQL | families.SQL | operators.SQL
