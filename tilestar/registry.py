"""All queries of the library, by name, and the SQL that gives the same rows where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tilestar import surround, workloads  # noqa: F401  surround adds its queries to those of workloads


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.flagship(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(workloads.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(workloads.ORACLES)
