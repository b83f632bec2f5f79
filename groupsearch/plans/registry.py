"""The registered queries and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import oracle, queries as exact, workloads


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.search_threshold(spark, sf_dir)


def queries() -> dict:
    return exact.queries() | workloads.queries()


def oracle_sql() -> dict[str, str]:
    return oracle.sql()
