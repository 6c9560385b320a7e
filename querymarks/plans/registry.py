"""Queries of the grading engine, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators import experiments, relational


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return experiments.graded_marks(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return experiments.queries() | relational.queries()


def oracle_sql() -> dict[str, str]:
    return experiments.oracle_sql() | relational.oracle_sql()
