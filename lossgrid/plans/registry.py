"""Queries of the library and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import queries as exact
from . import checked, relational, studies


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.QUERIES["merge_hv_pass"](spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return exact.QUERIES | relational.QUERIES | checked.QUERIES | studies.QUERIES


def oracle_sql() -> dict[str, str]:
    return exact.SQL | relational.SQL | checked.SQL
