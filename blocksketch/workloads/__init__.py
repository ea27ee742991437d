"""The registered workloads and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import algebra, optimisation, products, streams


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return products.QUERIES | algebra.QUERIES | optimisation.QUERIES | streams.QUERIES


def oracle_sql() -> dict[str, str]:
    return products.ORACLES | algebra.ORACLES | optimisation.ORACLES | streams.ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return products.flagship(spark, sf_dir)
