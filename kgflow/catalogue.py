"""All queries of the engine with their reference SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from kgflow.workloads import assembled, common, judged, lifecycle, operators, star, surface

__all__ = ["assembled", "flagship", "judged", "oracle_sql", "operators", "queries", "star", "surface"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The incremental loop over three windows, measured."""
    return lifecycle.m_delta_precision(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(common.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(common.ORACLES)
