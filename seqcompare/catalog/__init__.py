"""The registered queries of the engine and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import comparison, reliability, statistics, streams, surrounding
from .base import ORACLES, QUERIES

__all__ = ["comparison", "entry", "oracle_sql", "queries", "reliability", "statistics", "streams", "surrounding"]


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """D2 of all pairs of documents' words of four bases."""
    return comparison.flagship(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
