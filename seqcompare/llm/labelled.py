"""Bounded samples of labelled rows, on which classifiers are fitted."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold

#: At most this many labelled documents fit a classifier; those of the smallest id hashes.
MAX_TRAINING_ROWS = 20_000


def sample(labels: DataFrame, column: str, folds: int = 5, held: int = 0, most: int = MAX_TRAINING_ROWS) -> DataFrame:
    """(doc_id, label 0 or 1): at most ``most`` rows outside the held-out fold. Of repeated ids the largest label counts."""
    rows = labels.where(F.col("doc_id").isNotNull() & F.col(column).isNotNull() & (fold("doc_id", folds) != held))
    one = rows.groupBy("doc_id").agg(F.max((F.col(column) > 0).cast("int")).alias("label"))
    return one.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)


def training_rows(docs: DataFrame, labels: DataFrame, column: str, most: int = MAX_TRAINING_ROWS) -> DataFrame:
    """(doc_id, text, label); the joined side has ``most`` rows at most, so it may be broadcast."""
    return docs.select("doc_id", "text").join(F.broadcast(sample(labels, column, most=most)), "doc_id")
