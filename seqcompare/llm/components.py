"""Connected components of a graph of links, by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

ROUNDS = 60


def _star(pairs: DataFrame, small: bool) -> DataFrame:
    """Hook each neighbour (all larger ones, or the smaller ones and the node itself) to the least of the neighbourhood."""
    both = pairs if small else pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    joined = both.join(least, "u")
    if small:
        hooked = joined.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.where("u != m").select("u", F.col("m").alias("v")))
    else:
        hooked = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return hooked.where("u != v").distinct()


def components(links: DataFrame) -> DataFrame:
    """(doc_id, root) for every end of (doc_id, other): root is the least id that links lead to. Self-links are ignored.

    Each round is a table in the shared folder; a round that leaves the set of links as it was is the last.
    """
    pairs = written(links.where("doc_id != other").select(F.greatest("doc_id", "other").alias("u"), F.least("doc_id", "other").alias("v")).distinct(), "stars")
    mark = None
    for _ in range(ROUNDS):
        pairs = written(_star(_star(pairs, small=False), small=True), "stars")
        now = pairs.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("components did not settle")
    return pairs.select(F.col("u").alias("doc_id"), F.col("v").alias("root")).unionByName(pairs.select(F.col("v").alias("doc_id"), F.col("v").alias("root"))).distinct()
