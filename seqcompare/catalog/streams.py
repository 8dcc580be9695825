"""Queries of streams, run over all files at hand and compared with batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import stats
from ..sources import carriers
from ..streaming import counts as streaming
from .base import SYMBOL, c4, query, stat

_DAY = "CAST(date_trunc('day', ts) AS TIMESTAMP)"


@query("stream_tumbling", f'SELECT {_DAY} AS "start", {SYMBOL} AS symbol, count(*) AS n FROM events GROUP BY ALL')
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = streaming.collected(streaming.windowed(streaming.events(spark, sf_dir)), "stream_tumbling")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "symbol", "n")


@query("stream_sliding", f"WITH w AS (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s, {SYMBOL} AS symbol FROM events) SELECT CAST(s AS TIMESTAMP) AS \"start\", symbol, count(*) AS n FROM w GROUP BY ALL")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = streaming.collected(streaming.windowed(streaming.events(spark, sf_dir), "sliding"), "stream_sliding")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "symbol", "n")


@query("stream_session", 'WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT CAST(user_id AS VARCHAR) AS "user", CAST(min(ts) AS TIMESTAMP) AS "start", count(*) AS n FROM s GROUP BY user_id, k')
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = streaming.collected(streaming.windowed(streaming.events(spark, sf_dir), "session"), "stream_session")
    return out.select(F.col("symbol").alias("user"), F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_late", f'SELECT {_DAY} AS "start", {SYMBOL} AS symbol, count(*) AS n FROM events WHERE {_DAY} + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events) GROUP BY ALL')
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Append mode: only windows that the watermark has passed."""
    out = streaming.collected(streaming.windowed(streaming.events(spark, sf_dir)), "stream_late", "append")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "symbol", "n")


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streaming.collected(streaming.distinct_events(streaming.events(spark, sf_dir)), "stream_dedup", "append").agg(F.count("*").alias("n"))


@query("stream_kmers", "WITH seq AS (SELECT 'b' || item_id AS seq_id, translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC') AS residues FROM benchmark), " + stat(4) + " SELECT * FROM stat")
def stream_kmers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running counts over a stream of sequence parts equal those of batch."""
    schema = spark.read.parquet(f"{sf_dir}/benchmark.parquet").schema
    raw = spark.readStream.schema(schema).parquet(f"{sf_dir}/benchmark.parquet*")
    parts = raw.select(F.concat(F.lit("b"), F.col("item_id").cast("string")).alias("seq_id"), F.col("item_id").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), carriers.acgt(F.col("text")).alias("residues"))
    return streaming.collected(streaming.kmer_counts(parts, 4), "stream_kmers").select("seq_id", "feature", F.col("value").cast("bigint").alias("value"))


@query("stream_stateful", f"WITH {c4()}, {stat(3)} SELECT seq_id, feature, value FROM stat")
def stream_stateful(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words across batches, by state: the sums of their increments are the counts of batch."""
    out = streaming.collected(streaming.stateful_kmers(streaming.events(spark, sf_dir), 3), "stream_stateful", "append")
    return out.groupBy(F.col("user_id").cast("string").alias("seq_id"), "feature").agg(F.sum("n").alias("value"))


@query("stream_static", "WITH seq AS (SELECT 'b' || item_id AS seq_id, translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC') AS residues FROM benchmark), " + stat(4) + " SELECT a.seq_id, b.seq_id AS ref_id, CAST(sum(a.value * b.value) AS BIGINT) AS value FROM stat a JOIN stat b ON a.feature = b.feature GROUP BY ALL")
def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances of streamed sequences to a fixed reference."""
    reference = stats.counts(carriers.benchmark_items(spark, sf_dir), 4)
    schema = spark.read.parquet(f"{sf_dir}/benchmark.parquet").schema
    raw = spark.readStream.schema(schema).parquet(f"{sf_dir}/benchmark.parquet*")
    parts = raw.select(F.concat(F.lit("b"), F.col("item_id").cast("string")).alias("seq_id"), F.col("item_id").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), carriers.acgt(F.col("text")).alias("residues"))
    return streaming.collected(streaming.score_against(parts, reference, 4), "stream_static").select("seq_id", "ref_id", F.col("value").cast("bigint").alias("value"))


@query("stream_interval", "SELECT a.user_id, a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = streaming.interval_join(streaming.events(spark, sf_dir), streaming.events(spark, sf_dir))
    return streaming.collected(joined, "stream_interval", "append")
