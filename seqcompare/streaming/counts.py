"""Statistics of streams: running word counts, event-time symbol histograms, duplicates, and words across batches."""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.fs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceStreamArrowWriter, WriterCommitMessage
from pyspark.sql.types import StructType

from ..operators.stats import KmerCount
from ..sources.carriers import EVENT_SYMBOLS
from ..stages import shared_folder


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files, with an event time that watermarks accept and the type's symbol."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    symbol = F.create_map(*(F.lit(x) for kv in EVENT_SYMBOLS.items() for x in kv))[F.col("event_type")]
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", symbol.alias("symbol"), "value")


def kmer_counts(stream: DataFrame, k: int) -> DataFrame:
    """Running counts of (seq_id, feature) over a stream of sequence parts: sums of partial counts, as in batch."""
    return KmerCount(k).extract(stream).groupBy("seq_id", "feature").agg(F.sum("value").alias("value"))


def windowed(stream: DataFrame, kind: str = "tumbling", width: str = "1 day", slide: str = "12 hours", gap: str = "30 minutes", watermark: str = "10 minutes") -> DataFrame:
    """Symbol histograms of event-time windows; rows later than the watermark are left out."""
    late = stream.withWatermark("ts", watermark)
    if kind == "session":
        out = late.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
        return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.col("user_id").cast("string").alias("symbol"), "n")
    window = F.window("ts", width) if kind == "tumbling" else F.window("ts", width, slide)
    return late.groupBy(window.alias("w"), "symbol").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "symbol", "n")


def distinct_events(stream: DataFrame, watermark: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def stateful_kmers(stream: DataFrame, k: int) -> DataFrame:
    """(user_id, feature, n) increments: words of each user's symbols, those across two batches among them.

    The state of a user is the last k - 1 symbols; a batch's events are in order of time and id.
    """

    def work(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(frames))
        order = np.lexsort((pdf["event_id"].to_numpy(), pdf["ts"].to_numpy()))
        text = (state.get[0] if state.exists else "") + "".join(pdf["symbol"].to_numpy()[order])
        state.update((text[-(k - 1) :] if k > 1 else "",))
        words = Counter(text[i : i + k] for i in range(len(text) - k + 1))
        yield pd.DataFrame({"user_id": key[0], "feature": list(words), "n": np.array(list(words.values()), "int64")})

    return stream.groupBy("user_id").applyInPandasWithState(work, "user_id bigint, feature string, n bigint", "tail string", "append", "NoTimeout")


def score_against(stream: DataFrame, reference: DataFrame, k: int) -> DataFrame:
    """Running inner products of streamed sequences' words with fixed reference statistics."""
    words = KmerCount(k).extract(stream).select("seq_id", "feature", "value")
    met = words.join(F.broadcast(reference.select(F.col("seq_id").alias("ref_id"), "feature", F.col("value").alias("ref_value"))), "feature")
    return met.groupBy("seq_id", "ref_id").agg(F.sum(F.col("value") * F.col("ref_value")).alias("value"))


def interval_join(a: DataFrame, b: DataFrame, within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Pairs of a user's events of two streams, the second at most ``within`` after the first."""
    left = a.withWatermark("ts", watermark).select(F.col("user_id"), F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"))
    right = b.withWatermark("ts", watermark).select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"))
    return left.join(right, F.expr(f"user_id = b_user and b_ts >= a_ts and b_ts <= a_ts + interval {within} and a_id <> b_id")).select("user_id", "a_id", "b_id")


class _Parts(DataSource):
    """A sink whose tasks write Parquet files in a shared folder, one folder for each batch: with ``complete`` output the last is the whole.

    The driver gets the names of files only; the memory sink would hold all rows there.
    """

    @classmethod
    def name(cls) -> str:
        return "seqcompare_parts"

    def streamWriter(self, schema: StructType, overwrite: bool) -> "_PartsWriter":
        return _PartsWriter(self.options["path"])


@dataclass
class _Written(WriterCommitMessage):
    file: str | None


class _PartsWriter(DataSourceStreamArrowWriter):
    def __init__(self, path: str):
        self.path = path

    def write(self, batches: Iterator[pa.RecordBatch]) -> _Written:
        fs, folder = file_system(self.path)
        name, out = f"{folder}/staged/{uuid.uuid4().hex}.parquet", None
        for b in batches:
            if out is None:
                fs.create_dir(f"{folder}/staged", recursive=True)
                out = pq.ParquetWriter(name, b.schema, filesystem=fs)
            out.write_batch(b)
        if out is None:
            return _Written(None)
        out.close()
        return _Written(name)

    def commit(self, messages: list, batchId: int) -> None:
        fs, folder = file_system(self.path)
        own = f"{folder}/batch={batchId}"
        fs.create_dir(own, recursive=True)
        for name in (m.file for m in messages if m is not None and m.file):
            fs.move(name, f"{own}/{name.rsplit('/', 1)[1]}")

    def abort(self, messages: list, batchId: int) -> None:
        fs, _ = file_system(self.path)
        for name in (m.file for m in messages if m is not None and m.file):
            fs.delete_file(name)


def file_system(path: str) -> tuple[pa.fs.FileSystem, str]:
    return pa.fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


def collected(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """What a stream over all files at hand gives, as a table in the shared folder."""
    spark = stream.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    spark.dataSource.register(_Parts)
    query = stream.writeStream.format(_Parts.name()).option("path", path).option("checkpointLocation", f"{path}-state").outputMode(mode).trigger(availableNow=True).start()
    try:
        query.awaitTermination()
    finally:
        query.stop()
    fs, folder = file_system(path)
    made = [f.path for f in fs.get_file_info(pa.fs.FileSelector(folder, allow_not_found=True)) if "/batch=" in f.path]
    batches = sorted(made, key=lambda p: int(p.rsplit("=", 1)[1]))
    if mode == "complete":
        batches = batches[-1:]
    full = [p for p in batches if fs.get_file_info(pa.fs.FileSelector(p))]
    if not full:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(f"{path}/{p.rsplit('/', 1)[1]}" for p in full))
