"""Helpers that several corpus operators share: shared-folder tables, tokens by numpy, row ids."""

from __future__ import annotations

import ctypes
import gc
import pickle
import sys
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import Broadcast, cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space between words: space and the controls 0x09 to 0x0D.
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
WORD_SPLIT = r"[\x20\x09-\x0D]+"

#: Text bytes that one numpy step works on; a longer document is a step of its own.
STEP_BYTES = 512 << 10

_SPACE = np.zeros(256, dtype=bool)
_SPACE[list(SPACES)] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. In local mode, where it may be unset, one below the warehouse."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return found or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_stages"


#: Tables written in the shared folder by this process, in order.
_WRITTEN: list[str] = []


def stage_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: its lineage is cut, and it outlives lost executors."""
    spark = df.sparkSession
    path = stage_path(spark, name)
    give_back()
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def stage_tables() -> list[str]:
    """Tables written so far that are still there."""
    return list(_WRITTEN)


def dropped(spark: SparkSession, tables: list[str]) -> None:
    """Remove tables that nothing reads any more."""
    for path in tables:
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
        _WRITTEN.remove(path)


def sent(spark: SparkSession, thing: object) -> Broadcast:
    """A broadcast of anything, whole: ``got`` opens it in a task. Only for things of a bounded size."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(thing))


def tidy(step):
    """The step, and then what the worker's allocators hold for later goes back: idle workers stay small."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from step(batches)
        finally:
            give_back()

    return run


def give_back() -> None:
    """Memory that allocators hold for later goes back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        ctypes.CDLL(None).malloc_trim(0)


def got(parcel: Broadcast) -> object:
    return pickle.loads(parcel.value)


def lean(spark: SparkSession) -> None:
    """Arrow batches of fewer rows, as rows are whole documents here and a batch is in memory several times over.

    Small lists of many groups are gathered by hash: a task's groups are bounded by its partition, and Spark spills beyond.
    Both are read when a query runs, so that they can't be put back before; other queries give the same results with them.
    """
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1000")
    spark.conf.set("spark.sql.objectHashAggregate.sortBased.fallbackThreshold", "200000")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    lean(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def fold(column: str, modulus: int) -> Column:
    """crc32 of an id as text, modulo ``modulus``: the fold that decides what is held out."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % modulus


def bundled(docs: DataFrame, keep: tuple[str, ...]) -> DataFrame:
    """doc_id, text and the columns of ``keep`` as one, so that their names can't clash with an operator's own."""
    return docs.select("doc_id", "text", *([F.struct(*(F.col(k).alias(f"c{i}") for i, k in enumerate(keep))).alias("_kept")] if keep else []))


def kept_names(own: list[str], keep: tuple[str, ...]) -> dict[str, str]:
    """What kept columns are called in a result: their own name, or ``input_`` before it where the operator's column has it."""
    out: dict[str, str] = {}
    for k in keep:
        name = k
        while name in own or name in out.values() or (name != k and name in keep):
            name = f"input_{name}"
        out[k] = name
    return out


def unbundled(df: DataFrame, keep: tuple[str, ...]) -> DataFrame:
    """The operator's columns, and the kept ones by ``kept_names``."""
    own = [c for c in df.columns if c != "_kept"]
    return df.select(*own, *(F.col(f"_kept.c{i}").alias(name) for i, name in enumerate(kept_names(own, keep).values())))


def packed(df: DataFrame, *keep: str) -> DataFrame:
    """``keep`` and ``z``, the text compressed: a shuffle of whole texts then moves a third of the bytes."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=3)
        for b in batches:
            z = [press.compress((t or "").encode("utf-8", "replace")) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), pa.array(z, pa.binary())], names=[*keep, "z"])

    kinds = {f.name: f.dataType.simpleString() for f in df.schema}
    return df.select(*keep, "text").mapInArrow(tidy(step), ", ".join(f"`{k}` {kinds[k]}" for k in keep) + ", z binary")


def unpacked(z: pa.Array) -> pa.Array:
    press = zstandard.ZstdDecompressor()
    return pa.array([press.decompress(x).decode() if x is not None else "" for x in z.to_pylist()], pa.string())


def steps(batch: pa.RecordBatch, column: str = "text", most: int = STEP_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of a batch with about ``most`` bytes of text each."""
    offsets = text_buffers(batch.column(column))[1]
    start = 0
    while start < len(batch):
        stop = int(np.searchsorted(offsets, offsets[start] + most, "right")) - 1
        stop = min(max(stop, start + 1), len(batch))
        yield start, stop
        start = stop


def text_buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column, and the byte offsets of its rows (null: empty)."""
    if pa.types.is_large_string(texts.type):
        texts = texts.cast(pa.string())
    if texts.null_count:
        texts = texts.fill_null("")
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int32, count=len(texts) + 1 + texts.offset)[texts.offset :].astype(np.int64)
    data = texts.buffers()[2]
    return (np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


class Words:
    """The words of a run of texts: byte bounds, the row of each, and where each row's words start."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        data, offsets = text_buffers(texts)
        base, end = int(offsets[0]), int(offsets[-1])
        n = end - base
        self.rows = len(texts)
        self.offsets = offsets - base
        padded = np.zeros(n + 16, np.uint8)
        padded[:n] = _LOWER[data[base:end]] if lower else data[base:end]
        self.bytes = padded
        inner = ~_SPACE[padded[:n]]
        edge = np.zeros(n + 1, bool)
        edge[self.offsets] = True
        first, last = inner.copy(), inner.copy()
        if n:
            first[1:] &= ~inner[:-1] | edge[1:n]
            last[:-1] &= ~inner[1:] | edge[1:n]
        self.starts, self.ends = np.flatnonzero(first), np.flatnonzero(last) + 1
        self.bounds = np.searchsorted(self.starts, self.offsets)
        self.counts = np.diff(self.bounds)
        self.row = np.repeat(np.arange(self.rows), self.counts)

    def hashes(self, seed: int = 0) -> np.ndarray:
        """A 64-bit hash of each word's bytes."""
        lanes = np.ndarray((len(self.bytes) - 8,), "<u8", self.bytes.data, 0, (1,))
        size = self.ends - self.starts
        h = mixed(size.astype(np.uint64) + np.uint64(seed * 1_000_003 + 1))
        live, k = np.arange(len(size)), 0
        while len(live):
            left = size[live] - k
            lane = lanes[self.starts[live] + k]
            short = left < 8
            lane = np.where(short, lane & ((np.uint64(1) << (np.minimum(left, 7) * 8).astype(np.uint64)) - np.uint64(1)), lane)
            if k == 0:
                h = mixed(h ^ lane)
            else:
                h[live] = mixed(h[live] * _M2 ^ lane)
            k += 8
            live = live[left > 8]
        return h

    def word(self, i: int) -> bytes:
        return self.bytes[self.starts[i] : self.ends[i]].tobytes()


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mix."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each k consecutive hashes; the last k - 1 places have none. Rows are not told apart here."""
    done, size, parts = None, 0, h
    width, left = 1, k
    while left:
        if left & 1:
            if done is None:
                done, size = parts, width
            else:
                n = len(h) - size - width + 1
                done, size = (mixed(done[:n] * _M1 + parts[size : size + n]) if n > 0 else done[:0]), size + width
        left >>= 1
        if left:
            n = len(h) - 2 * width + 1
            parts = mixed(parts[:n] * _M1 + parts[width : width + n]) if n > 0 else parts[:0]
            width *= 2
    return done


def starts_of(words: Words, k: int) -> np.ndarray:
    """Places in the run of words at which k words of one row start."""
    many = np.maximum(words.counts - k + 1, 0)
    total = int(many.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = words.bounds[:-1] - np.concatenate([[0], np.cumsum(many)[:-1]])
    return np.arange(total) + np.repeat(shift, many)


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64)


def batch(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, (pa.Array, pa.ChunkedArray)) else pa.array(c) for c in columns.values()], names=list(columns))


class Tally:
    """Counts of 64-bit keys within a task; ``add`` gives a batch to hand on when it holds ``most`` of them."""

    def __init__(self, most: int = 2_000_000):
        self.most, self.keys, self.counts, self.held, self.next = most, [], [], 0, most

    def add(self, keys: np.ndarray) -> pa.RecordBatch | None:
        if len(keys):
            k, n = np.unique(keys, return_counts=True)
            self.keys.append(k)
            self.counts.append(n)
            self.held += len(k)
        if self.held < self.next:
            return None
        self._merge()
        self.next = self.held + self.most
        return self.flush() if self.held >= self.most else None

    def _merge(self) -> None:
        k = np.concatenate(self.keys)
        order = np.argsort(k)
        k, n = k[order], np.concatenate(self.counts)[order]
        first = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
        self.keys, self.counts, self.held = [k[first]], [np.add.reduceat(n, first)], len(first)

    def flush(self) -> pa.RecordBatch | None:
        if not self.held:
            return None
        self._merge()
        out = batch(key=signed(self.keys[0]), n=self.counts[0].astype(np.int64))
        self.keys, self.counts, self.held, self.next = [], [], 0, self.most
        return out


def tallied(df: DataFrame, keys_of) -> DataFrame:
    """(key, n) over all rows: ``keys_of`` gives the 64-bit keys of some texts. Counted in each task first."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = Tally()
        for b in batches:
            for lo, hi in steps(b):
                if (full := tally.add(keys_of(b.column("text").slice(lo, hi - lo)))) is not None:
                    yield full
        if (rest := tally.flush()) is not None:
            yield rest

    return df.select("text").mapInArrow(tidy(step), "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n"))
