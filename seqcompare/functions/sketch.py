"""Bottom sketches: the smallest hashes of a sequence's words, mergeable over its parts, and the distance they estimate."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import stats, windows
from ..stages import settled

#: Hashes that a task holds of all its sequences before it hands sketches on.
HELD = 4_000_000
#: Sketches of a sequence's parts are merged in so many groups first.
SALTS = 32


def hashed(word: Column, how: str = "xxhash64", seed: int = 42) -> Column:
    """md5 gives the same numbers in SQL elsewhere; xxhash64 is the faster one."""
    if how == "md5":
        return F.conv(F.substring(F.md5(word), 1, 15), 16, 10).cast("bigint")
    return F.xxhash64(F.lit(seed), word)


def _low(lists: Column, size: int) -> Column:
    return F.slice(F.sort_array(F.array_distinct(F.flatten(lists))), 1, size)


def _bottoms(batches: Iterator[pa.RecordBatch], k: int, size: int, canonical: bool, how: str = "mixed") -> Iterator[pa.RecordBatch]:
    """(seq_id, salt, low, n) of a task: each sequence's smallest hashes there, and its windows."""
    low: dict[str, np.ndarray] = {}
    many: dict[str, int] = {}

    def flush() -> pa.RecordBatch:
        names = list(low)
        out = [pa.array(names, pa.string()), pa.array([hash_place(n) for n in names], pa.int32()), pa.array([low[n] for n in names], pa.list_(pa.int64())), pa.array([many[n] for n in names], pa.int64())]
        low.clear()
        many.clear()
        return pa.RecordBatch.from_arrays(out, names=["seq_id", "salt", "low", "n"])

    batch = 0

    def hash_place(name: str) -> int:
        return (batch + len(name)) % SALTS

    def keep(name: str, own: np.ndarray, n: int) -> None:
        old = low.get(name)
        if old is not None and len(old) == size:
            own = own[own < old[-1]]
        low[name] = np.unique(own if old is None else np.concatenate([old, own]))[:size]
        many[name] = many.get(name, 0) + n

    for b in batches:
        batch += 1
        ids = b.column("seq_id").to_pylist()
        data, bounds = windows.symbols(b.column("residues"))
        if how == "md5" and len(data) and data.max() > 127:  # symbols of several bytes
            for name, text in zip(ids, b.column("residues").to_pylist(), strict=True):
                if text and len(text) >= k:
                    keep(name, np.array([int(hashlib.md5(w.encode()).hexdigest()[:15], 16) for w in {text[i : i + k] for i in range(len(text) - k + 1)}], np.int64), len(text) - k + 1)
            continue
        for part, starts, rows in windows.steps(data, bounds, k):
            if not len(starts):
                continue
            h = windows.word_md5(part, starts, k) if how == "md5" else windows.word_hashes(part, k, canonical)[starts]
            cuts = np.flatnonzero(np.append(True, rows[1:] != rows[:-1]))
            for lo, hi in zip(cuts.tolist(), [*cuts[1:].tolist(), len(rows)], strict=True):
                keep(ids[rows[lo]], h[lo:hi], hi - lo)
        if len(low) * size > HELD:
            yield flush()
    if low:
        yield flush()


def sketches(seq: DataFrame, k: int = 21, size: int = 1000, how: str = "mixed", canonical: bool = True, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, seq_id, sketch, n_words): the smallest ``size`` distinct hashes of a sequence's words, and its windows.

    ``mixed`` hashes by numpy: a task keeps the smallest of each of its sequences, so that what is shuffled is bounded by
    tasks times ``size``, and they are merged in two rounds. ``md5`` does the same for words of up to 55 symbols.
    ``xxhash64``, and md5 of canonical or longer words, hash by SQL functions, after the words are made distinct.
    """
    named = stats.keyed(seq, keys)
    if how == "mixed" or how == "md5" and not canonical and k <= 55:
        part = named.select("seq_id", "residues").mapInArrow(lambda batches: _bottoms(batches, k, size, canonical, how), "seq_id string, salt int, low array<bigint>, n bigint")
    else:
        words = stats.KmerCount(k, canonical=canonical).extract(named).groupBy("seq_id", hashed(F.col("feature"), how).alias("h")).agg(F.sum("value").alias("n"))
        salted = words.withColumn("salt", F.pmod("h", F.lit(256)).cast("int"))
        part = salted.groupBy("seq_id", "salt").agg(F.array(F.slice(F.sort_array(F.collect_list("h")), 1, size)).alias("l"), F.sum("n").alias("n")).select("seq_id", "salt", F.flatten("l").alias("low"), "n")
    some = part.groupBy("seq_id", "salt").agg(_low(F.collect_list("low"), size).alias("low"), F.sum("n").alias("n"))
    whole = some.groupBy("seq_id").agg(_low(F.collect_list("low"), size).alias("sketch"), F.sum("n").alias("n_words"))
    return stats.unkeyed(whole, keys, seq)


def union(parts: DataFrame, size: int = 1000) -> DataFrame:
    """Sketches of the same sequence in one: the combiner of sketches (seq_id, sketch, n_words). A task merges its own first."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low: dict[str, np.ndarray] = {}
        many: dict[str, int] = {}

        def flush() -> pa.RecordBatch:
            out = [pa.array(list(low), pa.string()), pa.array(list(low.values()), pa.list_(pa.int64())), pa.array(list(many.values()), pa.int64())]
            low.clear(), many.clear()
            return pa.RecordBatch.from_arrays(out, names=["seq_id", "sketch", "n_words"])

        for b in batches:
            names, where = b.column("seq_id").to_numpy(zero_copy_only=False), b.column("n_words").to_numpy(zero_copy_only=False)
            lists = b.column("sketch")
            for name in dict.fromkeys(names.tolist()):
                mine = np.flatnonzero(names == name)
                own = lists.take(pa.array(mine)).flatten().to_numpy()
                low[name] = np.unique(np.concatenate([low.get(name, own[:0]), own]))[:size]
                many[name] = many.get(name, 0) + int(where[mine].sum())
            if len(low) * size > HELD:
                yield flush()
        if low:
            yield flush()

    some = parts.select("seq_id", F.col("sketch").cast("array<bigint>").alias("sketch"), F.col("n_words").cast("bigint").alias("n_words")).mapInArrow(merge, "seq_id string, sketch array<bigint>, n_words bigint")
    return some.groupBy("seq_id").agg(_low(F.collect_list("sketch"), size).alias("sketch"), F.sum("n_words").alias("n_words"))


def estimated(a: Column, b: Column, size: int) -> tuple[Column, Column]:
    """Shared hashes among the smallest of the union, and how many those are."""
    union = F.slice(F.sort_array(F.array_union(a, b)), 1, size)
    shared = F.size(F.array_intersect(union, F.array_intersect(a, b)))
    return shared, F.size(union)


def distance(jaccard: Column, k: int) -> Column:
    """-ln(2j / (1 + j)) / k, and 1 where nothing is shared."""
    return F.when(jaccard > 0, F.least(-F.log(2 * jaccard / (1 + jaccard)) / k, F.lit(1.0))).otherwise(1.0)


def matrix(sketched: DataFrame, k: int, size: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, i, j, shared, jaccard, value): pairs that share a hash are found by a join on hashes, all others have distance 1."""
    ids = sketched.select(*keys, "seq_id")
    each = sketched.select(*keys, "seq_id", F.explode("sketch").alias("h"))
    pair = [*keys, "i", "j"]
    met = each.withColumnRenamed("seq_id", "i").join(each.withColumnRenamed("seq_id", "j"), [*keys, "h"]).where("i < j").select(*pair).distinct()
    a, b = sketched.select(*keys, F.col("seq_id").alias("i"), F.col("sketch").alias("a")), sketched.select(*keys, F.col("seq_id").alias("j"), F.col("sketch").alias("b"))
    shared, many = estimated(F.col("a"), F.col("b"), size)
    scored = met.join(a, [*keys, "i"]).join(b, [*keys, "j"]).select(*pair, shared.cast("bigint").alias("shared"), (shared / many).alias("jaccard"))
    one, two = ids.withColumnRenamed("seq_id", "i"), ids.withColumnRenamed("seq_id", "j")
    grid = one.join(F.broadcast(two), list(keys)).where("i < j") if keys else one.join(F.broadcast(two), F.col("i") < F.col("j"))
    filled = grid.join(scored, pair, "left").fillna(0, ["shared", "jaccard"])
    return filled.select(*pair, "shared", "jaccard", distance(F.col("jaccard"), k).alias("value"))


#: Bytes of words' marks that a task holds before it hands them on, and ranges of words that are put together apart.
MARKED, SHARES = 1 << 28, 64


def exact(seq: DataFrame, k: int, alphabet: str = "ACGT") -> DataFrame:
    """(i, j, both, jaccard): distinct words that pairs i < j share, and their exact Jaccard index; pairs that share none have no row.

    Words are bits of their number in the alphabet, so what a task hands on is bounded by its sequences times the dictionary,
    and pairs meet as products of matrices, range by range. Windows with other symbols are an error.
    """
    many = len(alphabet) ** k
    if many > 1 << 24:
        raise ValueError("a dictionary of more than 2^24 words is too large to be marked")
    wide = -(-many // (8 * SHARES)) * 8
    coded = np.full(256, -1, np.int64)
    coded[list(alphabet.encode())] = np.arange(len(alphabet))

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, np.ndarray] = {}

        def flush() -> Iterator[pa.RecordBatch]:
            for name, own in seen.items():
                bits = np.packbits(own.reshape(SHARES, wide), axis=1)
                there = np.flatnonzero(bits.any(axis=1))
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(there), pa.string()), pa.array(there.astype(np.int32)), pa.array([zlib.compress(bits[r].tobytes(), 1) for r in there], pa.binary())], names=["seq_id", "share", "bits"])
            seen.clear()

        for b in batches:
            ids = b.column("seq_id").to_pylist()
            data, bounds = windows.symbols(b.column("residues"))
            for part, starts, rows in windows.steps(data, bounds, k):
                if not len(starts):
                    continue
                code = coded[part]
                if code.min() < 0:
                    raise ValueError("a symbol is not in the alphabet")
                word = windows.numbered(code, len(alphabet), k)[starts]
                cuts = np.flatnonzero(np.append(True, rows[1:] != rows[:-1]))
                for lo, hi in zip(cuts.tolist(), [*cuts[1:].tolist(), len(rows)], strict=True):
                    name = ids[rows[lo]]
                    if name not in seen:
                        seen[name] = np.zeros(SHARES * wide, bool)
                    seen[name][word[lo:hi]] = True
                if len(seen) * SHARES * wide > MARKED:
                    yield from flush()
        yield from flush()

    def meet(table: pa.Table) -> pa.Table:
        names, at = np.unique(table.column("seq_id").to_numpy(), return_inverse=True)
        bits = np.zeros((len(names), wide // 8), np.uint8)
        for n, own in zip(at.tolist(), table.column("bits"), strict=True):
            bits[n] |= np.frombuffer(zlib.decompress(own.as_py()), np.uint8)
        marks = np.unpackbits(bits, axis=1).astype(np.float32)  # whole numbers below 2^24 are exact
        both = marks @ marks.T
        i, j = np.nonzero(np.triu(both))
        return pa.table({"i": pa.array(names[i], pa.string()), "j": pa.array(names[j], pa.string()), "both": pa.array(both[i, j].astype(np.int64))})

    marked = seq.select("seq_id", "residues").mapInArrow(mark, "seq_id string, share int, bits binary")
    met = settled(marked.groupBy("share").applyInArrow(meet, "i string, j string, both bigint").groupBy("i", "j").agg(F.sum("both").alias("both")))
    own = met.where("i = j")
    pairs = met.where("i < j").join(own.select("i", F.col("both").alias("a")), "i").join(own.select("j", F.col("both").alias("b")), "j")
    return pairs.select("i", "j", "both", (F.col("both") / (F.col("a") + F.col("b") - F.col("both"))).alias("jaccard"))
