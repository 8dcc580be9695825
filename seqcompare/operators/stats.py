"""Partial statistics of parts and their combination: rows of (seq_id, feature, value)."""

from __future__ import annotations

from abc import ABC, abstractmethod
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.formats import chunk
from . import windows

STATISTICS: dict[str, type] = {}
COMBINERS: dict[str, Callable[[Column], Column]] = {"sum": F.sum, "max": F.max, "min": F.min}


def register_statistic(name: str):
    """Register a statistic for configurations: its class takes its options by name."""

    def put(kind: type) -> type:
        STATISTICS[name] = kind
        return kind

    return put


def register_combiner(name: str, combine: Callable[[Column], Column]) -> None:
    COMBINERS[name] = combine


class Statistic(ABC):
    """``extract`` gives partial rows of (seq_id, feature, value) without a shuffle."""

    @abstractmethod
    def extract(self, seq: DataFrame) -> DataFrame: ...


def _windows(seq: DataFrame, span: int, word: Callable[[Column, Column], Column], size: int) -> DataFrame:
    """One row for each start of a span within a part; shorter parts have none (``sequence`` would count down)."""
    parts = chunk(seq, size, span - 1).where(F.length("residues") >= span)
    starts = F.sequence(F.lit(1), F.length("residues") - span + 1)
    return parts.select("seq_id", "part_id", "offset", F.explode_outer(F.transform(starts, lambda i: word(F.col("residues"), i))).alias("feature"))


@register_statistic("kmer")
class KmerCount(Statistic):
    """Words of k symbols; ``canonical`` takes a word or its reverse complement, whichever is less.

    Windows are coded by numpy on Arrow batches and counted there, so that what is aggregated is already small. ``jvm``
    makes them as rows by SQL functions instead, one for each window (five times the time for words of four bases).
    """

    def __init__(self, k: int, canonical: bool = False, without: str | None = None, part: int = 256, jvm: bool = False):
        self.k, self.canonical, self.without, self.part, self.jvm = k, canonical, without, part, jvm

    def extract(self, seq: DataFrame) -> DataFrame:
        if self.jvm:
            return self._rows(seq)
        k, both, without = self.k, self.canonical, self.without

        def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                yield from windows.counted(b.column("seq_id"), b.column("residues"), k, both, without)

        return seq.select("seq_id", "residues").mapInArrow(step, "seq_id string, feature string, value bigint")

    def _rows(self, seq: DataFrame) -> DataFrame:
        rows = _windows(seq, self.k, lambda r, i: F.substring(r, i, F.lit(self.k)), self.part).select("seq_id", "feature")
        if self.without:
            rows = rows.where(~F.contains("feature", F.lit(self.without)))
        if self.canonical:
            rows = rows.withColumn("feature", canonical(F.col("feature")))
        return rows.withColumn("value", F.lit(1).cast("bigint"))


def canonical(word: Column) -> Column:
    return F.least(word, F.reverse(F.translate(word, "ACGT", "TGCA")))


def packed(word: Column) -> Column:
    """A word of up to 31 bases as a number in base 4."""
    return F.conv(F.translate(word, "ACGT", "0123"), 4, 10).cast("bigint")


@register_statistic("composition")
class Composition(KmerCount):
    def __init__(self, **options):
        super().__init__(1, **options)


@register_statistic("spaced")
class SpacedWord(Statistic):
    """Symbols at the places where the pattern has 1; with ``payload``, also place and the symbols at 0."""

    def __init__(self, pattern: str, part: int = 256):
        self.pattern, self.part = pattern, part

    def _at(self, mark: str) -> list[int]:
        return [i for i, c in enumerate(self.pattern) if c == mark]

    def extract(self, seq: DataFrame) -> DataFrame:
        pick = lambda r, i: F.concat(*(F.substring(r, i + o, F.lit(1)) for o in self._at("1")))
        return _windows(seq, len(self.pattern), pick, self.part).select("seq_id", "feature", F.lit(1).cast("bigint").alias("value"))

    def occurrences(self, seq: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
        """(keys, seq_id, part_id, place, word, free): every spaced word with its free symbols."""
        span = len(self.pattern)
        parts = chunk(seq, self.part, span - 1).where(F.length("residues") >= span)
        each = parts.select(*keys, "seq_id", "part_id", "offset", "residues", F.explode_outer(F.sequence(F.lit(1), F.length("residues") - span + 1)).alias("i"))
        pick = lambda mark: F.concat(*(F.substring("residues", F.col("i") + o, F.lit(1)) for o in self._at(mark)))
        return each.select(*keys, "seq_id", "part_id", (F.col("offset") + F.col("i") - 1).alias("place"), pick("1").alias("word"), pick("0").alias("free"))


@register_statistic("shingle")
class TokenShingle(Statistic):
    """k consecutive words; takes rows of (seq_id, words)."""

    def __init__(self, k: int):
        self.k = k

    def extract(self, seq: DataFrame) -> DataFrame:
        long = seq.where(F.size("words") >= self.k)
        starts = F.sequence(F.lit(1), F.size("words") - self.k + 1)
        return long.select("seq_id", F.explode_outer(F.transform(starts, lambda i: F.array_join(F.slice("words", i, self.k), " "))).alias("feature"), F.lit(1).cast("bigint").alias("value"))


@register_statistic("histogram")
class ColumnHistogram(Statistic):
    """A column's values as features of a key, counted or weighted."""

    def __init__(self, key: str, feature: str, weight: str | None = None):
        self.key, self.feature, self.weight = key, feature, weight

    def extract(self, df: DataFrame) -> DataFrame:
        value = F.col(self.weight) if self.weight else F.lit(1).cast("bigint")
        return df.select(F.col(self.key).cast("string").alias("seq_id"), F.col(self.feature).alias("feature"), value.alias("value"))


def combine(partial: DataFrame, how: str = "sum", keys: tuple[str, ...] = ()) -> DataFrame:
    """One row for each sequence and feature; counted in each task before the shuffle. ``keys`` go along (a replicate)."""
    return partial.groupBy(*keys, "seq_id", "feature").agg(COMBINERS[how](F.col("value")).alias("value"))


def counts(seq: DataFrame, k: int, **options) -> DataFrame:
    return combine(KmerCount(k, **options).extract(seq))


def keyed(df: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """Sequences with their keys in their name, for statistics that know names only."""
    return df.withColumn("seq_id", F.concat_ws("\x01", *(F.col(k).cast("string") for k in keys), "seq_id")) if keys else df


def unkeyed(df: DataFrame, keys: tuple[str, ...], like: DataFrame, name: str = "seq_id") -> DataFrame:
    """The keys of a name as columns again, of the types they have in ``like``."""
    kinds, parts = dict(like.dtypes), F.split(name, "\x01")
    rest = [c for c in df.columns if c != name]
    return df.select(*(parts[n].cast(kinds[k]).alias(k) for n, k in enumerate(keys)), parts[len(keys)].alias(name), *rest) if keys else df


def keyed_counts(seq: DataFrame, k: int, keys: tuple[str, ...] = (), **options) -> DataFrame:
    """(keys, seq_id, feature, value): word counts within each key."""
    return unkeyed(combine(KmerCount(k, **options).extract(keyed(seq, keys))), keys, seq)


# Filters: on features before the combination, on values after it.


def by_feature(stat: DataFrame, condition: Column | str) -> DataFrame:
    return stat.where(condition)


def no_symbol(stat: DataFrame, symbol: str = "N") -> DataFrame:
    return stat.where(~F.contains("feature", F.lit(symbol)))


def alphabet(stat: DataFrame, symbols: str) -> DataFrame:
    return stat.where(F.col("feature").rlike(f"^[{symbols}]+$"))


def only_in(stat: DataFrame, allowed: DataFrame) -> DataFrame:
    return stat.join(allowed.select("feature").distinct(), "feature", "left_semi").select(stat.columns)


def not_in(stat: DataFrame, stopped: DataFrame) -> DataFrame:
    return stat.join(stopped.select("feature").distinct(), "feature", "left_anti").select(stat.columns)


def by_value(stat: DataFrame, condition: Column | str) -> DataFrame:
    return stat.where(condition)


def min_count(stat: DataFrame, least: int) -> DataFrame:
    return stat.where(F.col("value") >= least)


def doc_freq(stat: DataFrame, least: int = 1, most: int | None = None) -> DataFrame:
    """Features of at least ``least`` and at most ``most`` sequences."""
    kept = stat.groupBy("feature").agg(F.count("*").alias("df")).where(F.col("df") >= least)
    kept = kept.where(F.col("df") <= most) if most is not None else kept
    return stat.join(kept.select("feature"), "feature", "left_semi").select(stat.columns)


# Totals of each sequence, and values on one scale.


def marginals(stat: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(seq_id, total, distinct, sumsq, sumsqrt, top): a row for each sequence."""
    v = F.col("value")
    return stat.groupBy(*keys, "seq_id").agg(F.sum(v).alias("total"), F.count("*").alias("distinct"), F.sum(v * v).alias("sumsq"), F.sum(F.sqrt(v)).alias("sumsqrt"), F.max(v).alias("top"))


def normalise(stat: DataFrame, how: str = "frequency", dictionary: int | None = None) -> DataFrame:
    """Values by sequence: none, frequency, l2, zscore (over all ``dictionary`` words), minmax (over present ones), log1p, binary."""
    w, v = Window.partitionBy("seq_id"), F.col("value").cast("double")
    if how == "zscore":
        if not dictionary:
            raise ValueError("zscore is over a dictionary: give its size")
        mean = F.sum(v).over(w) / dictionary
        new = (v - mean) / F.sqrt(F.sum(v * v).over(w) / dictionary - mean * mean)
    elif how == "minmax":
        low, high = F.min(v).over(w), F.max(v).over(w)
        new = F.when(high > low, (v - low) / (high - low)).otherwise(F.lit(1.0))
    else:
        new = {"none": v, "frequency": v / F.sum(v).over(w), "l2": v / F.sqrt(F.sum(v * v).over(w)), "log1p": F.log1p(v), "binary": F.lit(1.0)}[how]
    return stat.select("seq_id", "feature", new.alias("value"))


def class_histogram(stat: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(seq_id, class, value, n_words): words of equal composition and count together; class is the word's sorted symbols."""
    kind = F.array_join(F.array_sort(F.split("feature", "")), "")
    return stat.select(*keys, "seq_id", kind.alias("class"), "value").groupBy(*keys, "seq_id", "class", "value").agg(F.count("*").alias("n_words"))
