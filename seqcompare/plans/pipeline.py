"""A whole run from a configuration: sequences, a statistic, filters, normalisation, functions, and where the matrix goes."""

from __future__ import annotations

import json
import sys
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.library import get
from ..operators import stats
from ..sources import carriers, formats
from . import matrix


@dataclass
class PipelineConfig:
    """Every stage may be left out but the statistic and the functions."""

    source: dict
    statistic: dict
    functions: list = field(default_factory=lambda: ["d2"])
    feature_filters: list = field(default_factory=list)
    value_filters: list = field(default_factory=list)
    combiner: str = "sum"
    normalise: dict | None = None
    strategy: str = "auto"
    output: dict | None = None

    @classmethod
    def load(cls, text: str) -> PipelineConfig:
        return cls(**json.loads(text))


CARRIERS = {
    "documents": carriers.documents, "language_sources": carriers.language_sources, "user_events": carriers.user_events, "benchmark_items": carriers.benchmark_items,
    "pages": carriers.pages, "conversations": carriers.conversations,
}


def sequences(spark: SparkSession, source: dict) -> DataFrame:
    source = dict(source)
    kind = source.pop("kind")
    if kind in ("fasta", "fastq"):
        return getattr(formats, kind)(spark, source["path"])
    return CARRIERS[kind](spark, source.pop("dir"), **source)


def statistic(spark: SparkSession, config: PipelineConfig) -> DataFrame:
    options = dict(config.statistic)
    made = stats.STATISTICS[options.pop("kind")](**options)
    rows = made.extract(sequences(spark, config.source))
    for condition in config.feature_filters:
        rows = stats.by_feature(rows, condition)
    rows = stats.combine(rows, config.combiner)
    for condition in config.value_filters:
        rows = stats.by_value(rows, condition)
    return stats.normalise(rows, **config.normalise) if config.normalise else rows


def run(spark: SparkSession, config: PipelineConfig) -> DataFrame:
    functions = [get(**f) if isinstance(f, dict) else get(f) for f in config.functions]
    out = matrix.compute(statistic(spark, config), functions, config.strategy, k=config.statistic.get("k"))
    if config.output:
        out.write.mode(config.output.get("mode", "errorifexists")).partitionBy("fn").format(config.output.get("format", "parquet")).save(config.output["path"])
    return out


def main(args: list[str]) -> None:
    spark = SparkSession.builder.getOrCreate()
    with open(args[0]) as f:
        out = run(spark, PipelineConfig.load(f.read()))
    if "--show" in args:
        out.orderBy(F.col("fn"), "i", "j").show(50, False)


if __name__ == "__main__":
    main(sys.argv[1:])
