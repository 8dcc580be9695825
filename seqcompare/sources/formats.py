"""Sequence text formats and chunking."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def fasta(spark: SparkSession, path: str) -> DataFrame:
    """Records of a header line and folded residues; the first word of the header is the sequence's name."""
    raw = spark.read.option("lineSep", ">").text(path).where("trim(value) != ''")
    lines = F.split("value", "\r?\n")
    name = F.split(F.element_at(lines, 1), r"\s+")[0]
    residues = F.upper(F.regexp_replace(F.array_join(F.slice(lines, 2, F.size(lines)), ""), r"\s", ""))
    return raw.select(name.alias("seq_id"), F.lit(0).cast("bigint").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), residues.alias("residues"))


def fastq(spark: SparkSession, path: str) -> DataFrame:
    """Four-line records, whole files at a time: for reads in files of a moderate size."""
    whole = spark.read.text(path, wholetext=True)
    lines = F.filter(F.split("value", "\r?\n"), lambda x: x != "")
    count = F.floor(F.size(lines) / 4).cast("int")
    records = F.transform(F.sequence(F.lit(0), F.greatest(count - 1, F.lit(0))), lambda i: F.struct(F.get(lines, i * 4).alias("head"), F.get(lines, i * 4 + 1).alias("residues")))
    each = whole.where(count > 0).select(F.explode(records).alias("r"))
    return each.select(F.split(F.substring("r.head", 2, 1_000_000), r"\s+")[0].alias("seq_id"), F.lit(0).cast("bigint").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), F.upper("r.residues").alias("residues"))


def chunk(seq: DataFrame, size: int = 256, overlap: int = 0) -> DataFrame:
    """Parts of ``size`` starts each, with ``overlap`` symbols of the next part to their right.

    A substring costs as much as its place in the string, so that long sequences are cut before words are taken from them.
    """
    length, others = F.length("residues"), [c for c in seq.columns if c not in ("seq_id", "part_id", "offset", "residues")]
    starts = F.sequence(F.lit(0), F.greatest(length - overlap - 1, F.lit(0)), F.lit(size))
    each = seq.where(length > 0).select(*others, "seq_id", "part_id", "offset", "residues", F.explode_outer(starts).alias("at"))
    return each.select(*others, "seq_id", "part_id", (F.col("offset") + F.col("at")).alias("offset"), F.substring("residues", F.col("at") + 1, F.lit(size + overlap)).alias("residues"))
