"""Sequences (seq_id, part_id, offset, residues) and statistics (seq_id, feature, value) from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LETTERS = "abcdefghijklmnopqrstuvwxyz"
BASES = "ACGTACGTACGTACGTACGTACGTAC"
#: The symbol of each event type.
EVENT_SYMBOLS = {"click": "C", "view": "V", "purchase": "P", "signup": "S", "error": "E"}


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, or some of its columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def acgt(text: Column) -> Column:
    """Letters a to z of the lowered text, laid cyclically on four bases; all else is dropped."""
    return F.translate(F.regexp_replace(F.lower(text), "[^a-z]", ""), LETTERS, BASES)


def acgtn(text: Column) -> Column:
    """As ``acgt``, but each run of other characters is one N."""
    return F.translate(F.regexp_replace(F.lower(text), "[^a-z]+", "N"), LETTERS + "N", BASES + "N")


def _sequence(df: DataFrame, seq_id: Column, part_id: Column, residues: Column) -> DataFrame:
    return df.select(seq_id.cast("string").alias("seq_id"), part_id.cast("bigint").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), residues.alias("residues"))


def documents(spark: SparkSession, sf_dir: str, encode=acgt) -> DataFrame:
    """Each document a sequence."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text").where(F.col("text").isNotNull())
    return _sequence(dealt(docs), F.col("doc_id"), F.col("doc_id"), encode(F.col("text")))


def dealt(df: DataFrame) -> DataFrame:
    """Rows dealt to all cores where a scan has fewer tasks than there are cores; larger scans aren't shuffled."""
    cores = max(2, df.sparkSession.sparkContext.defaultParallelism)
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def language_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each language and source a sequence of many parts: words never cross documents."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source").where(F.col("text").isNotNull())
    return _sequence(dealt(docs), F.concat_ws("/", "lang", "source"), F.col("doc_id"), acgt(F.col("text")))


def user_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user a sequence of event symbols, in order of time and id."""
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    symbol = F.create_map(*(F.lit(x) for kv in EVENT_SYMBOLS.items() for x in kv))[F.col("event_type")]
    ordered = events.select("user_id", F.struct("ts", "event_id", symbol.alias("s")).alias("e")).groupBy("user_id").agg(F.array_sort(F.collect_list("e")).alias("e"))
    return _sequence(ordered, F.col("user_id"), F.lit(0), F.array_join(F.transform("e", lambda x: x.s), ""))


def event_cohorts(spark: SparkSession, sf_dir: str, cohorts: int = 16) -> DataFrame:
    """All users' events, in cohorts by user_id: a cohort is a sequence, and a user's events are a part of it."""
    own = user_events(spark, sf_dir).withColumn("part_id", F.col("seq_id").cast("bigint"))
    return own.select(F.concat(F.lit("c"), F.pmod("part_id", F.lit(cohorts)).cast("string")).alias("seq_id"), "part_id", "offset", "residues")


def conversation_groups(spark: SparkSession, sf_dir: str, groups: int = 5) -> DataFrame:
    """All turns, in groups by role and conv_id: a sequence for each role and group, a part for each turn. Roles are the gold tree."""
    rows = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text").where(F.col("text").isNotNull() & F.col("role").isNotNull())
    name = F.concat_ws("/", "role", F.pmod("conv_id", F.lit(groups)).cast("string"))
    return _sequence(dealt(rows), name, F.col("conv_id") * 100_000 + F.col("turn"), acgt(F.col("text")))


def benchmark_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = table(spark, sf_dir, "benchmark", "item_id", "text")
    return _sequence(items, F.concat(F.lit("b"), F.col("item_id").cast("string")), F.col("item_id"), acgt(F.col("text")))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "pages", "page_id", "html").where(F.col("html").isNotNull())
    return _sequence(rows, F.col("page_id"), F.col("page_id"), acgt(F.regexp_replace("html", "<[^>]*>", " ")))


def conversations(spark: SparkSession, sf_dir: str, role: str | None = None) -> DataFrame:
    rows = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text").where(F.col("text").isNotNull())
    rows = rows.where(F.col("role") == role) if role else rows
    return _sequence(rows, F.col("conv_id"), F.col("turn"), acgt(F.col("text")))


def embedding_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return rows.select(F.col("vec_id").cast("string").alias("seq_id"), F.posexplode("embedding").alias("feature", "value")).withColumn("value", F.col("value").cast("double"))


def nation_histograms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of segments, priorities, return flags and brands of each nation's customers."""
    nation, customer = table(spark, sf_dir, "nation", "n_nationkey", "n_name"), table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    orders, lines, part = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderpriority"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_returnflag"), table(spark, sf_dir, "part", "p_partkey", "p_brand")
    who = customer.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "c_mktsegment")
    bought = orders.join(who, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "n_name", "o_orderpriority")
    lined = lines.join(bought, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    parts = [(who, "c_mktsegment"), (bought, "o_orderpriority"), (lined, "l_returnflag"), (lined, "p_brand")]
    out = None
    for df, column in parts:
        counted = df.groupBy(F.col("n_name").alias("seq_id"), F.concat(F.lit(column + "="), F.col(column)).alias("feature")).agg(F.count("*").alias("value"))
        out = counted if out is None else out.unionByName(counted)
    return out


def words(text: Column) -> Column:
    """Lowered words of a text: runs of letters."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != "")
