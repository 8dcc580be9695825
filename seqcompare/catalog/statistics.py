"""Queries of statistics, filters and normalisation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import stats
from ..sources import carriers, formats
from .base import ACGTN, C5, NATION, WORDS, c1, c4, kmers, query, r, rs, shingles, stat


def value_long(df: DataFrame) -> DataFrame:
    return df.select("seq_id", "feature", F.col("value").cast("bigint").alias("value"))


@query("kmer_counts_doc", f"WITH {c1()}, {stat(4)} SELECT * FROM stat")
def kmer_counts_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(carriers.documents(spark, sf_dir), 4))


@query("kmer_counts_canonical", f"WITH {c1()}, {kmers(5)} SELECT seq_id, least(feature, reverse(translate(feature, 'ACGT', 'TGCA'))) AS feature, count(*) AS value FROM km GROUP BY ALL")
def kmer_counts_canonical(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(carriers.documents(spark, sf_dir), 5, canonical=True))


@query("kmer_counts_chunked", f"WITH {c1()}, {stat(4)} SELECT * FROM stat")
def kmer_counts_chunked(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(formats.chunk(carriers.documents(spark, sf_dir), 640, 3), 4, part=64))


@query("kmer_counts_events", f"WITH {c4()}, {stat(3)} SELECT * FROM stat")
def kmer_counts_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(carriers.user_events(spark, sf_dir), 3))


@query("kmer_counts_group", f"WITH {C5}, {stat(4)} SELECT * FROM stat")
def kmer_counts_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(carriers.language_sources(spark, sf_dir), 4))


@query("kmer_packed", f"""WITH {c1()}, {stat(4)} SELECT seq_id, CAST((strpos('ACGT', substr(feature, 1, 1)) - 1) * 64 + (strpos('ACGT', substr(feature, 2, 1)) - 1) * 16 + (strpos('ACGT', substr(feature, 3, 1)) - 1) * 4 + strpos('ACGT', substr(feature, 4, 1)) - 1 AS BIGINT) AS packed, value FROM stat""")
def kmer_packed(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = stats.counts(carriers.documents(spark, sf_dir), 4)
    return counts.select("seq_id", stats.packed(F.col("feature")).alias("packed"), F.col("value").cast("bigint").alias("value"))


@query("kmer_no_n", f"WITH {c1(ACGTN)}, {stat(4)} SELECT * FROM stat WHERE NOT contains(feature, 'N')")
def kmer_no_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.counts(carriers.documents(spark, sf_dir, carriers.acgtn), 4, without="N"))


_BENCH_WORDS = f"bw AS (SELECT DISTINCT unnest({WORDS}) AS feature FROM benchmark)"


def _doc_words(spark: SparkSession, sf_dir: str, k: int = 1) -> DataFrame:
    docs = carriers.dealt(carriers.table(spark, sf_dir, "documents", "doc_id", "text").where("text is not null"))
    seq = docs.select(F.col("doc_id").cast("string").alias("seq_id"), carriers.words(F.col("text")).alias("words"))
    return stats.combine(stats.TokenShingle(k).extract(seq))


def _bench_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return carriers.table(spark, sf_dir, "benchmark", "text").select(F.explode(carriers.words(F.col("text"))).alias("feature")).distinct()


@query("stoplist_anti", f"WITH {shingles(1)}, {_BENCH_WORDS} SELECT * FROM stat WHERE feature NOT IN (SELECT feature FROM bw)")
def stoplist_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.not_in(_doc_words(spark, sf_dir), _bench_words(spark, sf_dir)))


@query("allowlist_semi", f"WITH {shingles(1)}, {_BENCH_WORDS} SELECT * FROM stat WHERE feature IN (SELECT feature FROM bw)")
def allowlist_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.only_in(_doc_words(spark, sf_dir), _bench_words(spark, sf_dir)))


@query("alphabet_filter", f"WITH {c1(ACGTN)}, {stat(3)} SELECT * FROM stat WHERE regexp_full_match(feature, '[ACGT]+')")
def alphabet_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.alphabet(stats.counts(carriers.documents(spark, sf_dir, carriers.acgtn), 3), "ACGT"))


@query("min_count_filter", f"WITH {c1()}, {stat(4)} SELECT * FROM stat WHERE value >= 3")
def min_count_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.min_count(stats.counts(carriers.documents(spark, sf_dir), 4), 3))


@query("doc_freq_filter", f"WITH {shingles(1)}, df AS (SELECT feature FROM stat GROUP BY feature HAVING count(*) BETWEEN 3 AND 50) SELECT stat.* FROM stat JOIN df USING (feature)")
def doc_freq_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.doc_freq(_doc_words(spark, sf_dir), 3, 50))


_SCALES = {
    "frequency": "value / sum(value) OVER w",
    "l2": "value / sqrt(sum(value * value) OVER w)",
    "zscore": "(value - sum(value) OVER w / 125.0) / sqrt(sum(value * value) OVER w / 125.0 - power(sum(value) OVER w / 125.0, 2))",
    "minmax": "CASE WHEN max(value) OVER w > min(value) OVER w THEN (value - min(value) OVER w) / (max(value) OVER w - min(value) OVER w) ELSE 1.0 END",
    "log1p": "ln(value + 1.0)",
    "binary": "1.0",
}


def _scaled(how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        counts = stats.counts(carriers.user_events(spark, sf_dir), 3)
        return stats.normalise(counts, how, 125).select("seq_id", "feature", r(F.col("value"), 6).alias("x"))

    return run


for _how, _sql in _SCALES.items():
    query(f"kmer_{_how}_norm", f"WITH {c4()}, {stat(3)} SELECT seq_id, feature, {rs(f'CAST({_sql} AS DOUBLE)', 6)} AS x FROM stat WINDOW w AS (PARTITION BY seq_id)")(_scaled(_how))


@query("composition", f"WITH {C5}, {stat(1)} SELECT seq_id, feature AS symbol, value AS n, {rs('value / sum(value) OVER (PARTITION BY seq_id)', 6)} AS p FROM stat")
def composition(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = stats.combine(stats.Composition().extract(carriers.language_sources(spark, sf_dir)))
    shares = stats.normalise(counts, "frequency")
    return counts.join(shares.withColumnRenamed("value", "p"), ["seq_id", "feature"]).select("seq_id", F.col("feature").alias("symbol"), F.col("value").cast("bigint").alias("n"), r(F.col("p"), 6).alias("p"))


@query("marginals", f'WITH {c1()}, {stat(4)} SELECT seq_id, CAST(sum(value) AS BIGINT) AS total, count(*) AS "distinct", CAST(sum(value * value) AS BIGINT) AS sumsq, max(value) AS top FROM stat GROUP BY seq_id')
def marginals(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = stats.marginals(stats.counts(carriers.documents(spark, sf_dir), 4))
    return m.select("seq_id", *(F.col(c).cast("bigint").alias(c) for c in ("total", "distinct", "sumsq", "top")))


@query("class_histogram", f"WITH {c4()}, {stat(3)} SELECT seq_id, array_to_string(list_sort(string_split(feature, '')), '') AS class, value, count(*) AS n_words FROM stat GROUP BY ALL")
def class_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.class_histogram(value_long(stats.counts(carriers.user_events(spark, sf_dir), 3)))


@query("token_shingles", f"WITH {shingles(3)} SELECT * FROM stat")
def token_shingles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(_doc_words(spark, sf_dir, 3))


@query("spaced_word_counts", f"WITH {c1()}, km AS (SELECT seq_id, substr(residues, i, 2) || substr(residues, i + 3, 2) AS feature FROM (SELECT seq_id, residues, unnest(range(1, length(residues) - 3)) AS i FROM seq)) SELECT seq_id, feature, count(*) AS value FROM km GROUP BY ALL")
def spaced_word_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.combine(stats.SpacedWord("11011").extract(carriers.documents(spark, sf_dir))))


@query("column_histogram_nation", f"WITH {NATION} SELECT seq_id AS n_name, feature, value FROM stat")
def column_histogram_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(carriers.nation_histograms(spark, sf_dir)).withColumnRenamed("seq_id", "n_name")


@query("column_histogram_priority", "SELECT CAST(o_custkey AS VARCHAR) AS seq_id, o_orderpriority AS feature, count(*) AS value FROM orders GROUP BY ALL")
def column_histogram_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return value_long(stats.combine(stats.ColumnHistogram("o_custkey", "o_orderpriority").extract(carriers.table(spark, sf_dir, "orders"))))


@query("combine_max", f"WITH {C5}, km AS (SELECT CAST(doc_id AS VARCHAR) AS d, lang || '/' || source AS seq_id, {'translate(regexp_replace(lower(text), ' + repr('[^a-z]') + ', ' + repr('') + ', ' + repr('g') + '), ' + repr(carriers.LETTERS) + ', ' + repr(carriers.BASES) + ')'} AS residues FROM documents), one AS (SELECT d, seq_id, substr(residues, i, 3) AS feature FROM (SELECT d, seq_id, residues, unnest(range(1, length(residues) - 1)) AS i FROM km)), per AS (SELECT d, seq_id, feature, count(*) AS value FROM one GROUP BY ALL) SELECT seq_id, feature, max(value) AS value FROM per GROUP BY ALL")
def combine_max(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest count of a part, as a combiner other than the sum."""
    parts = carriers.language_sources(spark, sf_dir).withColumns({"group": F.col("seq_id"), "seq_id": F.col("part_id").cast("string")})
    per_part = stats.counts(parts.drop("group"), 3).join(parts.select("seq_id", "group"), "seq_id").select(F.col("group").alias("seq_id"), "feature", "value")
    return value_long(stats.combine(per_part, "max"))


@query("eligible", f"WITH {c1()} SELECT seq_id, CAST(length(residues) AS BIGINT) AS len, length(residues) >= 10 AS fits FROM seq")
def eligible(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequences long enough for every function and null model: words of 4, draws of 10, patterns of 5."""
    seq = carriers.documents(spark, sf_dir)
    return seq.select("seq_id", F.length("residues").cast("bigint").alias("len"), (F.length("residues") >= 10).alias("fits"))
