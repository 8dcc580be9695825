"""A training corpus from raw documents: five stages, each on all that the one before it kept.

Each stage is written as Parquet in the shared folder and read again as the next one's documents; what it wrote on its way
is removed then.

Cases that hold for all stages: a null or empty text is a document without words, which only the classifier may reject; no
stage cuts a text short, however long it is; a row without a doc_id is never a copy, a repeat or contaminated, and stays if
the classifier takes it; of rows that repeat a doc_id, one stays at the join. An empty table gives an empty result with the
same columns. Other columns of documents go along as they are, whatever their names; where the last stage's own columns
(n_tokens, ids) have the name of one, that one is ``input_n_tokens`` or ``input_ids``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqcompare.llm import decontamination, ngram_join, quality_classifier, sentence_pieces, substring_dedup
from seqcompare.llm.common import dropped, kept_names, lean, stage_tables, table, written


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    lean(spark)
    model = quality_classifier.fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality_classifier.accepted(docs, model)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, that of the smallest id."""
    lean(spark)
    return ngram_join.one_of_each(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated windows of words are cut out of the texts, and n_chars follows."""
    lean(spark)
    others = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    cut = substring_dedup.deduplicated(docs, keep=others)
    names = kept_names(list(substring_dedup.COLUMNS), others)
    columns = {c: F.col(names.get(c, c)) for c in docs.columns}
    if "n_chars" in others:
        columns["n_chars"] = F.length("text").cast(docs.schema["n_chars"].dataType)
    return cut.select(*(c.alias(name) for name, c in columns.items()))


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a passage of a benchmark item go."""
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts become piece ids (doc_id, n_tokens, ids); the other columns stay."""
    lean(spark)
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    return sentence_pieces.encoded(docs, None, *others)


STAGES = [
    ("quality classifier", quality),
    ("n-gram Jaccard join", near_duplicates),
    ("substring dedup", repeated_passages),
    ("benchmark decontamination", decontaminated),
    ("SentencePiece encoding and decoding", encoded),
]

#: The stages learn a model and compare shingles by hash, which SQL can't express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in STAGES:
        before = set(stage_tables())
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
        made = [t for t in stage_tables() if t not in before]
        dropped(spark, [*made[:-1], *last])  # the stage's result is the last table
        last = made[-1:]
    return docs
