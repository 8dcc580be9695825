"""The pipeline against a brute-force version of its stages, and its guard."""

import corpus_pipeline
from pyspark.sql import functions as F

from seqcompare.llm import decontamination
from seqcompare.llm.common import stage_tables
from tests.llm.test_operators import HARD, PASSAGE, jaccard_pairs, removed, roots


def test_stages_keep_columns_and_decisions(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").withColumns({"z": F.lit(1), "n_removed": F.lit(2)})
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality classifier", "n-gram Jaccard join", "substring dedup", "benchmark decontamination", "SentencePiece encoding and decoding"]
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in kept.collect()}
        out = stage(spark, kept, small)
        assert out.columns == docs.columns
        kept = spark.createDataFrame(out.collect(), docs.schema)
        after = {r.doc_id: r.text for r in kept.collect()}
        if name == "n-gram Jaccard join":
            root = roots(before, jaccard_pairs(before))
            assert set(after) == {i for i in before if root[i] == i}
        if name == "substring dedup":
            want = removed(list(before.items()))
            assert set(after) == set(before) and all(len(after[i].split()) == want[i][0] - want[i][1] for i in after)
        if name == "benchmark decontamination":
            items = [r.text for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
            assert all(i not in after for i, t in before.items() if any(x in t for x in items))
            bench = spark.read.parquet(f"{small}/benchmark.parquet")
            assert decontamination.overlaps(kept, bench).count() == 0
    last = stages["SentencePiece encoding and decoding"](spark, kept, small)
    assert last.count() == kept.count() and {"doc_id", "ids", "lang", "z"} <= set(last.columns)


def test_stages_of_hard_rows(spark, small):
    """Nulls in any column, empty and very long texts, ties, repeated rows and names that clash, through every stage."""
    kinds = "doc_id long, text string, lang string, source string, n_chars long, n_tokens string, ids int, input_ids int, kept_sha256 string"
    rows = [(i, t, None if i % 2 else "en", "s", None, f"t{i}", i, -i, "mine") for i, t in enumerate(HARD)]
    rows += [rows[10], rows[10], (None, PASSAGE, None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None)]
    docs = spark.createDataFrame(rows, kinds)
    for name, stage in corpus_pipeline.STAGES[1:]:
        for part in (docs, docs.limit(0)):
            out = stage(spark, part, small)
            assert out.columns == docs.columns if name != corpus_pipeline.STAGES[-1][0] else set(out.columns) == {"doc_id", "n_tokens", "ids", "input_n_tokens", "input_input_ids", "input_ids", "lang", "source", "n_chars", "kept_sha256"}
            got = out.collect()
            if part is not docs:
                assert not got
                continue
            by = {r.doc_id: r for r in got if r.doc_id is not None}
            assert sum(r.doc_id is None for r in got) == 2
            if name == "n-gram Jaccard join":
                assert set(by) < set(range(len(HARD))) and {0, 1, 2, 5} <= set(by)
            elif name == corpus_pipeline.STAGES[-1][0]:
                assert all(r.input_n_tokens == f"t{i}" and r.kept_sha256 == "mine" and r.n_tokens == len(r.ids) for i, r in by.items())
            else:
                assert set(by) == set(range(len(HARD))) and all(r.n_tokens == f"t{i}" and r.ids == i and r.input_ids == -i and r.kept_sha256 == "mine" for i, r in by.items())


def test_classifier_stage_of_hard_rows(spark, tmp_path):
    spark.createDataFrame([(i, i % 2) for i in range(len(HARD))], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(HARD)] + [(None, None, 2)], "doc_id long, text string, score int")
    out = corpus_pipeline.quality(spark, docs, str(tmp_path))
    assert out.columns == docs.columns and out.count() <= len(HARD) + 1 and corpus_pipeline.quality(spark, docs.limit(0), str(tmp_path)).count() == 0


def test_run_gives_all_rows_and_leaves_one_table(spark, small):
    before = set(stage_tables())
    assert corpus_pipeline.run(spark, small).count() > 100
    assert len(set(stage_tables()) - before) == 1
