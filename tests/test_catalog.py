"""Registered queries: their columns against their oracles, streams against batch, and the guard of the corpus operators."""

import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

from seqcompare import catalog
from seqcompare.streaming import counts as streaming

REPO = Path(__file__).resolve().parents[1]
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = ["kmer_counts_doc", "kmer_no_n", "class_histogram", "af_d2s", "af_chebyshev", "strategy_binned", "bootstrap_q7", "matrix_test", "noise_select", "event_asof", "range_draws", "stream_session", "stream_stateful", "configured_pipeline"]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_oracle(spark, small, duck, name):
    df = catalog.queries()[name](spark, small)
    columns = sorted(df.columns)
    oracle = duck.sql(catalog.oracle_sql()[name])
    assert sorted(oracle.columns) == columns
    key = lambda row: tuple(repr(x) for x in row)
    ours = sorted((tuple(r[c] for c in columns) for r in df.collect()), key=key)
    theirs = sorted((tuple(r[oracle.columns.index(c)] for c in columns) for r in oracle.fetchall()), key=key)
    assert ours == theirs


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_streams_are_collected_in_files(spark, small, mode):
    stream = streaming.events(spark, small)
    found = streaming.collected(streaming.windowed(stream, "session") if mode == "complete" else streaming.stateful_kmers(stream, 3), f"files-{mode}", mode)
    assert found.inputFiles() and found.count() > 100  # the memory sink holds rows on the driver and has no files


def test_a_stream_without_rows_is_an_empty_table(spark, small):
    found = streaming.collected(streaming.events(spark, small).where("user_id < 0"), "none", "append")
    assert found.count() == 0 and "symbol" in found.columns


def test_oracles_are_of_queries():
    assert set(catalog.oracle_sql()) <= set(catalog.queries()) and len(catalog.queries()) > 120


def test_entry(spark, small):
    assert catalog.entry(spark, small).limit(5).count() == 5


def test_the_engine_stands_without_the_corpus_operators(tmp_path):
    shutil.copytree(REPO / "seqcompare", tmp_path / "seqcompare", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(REPO / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 120 and not any(n.startswith('op1_') for n in q) and e.llm is None"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": ":".join(p for p in sys.path if p and str(REPO) not in p)})
