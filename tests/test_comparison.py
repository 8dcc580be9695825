"""Pair functions and plans against brute force over whole dictionaries."""

import hashlib
from itertools import product

import numpy as np
import pyarrow.compute as pc
import pytest
from pyspark.sql import functions as F

from seqcompare import baselines, cost
from seqcompare.catalog import comparison
from seqcompare.cost import python_nodes
from seqcompare.functions import sketch, spaced
from seqcompare.functions.library import EIGHTEEN, REGISTRY, classes, get
from seqcompare.operators import stats, windows
from seqcompare.plans import matrix, pipeline, search
from seqcompare.sources import carriers, formats, sinks

WORDS = ["".join(w) for w in product("ACGT", repeat=2)]
TEXTS = {"a": "ACGTACGGTTACA", "b": "AACCGGTTAACC", "c": "TTTTTTTTTT", "d": "ACACACACGT"}
SEQ = "seq_id string, part_id bigint, offset bigint, residues string"


@pytest.fixture(scope="module")
def seq(spark):
    return spark.createDataFrame([(k, 0, 0, v) for k, v in TEXTS.items()], SEQ)


@pytest.fixture(scope="module")
def stat(seq):
    return stats.counts(seq, 2).cache()


def vector(name: str) -> np.ndarray:
    t = TEXTS[name]
    return np.array([sum(t[i : i + 2] == w for i in range(len(t) - 1)) for w in WORDS], float)


def background(x: np.ndarray) -> np.ndarray:
    n = {s: sum(v * w.count(s) for v, w in zip(x, WORDS, strict=True)) for s in "ACGT"}
    return np.array([np.prod([n[s] / sum(n.values()) for s in w]) for w in WORDS]) * x.sum()


def brute(fn: str, a: str, b: str) -> float:
    x, y = vector(a), vector(b)
    p, q, z = x / x.sum(), y / y.sum(), x + y > 0
    e, f = background(x), background(y)
    kl = lambda u, v: (u[u > 0] * np.log(u[u > 0] / v[u > 0])).sum()
    dot = (x * y).sum()
    cosine = dot / np.sqrt((x * x).sum() * (y * y).sum())
    u, v = (x + 1) / (x + 1).sum(), (y + 1) / (y + 1).sum()
    with np.errstate(all="ignore"):
        size = np.sqrt((x - e) ** 2 + (y - f) ** 2)
        return {
            "d2": lambda: dot, "d2z": lambda: ((x - x.mean()) * (y - y.mean())).sum() / (x.std() * y.std()), "euclidean": lambda: np.sqrt(((x - y) ** 2).sum()),
            "sqeuclidean": lambda: ((x - y) ** 2).sum(), "manhattan": lambda: abs(x - y).sum(), "canberra": lambda: (abs(x - y)[z] / (x + y)[z]).sum(),
            "chisq": lambda: ((x - y)[z] ** 2 / (x + y)[z]).sum(), "sqchord": lambda: ((np.sqrt(x) - np.sqrt(y)) ** 2).sum(), "harmonic": lambda: (2 * (x * y)[z] / (x + y)[z]).sum(),
            "intersection": lambda: np.minimum(x, y).sum(), "kulczynski2": lambda: (1 / x.sum() + 1 / y.sum()) / 2 * np.minimum(x, y).sum(), "jaccard": lambda: ((x > 0) & (y > 0)).sum() / z.sum(),
            "jsd": lambda: (kl(p, (p + q) / 2) + kl(q, (p + q) / 2)) / 2, "cosine": lambda: cosine, "angle": lambda: np.arccos(min(1, cosine)), "containment": lambda: ((x > 0) & (y > 0)).sum() / (x > 0).sum(),
            "minkowski3": lambda: (abs(x - y) ** 3).sum() ** (1 / 3), "jeffrey": lambda: ((u - v) * np.log(u / v)).sum(), "chebyshev": lambda: abs(x - y).max(),
            "d2s": lambda: np.where(size > 0, (x - e) * (y - f) / size, 0).sum(), "d2star": lambda: np.where(e * f > 0, (x - e) * (y - f) / np.sqrt(e * f), 0).sum(),
        }[fn]()


FUNCTIONS = [get(n, words=16) if n in ("d2z", "jeffrey") else get(n) for n in REGISTRY if n != "udf_product"]


@pytest.mark.parametrize("plan", ["none", "binned", "postings", "blocks", "total"])
def test_every_function_in_every_plan(stat, plan):
    rows = matrix.compute(stat, FUNCTIONS, plan, k=2).collect()
    assert len(rows) == 6 * len(FUNCTIONS)
    for r in rows:
        assert r.value == pytest.approx(brute(r.fn, r.i, r.j), abs=1e-8), (r.fn, r.i, r.j)


def test_there_are_eighteen_and_classes_count_all_words():
    assert len(EIGHTEEN) == 18
    assert sum(n for _, n in classes("ACGT", 5)) == 4**5


def test_pairs_that_share_nothing_stay(spark):
    two = spark.createDataFrame([("a", 0, 0, "AAAA"), ("b", 0, 0, "CCCC")], SEQ)
    rows = {r.fn: r.value for r in matrix.compute(stats.counts(two, 2), ["d2", "manhattan", "chebyshev"], "none").collect()}
    assert rows == {"d2": 0, "manhattan": 6, "chebyshev": 3}


def test_chunks_and_parts_change_nothing(seq):
    whole = {tuple(r) for r in stats.counts(seq, 3).collect()}
    for size in (1, 2, 5):
        assert {tuple(r) for r in stats.counts(seq, 3, part=size).collect()} == whole
    assert sum(n for *_, n in whole) == sum(len(t) - 2 for t in TEXTS.values())


def test_short_sequences_have_no_words(spark):
    assert stats.counts(spark.createDataFrame([("a", 0, 0, "AC"), ("b", 0, 0, "")], SEQ), 3).count() == 0


def test_one_sequence_has_no_pairs(spark):
    one = spark.createDataFrame([("a", 0, 0, "ACGT")], SEQ)
    assert matrix.compute(stats.counts(one, 2), ["d2"], "none").count() == 0


def test_threshold_on_parts_differs_from_threshold_on_sums(spark):
    parts = spark.createDataFrame([("a", 0, 0, "AAA"), ("a", 1, 0, "AAA")], SEQ)
    assert stats.min_count(stats.counts(parts, 3), 2).count() == 1


def test_total_plan_refuses_large_statistics(stat, monkeypatch):
    monkeypatch.setattr(matrix, "MAX_TOTAL_ROWS", 3)
    with pytest.raises(ValueError, match="too large"):
        matrix.compute(stat, ["d2"], "total")


def test_metric_laws(stat):
    rows = {(r.fn, r.i, r.j): r.value for r in matrix.compute(stat, ["euclidean", "manhattan", "chebyshev", get("jsd", sqrt=True)], "none").collect()}
    for fn in ("euclidean", "manhattan", "chebyshev", "jsd"):
        d = lambda a, b, fn=fn: rows[(fn, min(a, b), max(a, b))]
        assert all(d(a, b) <= d(a, c) + d(c, b) + 1e-9 for a, b, c in product("abcd", repeat=3) if len({a, b, c}) == 3)


def test_mirror_and_phylip(stat):
    square = matrix.mirror(matrix.compute(stat, ["d2"], "none"), matrix.self_values(stat, "d2"))
    assert square.count() == 16
    lines = sinks.phylip(square).splitlines()
    assert lines[0] == "4" and lines[1].startswith("a ") and len(lines) == 5


def test_extraction_by_rows_stays_in_the_jvm(seq):
    assert python_nodes(stats.counts(seq, 4, jvm=True)) == 0


ODD = {"empty": "", "null": None, "n": "ACNNGT", "wide": "ACGTÄCGT", "long": "ACGGT" * 300, "short": "A"}


@pytest.mark.parametrize("options", [{}, {"canonical": True}, {"without": "N"}])
@pytest.mark.parametrize("k", [1, 3, 21, 40])
def test_both_ways_of_counting_agree(spark, monkeypatch, k, options):
    if options.get("canonical"):
        odd = {n: t for n, t in ODD.items() if n != "wide"}
    else:
        odd = ODD
    monkeypatch.setattr(windows, "STEP", 64)
    rows = spark.createDataFrame([(n, p, 0, t) for n, t in odd.items() for p in (0, 1)] + [(k, 0, 0, v) for k, v in TEXTS.items()], SEQ)
    one, two = ({tuple(r) for r in stats.counts(rows, k, **options, **more).collect()} for more in ({}, {"jvm": True}))
    assert one == two


def test_steps_cover_every_window_once():
    data, bounds = np.frombuffer(b"ACGTACGTAC" * 40, np.uint8), np.array([0, 3, 3, 250, 252, 400])
    windows_of = sorted((int(row), bytes(part[s : s + 4])) for part, starts, rows in windows.steps(data, bounds, 4) for s, row in zip(starts, rows, strict=True))
    assert windows_of == sorted((r, bytes(data[i : i + 4])) for r in range(5) for i in range(bounds[r], bounds[r + 1] - 3))


def test_sketch_is_exact_when_it_holds_every_word(seq, stat):
    est = {(r.i, r.j): r.jaccard for r in sketch.matrix(sketch.sketches(seq, 2, 100, canonical=False), 2, 100).collect()}
    for r in matrix.compute(stat, ["jaccard"], "none").collect():
        assert est[r.i, r.j] == pytest.approx(r.value)


def test_sketch_error_and_baseline(spark, small):
    rows = carriers.documents(spark, small).where("part_id < 20")
    texts = {r.seq_id: r.residues for r in rows.collect()}
    exact = {(r.i, r.j): r.value for r in matrix.compute(stats.counts(rows, 9, canonical=True), ["jaccard"], "none").collect()}
    est = sketch.matrix(sketch.sketches(rows, 9, 400), 9, 400).collect()
    assert all(abs(r.jaccard - exact[r.i, r.j]) <= 4 * (max(exact[r.i, r.j], 0.01) / 400) ** 0.5 for r in est)
    local = baselines.local_sketch(texts, 9, 400, 2)
    assert all(abs(local[r.i, r.j] - r.value) < 0.1 for r in est if exact[r.i, r.j] > 0.05)  # rarer sharing makes both unsure


def mutated(text: str, rate: float, rng: np.random.Generator) -> str:
    return "".join("ACGT"[("ACGT".index(c) + rng.integers(1, 4)) % 4] if rng.random() < rate else c for c in text)


def test_spaced_words_recover_a_planted_rate(spark):
    rng = np.random.default_rng(3)
    text = "".join(rng.choice(list("ACGT"), 3000))
    texts = {"a": text, "b": mutated(text, 0.1, rng), "c": "".join(rng.choice(list("ACGT"), 30))}
    seq = spark.createDataFrame([(k, 0, 0, v) for k, v in texts.items()], SEQ)
    pattern = "110010100110000110101"
    got = {(r.i, r.j): r.value for r in spaced.distance(seq, [pattern]).collect()}
    assert got["a", "b"] == pytest.approx(-0.75 * np.log(1 - 0.1 * 4 / 3), rel=0.25)
    assert got["b", "c"] is None
    local = baselines.local_spaced(texts, pattern)
    assert {k: v and round(v, 9) for k, v in local.items()} == {k: v and round(v, 9) for k, v in got.items()}


def test_configuration_and_registration(spark, small):
    config = pipeline.PipelineConfig.load('{"source": {"kind": "user_events", "dir": "%s"}, "statistic": {"kind": "kmer", "k": 2}, "functions": ["d2", {"name": "d2z", "words": 25}], "normalise": {"how": "frequency"}}' % small)
    assert {r.fn for r in pipeline.run(spark, config).select("fn").distinct().collect()} == {"d2", "d2z"}
    with pytest.raises(KeyError, match="no pair function"):
        get("nothing")


def test_formats(spark, tmp_path):
    (tmp_path / "x.fa").write_text(">s1 first\nACGT\nAC\n>s2\nTTTT\n")
    (tmp_path / "x.fq").write_text("@r1\nACGT\n+\nIIII\n@r2 more\nGG\n+\nII\n")
    assert {(r.seq_id, r.residues) for r in formats.fasta(spark, str(tmp_path / "x.fa")).collect()} == {("s1", "ACGTAC"), ("s2", "TTTT")}
    assert {(r.seq_id, r.residues) for r in formats.fastq(spark, str(tmp_path / "x.fq")).collect()} == {("r1", "ACGT"), ("r2", "GG")}
    rows = stats.counts(formats.fasta(spark, str(tmp_path / "x.fa")), 2)
    sinks.write(rows, str(tmp_path / "out"), "csv")
    assert spark.read.csv(str(tmp_path / "out")).count() == rows.count()


def test_canonical_and_packed(spark):
    row = spark.range(1).select(stats.canonical(F.lit("TTT")).alias("c"), stats.packed(F.lit("T" * 31)).alias("p")).first()
    assert row.c == "AAA" and row.p == 4**31 - 1


@pytest.mark.parametrize("blocks", [2, 3])
def test_binned_by_blocks_and_without_dense_arrays(stat, monkeypatch, blocks):
    monkeypatch.setattr(matrix, "MAX_DENSE", 1)
    for r in matrix.compute(stat, FUNCTIONS, "binned", k=2, blocks=blocks, bins=3).collect():
        assert r.value == pytest.approx(brute(r.fn, r.i, r.j), abs=1e-8), (r.fn, r.i, r.j)


def test_keys_are_datasets_of_their_own(spark, seq):
    two = seq.withColumn("set", F.lit(1)).unionByName(seq.withColumn("set", F.lit(2)).where("seq_id != 'd'"))
    rows = matrix.compute(stats.keyed_counts(two, 2, ("set",)), FUNCTIONS, "none", keys=("set",), k=2).collect()
    assert len(rows) == 9 * len(FUNCTIONS) and all(r.value == pytest.approx(brute(r.fn, r.i, r.j), abs=1e-8) for r in rows)


def test_other_moments(spark, stat):
    rows = matrix.compute(stat, [get("d2z", words=16, moments="iid")], "none").collect()
    for r in rows:
        x, y = vector(r.i), vector(r.j)
        sd = np.sqrt(x.sum() / 16 * 15 / 16 * y.sum() / 16 * 15 / 16)
        assert r.value == pytest.approx(((x - x.mean()) * (y - y.mean())).sum() / sd)
    with pytest.raises(ValueError, match="moments"):
        get("d2z", words=16, moments="else")


def test_sketches_of_parts_unite(spark):
    rng = np.random.default_rng(2)
    text = "".join(rng.choice(list("ACGT"), 900))
    whole = spark.createDataFrame([("a", 0, 0, text)], SEQ)
    parts = spark.createDataFrame([(f"p{i}", 0, 0, text[i : i + 110]) for i in range(0, 900, 100)], SEQ)
    for how in ("mixed", "xxhash64"):
        one = sketch.sketches(whole, 11, 50, how).first().sketch
        united = sketch.union(sketch.sketches(parts, 11, 50, how).withColumn("seq_id", F.lit("a")), 50).first().sketch
        assert one == united and len(one) == 50 and one == sorted(one)


def test_spaced_words_with_a_substitution_matrix(spark):
    seq = spark.createDataFrame([("a", 0, 0, "ACAGT"), ("b", 0, 0, "ACGGT"), ("c", 0, 0, "ACTGT")], SEQ)
    scores = {("A", "G"): 1, ("A", "T"): -5, ("A", "A"): 2}
    found = {(r.i, r.j): r.score for r in spaced.matches(seq, "11011", threshold=-9, scores=scores).collect()}
    assert found == {("a", "b"): 1, ("a", "c"): -5, ("b", "c"): -1}


def test_chosen_pairs_only(spark, stat):
    pairs = spark.createDataFrame([("a", "c"), ("b", "d")], "i string, j string")
    rows = {(r.i, r.j): r.value for r in matrix.compute(stat, ["d2"], "none", only=pairs).collect()}
    assert rows == {p: pytest.approx(brute("d2", *p)) for p in (("a", "c"), ("b", "d"))}


def test_search_has_the_values_of_the_matrix_for_its_queries(spark):
    rng = np.random.default_rng(5)
    rows = [(str(n), 0, 0, "".join(rng.choice(list("ACGT"), int(rng.integers(4, 60))))) for n in range(90, 131)]
    seq = spark.createDataFrame(rows, "seq_id string, part_id bigint, offset bigint, residues string")
    names = ["d2", "euclidean", "manhattan", "jaccard", "jsd", "chebyshev", "containment", "minkowski3"]
    whole = {(r.fn, r.i, r.j): r.value for r in matrix.compute(stats.counts(seq, 3), names, "none").collect()}
    asked = seq.where("cast(seq_id as bigint) % 10 = 0")
    extract = stats.KmerCount(3).extract
    found = {(r.fn, r.i, r.j): r.value for r in search.compute(extract(asked), extract(seq), names).collect()}
    assert len(found) == len(names) * 5 * 40
    for (fn, i, j), value in found.items():
        if i < j or fn != "containment":
            assert value == pytest.approx(whole[fn, min(i, j), max(i, j)], abs=1e-9)


def test_search_makes_no_row_of_a_shared_feature(spark, small):
    found = comparison.af_d2_documents(spark, small)
    assert "Join" not in cost.plan_of(found)
    n = spark.read.parquet(f"{small}/documents.parquet").where("text is not null").count()
    asked = spark.read.parquet(f"{small}/documents.parquet").where("text is not null and doc_id % 100 = 0").count()
    assert found.count() == asked * (n - 1)


@pytest.mark.parametrize("text", ["ACGTACGGTTACAACCGGTTAACCGATTACA" * 3, "AÄCGTÄCGGTTACA", "ACG", ""])
def test_md5_sketches_are_made_in_tasks(spark, text):
    rows = spark.createDataFrame([("a", 0, 0, text), ("b", 0, 0, "GATTACAGATTACACATTAG")], SEQ)
    found = sketch.sketches(rows, 5, 7, "md5", canonical=False)
    plan = cost.plan_of(found)
    assert "Generate" not in plan and "md5(" not in plan  # no row for each word
    words = {text[i : i + 5] for i in range(len(text) - 4)}
    want = sorted(int(hashlib.md5(w.encode()).hexdigest()[:15], 16) for w in words)[:7]
    got = {r.seq_id: (list(r.sketch), r.n_words) for r in found.collect()}
    assert got.get("a") == ((want, len(text) - 4) if want else None) and len(got["b"][0]) == 7


def test_sketches_are_united_in_tasks(spark):
    parts = spark.createDataFrame([("g", list(range(n, n + 40, 3)), 5) for n in range(30)], "seq_id string, sketch array<bigint>, n_words bigint")
    united = sketch.union(parts, 10)
    assert "MapInArrow" in cost.plan_of(united)  # what is shuffled is bounded by tasks, not by parts
    assert [(list(r.sketch), r.n_words) for r in united.collect()] == [(list(range(10)), 150)]


def test_exact_jaccard_makes_no_row_of_a_word(spark):
    rng = np.random.default_rng(3)
    texts = {n: "".join(rng.choice(list("ACGT"), 200)) for n in "abcd"} | {"e": "AAAAAA"}
    rows = spark.createDataFrame([(n, 0, 0, t) for n, t in texts.items()], SEQ)
    words = {n: {t[i : i + 4] for i in range(len(t) - 3)} for n, t in texts.items()}
    found = sketch.exact(rows, 4)
    want = {(a, b): len(words[a] & words[b]) / len(words[a] | words[b]) for a in words for b in words if a < b and words[a] & words[b]}
    assert {(r.i, r.j): r.jaccard for r in found.collect()} == pytest.approx(want)
    assert "feature" not in cost.plan_of(found)
    with pytest.raises(Exception, match="not in the alphabet"):
        sketch.exact(rows.withColumn("residues", F.lit("ACGTNACGT")), 4).collect()


def test_spaced_words_are_matched_best_first_without_a_row_for_a_match(spark, monkeypatch):
    """the same matches as one by one, for words with many occurrences, copies, keys, substitution scores and letters beyond ASCII."""
    rng = np.random.default_rng(5)
    base = "".join(rng.choice(list("ACGT"), 400))
    texts = {"a": base + base[:100], "b": mutated(base, 0.2, rng) + "A" * 60, "c": mutated(base, 0.3, rng)[::-1] + "A" * 40, "d": "ÄC" * 30 + base[:80]}
    rows = [(k, s, p, 7, x) for k in (1, 2) for s, t in texts.items() for p, x in enumerate((t[: 150 * k], t[150 * k :], ""))]
    seq = spark.createDataFrame(rows, f"key int, {SEQ}").repartition(3)
    for pattern, options in (("1010011", {}), ("1001", {"scores": {("A", "G"): 1, ("C", "T"): 0, ("A", "C"): -3}, "threshold": -1}), ("1001", {"max_occurrences": 40}), ("11001", {"match": -1, "mismatch": 1, "threshold": 0})):
        found = spaced.matches(seq, pattern, keys=("key",), **options).toPandas()
        expected = {}
        for name, pdf in found.groupby(["key", "i", "j"]):
            keep = spaced.one_to_one(pdf := pdf.reset_index(drop=True))
            expected[name] = (len(keep), int(pdf["differ"].to_numpy()[keep].sum()))
        for cells in (spaced.CELLS, 9):  # with 9, words with many occurrences go by classes
            buckets, ones, span = 5, pattern.count("1"), len(pattern)
            monkeypatch.setattr(spaced, "CELLS", cells)
            dealt, got = spaced.dealt(seq, pattern, buckets, ("key",)).toArrow(), {}
            scoring = (options.get("threshold", 0), options.get("match", 1), options.get("mismatch", -1), options.get("scores"))
            for key in (1, 2):
                for bucket in range(buckets):
                    one = dealt.filter((pc.field("key") == key) & (pc.field("bucket") == bucket))
                    if one.num_rows:
                        for r in spaced._chosen(one, ("key",), ones, span, options.get("max_occurrences"), scoring).to_pylist():
                            n, differ = got.get((r["key"], r["i"], r["j"]), (0, 0))
                            got[r["key"], r["i"], r["j"]] = (n + r["n_match"], differ + r["differ"])
            assert got == expected
        values = spaced.distance(seq, [pattern], keys=("key",), **options)
        assert {(r.key, r.i, r.j): r.n_match for r in values.where("n_match > 0").collect()} == {k: v[0] for k, v in expected.items()}
        assert values.count() == 12 and "Generate" not in values._jdf.queryExecution().executedPlan().toString()
