"""Null models, tests, noise and trees: worked examples, ties and known trees."""

import hashlib
import subprocess
import sys
from itertools import permutations
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqcompare import cost, experiments
from seqcompare.operators import noise, nullmodel, significance, trees, windows
from seqcompare.sources import carriers

REPO = Path(__file__).resolve().parents[1]
SEQ = "seq_id string, part_id bigint, offset bigint, residues string"


@pytest.fixture(scope="module")
def seq(spark, small):
    return carriers.event_cohorts(spark, small, 5).cache()


@pytest.mark.parametrize("q", [1, 7, 10])
def test_bootstrap_keeps_lengths_and_draws_words_of_the_data(seq, q):
    parts = [r.residues for r in seq.collect()]
    own = {r.seq_id: r.n for r in seq.groupBy("seq_id").agg(F.sum(F.length("residues")).alias("n")).collect()}
    rows = nullmodel.bootstrap(seq, q, 3).collect()
    assert len(rows) == 15 and all(len(r.residues) == own[r.seq_id] for r in rows)
    for r in rows:
        for at in range(0, len(r.residues) - q + 1, q):
            assert any(r.residues[at : at + q] in t for t in parts)


@pytest.mark.parametrize("block", [3, 1024])
def test_bootstrap_by_parts_and_blocks_is_the_same(seq, monkeypatch, block):
    whole = {(r.replicate, r.seq_id): r.residues for r in nullmodel.bootstrap(seq, 7, 2).collect()}
    monkeypatch.setattr(nullmodel, "PART", 50)
    monkeypatch.setattr(nullmodel, "BLOCK", block)
    parts = nullmodel.bootstrap(seq, 7, 2, overlap=4).collect()
    assert len(parts) > 2 * len(whole)
    for r in parts:
        text = whole[r.replicate, r.seq_id]
        assert r.residues == text[r.offset : r.offset + 49 + 4]
    some = nullmodel.bootstrap(seq, 7, 2, only=seq.select("seq_id").where("seq_id = 'c1'").distinct()).collect()
    assert {r.seq_id for r in some} == {"c1"} and "".join(r.residues for r in sorted(some, key=lambda r: r.offset) if r.replicate == 0) == whole[0, "c1"]


def test_scopes_draw_from_their_own_sequences(spark, seq):
    two = spark.createDataFrame([("x", "a", 0, 0, "AAAAA"), ("x", "b", 0, 0, "CCCC"), ("y", "a", 0, 0, "GGG")], "scope string, " + SEQ)
    made = {(r.scope, r.seq_id): r.residues for r in nullmodel.bootstrap(two, 2, 1, keys=("scope",)).collect()}
    assert {k: len(v) for k, v in made.items()} == {("x", "a"): 5, ("x", "b"): 4, ("y", "a"): 3}
    assert made["y", "a"] == "GGG" and set(made["x", "a"] + made["x", "b"]) <= set("AC")


def test_bootstrap_does_not_depend_on_partitions(seq):
    get = lambda n: {(r.replicate, r.seq_id, r.residues) for r in nullmodel.bootstrap(seq.repartition(n), 7, 2).collect()}
    assert get(1) == get(5)


@pytest.mark.parametrize("keys", [(), ("scope",)])
def test_draws_are_never_broadcast(seq, keys):
    own = seq.withColumn("scope", F.lit("s")) if keys else seq
    made = nullmodel.bootstrap(own, 7, 3, keys=keys)
    assert made.collect()
    joins = [line for line in cost.plan_of(made).splitlines() if "Join" in line and "address_block" in line]
    assert joins and all("ShuffledHashJoin" in line for line in joins)


def test_draws_are_no_rows_of_their_own(spark, monkeypatch):
    """Draws are made by numpy and go in blocks; they are those of md5, for many and few, and for symbols of several bytes."""
    monkeypatch.setattr(nullmodel, "CHUNK", 700)
    monkeypatch.setattr(nullmodel, "BLOCK", 64)
    texts = {"a": "ACGT" * 300, "b": "GGÄ€C" * 4, "c": "T"}
    made = nullmodel.bootstrap(spark.createDataFrame([(k, 0, 0, t) for k, t in texts.items()], SEQ), 2, 2)
    plan = cost.plan_of(made)
    assert all("range" in line for line in plan.splitlines() if "md5(" in line) and "MapInArrow" in plan
    number = lambda text: int(hashlib.md5(text.encode()).hexdigest()[:15], 16)
    source = [t[i : i + 2] for _, _, t in sorted((number(f"range|{k}") % 1024, k, t) for k, t in texts.items()) for i in range(len(t) - 1)]
    want = {(r, k): "".join(source[number(f"1|{r}|{k}|{n}") % len(source)] for n in range(-(-len(t) // 2)))[: len(t)] for k, t in texts.items() for r in range(2)}
    assert {(r.replicate, r.seq_id): r.residues for r in made.collect()} == want


def test_numbered_md5():
    for prefix, lo, hi in (("1|0|c3", 95, 12000), ("x" * 60, 0, 600), ("é", 7, 9), ("1|2|" + "s" * 45, 0, 1200)):
        assert windows.numbered_md5(prefix, lo, hi).tolist() == [int(hashlib.md5(f"{prefix}|{n}".encode()).hexdigest()[:15], 16) for n in range(lo, hi)]


def test_bootstrap_of_short_sequences(spark):
    two = spark.createDataFrame([("a", 0, 0, "AC"), ("b", 0, 0, "ACGTA")], SEQ)
    assert {r.seq_id: len(r.residues) for r in nullmodel.bootstrap(two, 4, 1).collect()} == {"a": 2, "b": 5}
    with pytest.raises(ValueError, match="no sequence"):
        nullmodel.bootstrap(two, 9, 1)


def test_other_null_models(seq):
    own = {r.seq_id: r.residues for r in nullmodel._whole(seq).collect()}
    assert all(sorted(r.residues) == sorted(own[r.seq_id]) for r in nullmodel.generate(seq, "shuffle", 1).collect())
    for r in nullmodel.generate(seq, "markov", 3, order=1).collect():
        assert len(r.residues) == len(own[r.seq_id]) and all(r.residues[i : i + 2] in own[r.seq_id] for i in range(len(r.residues) - 2))
    assert len({r.residues for r in nullmodel.generate(seq, "markov", 3, order=1).where("seq_id = 'c1'").collect()}) == 3
    assert all(len(r.residues) == len(own[r.seq_id]) for r in nullmodel.generate(seq, "markov", 1, order=2).collect())
    assert all(set(r.residues) <= set("CV") for r in nullmodel.generate(seq, "uniform", 1, alphabet="CV").collect())


def observed_and_nulls(spark, t, values, fn="d2"):
    mat = spark.createDataFrame([(fn, "a", "b", t)], "fn string, i string, j string, value double")
    nulls = spark.createDataFrame([(fn, k, "a", "b", v) for k, v in enumerate(values)], "fn string, replicate int, i string, j string, value double")
    return mat, nulls


@pytest.mark.parametrize("t, values, fn, p", [(5.0, [1, 2, 3, 4], "d2", 0), (5.0, [5, 5, 5, 5], "d2", 1), (5.0, [1, 5, 6, 7], "d2", 0.75), (5.0, [6, 7, 5, 1], "manhattan", 0.5), (None, [1, 2, 3, 4], "spaced", 1), (0.5, [None, None, 0.1, 0.9], "spaced", 0.25)])
def test_p_values(spark, t, values, fn, p):
    mat, nulls = observed_and_nulls(spark, t, [None if v is None else float(v) for v in values], fn)
    assert significance.pvalues(mat, nulls, 4).first().p == pytest.approx(p)


def test_plus_one_and_resolution(spark):
    mat, nulls = observed_and_nulls(spark, 5.0, [1.0, 2.0, 3.0, 4.0])
    assert significance.pvalues(mat, nulls, 4, plus_one=True).first().p == pytest.approx(1 / 5)
    assert significance.resolution(190, 100) == {"min_attainable_p": 0.01, "needs_strict_max": True}


@pytest.mark.parametrize("passed, kind", [(3, "green"), (0, "red"), (2, "yellow"), (4, "green")])
def test_classes(spark, passed, kind):
    sig = spark.createDataFrame([("d2", k < passed) for k in range(4)], "fn string, reject boolean")
    assert significance.summary(sig).first()["class"] == kind


def test_related_sequences_are_found_and_random_ones_are_not(spark):
    rng = np.random.default_rng(5)
    make = lambda: "".join(rng.choice(list("ACGT"), 400))
    a = make()
    rows = spark.createDataFrame([("a", 0, 0, a), ("b", 0, 0, a[:380] + "ACGTACGTACGTACGTACGT"), ("c", 0, 0, make()), ("d", 0, 0, make())], SEQ)
    got = {(r.i, r.j): r.reject for r in significance.matrix_test(rows, ["d2"], 5, 1, 150).collect()}
    assert got["a", "b"] and sum(got.values()) <= 2


def test_early_stop_keeps_what_the_full_test_passes(spark, seq):
    full = {(r.i, r.j) for r in significance.matrix_test(seq, ["d2"], 3, 1, 10, seed=1).where("p = 0").collect()}
    live = {(r.i, r.j) for r in significance.early_stop(seq, ["d2"], 3, 1, 1, 10, seed=1).collect()}
    assert live == full


def matrix(spark, n=5):
    return spark.createDataFrame([("d2", str(i), str(j), float(i * 10 + j)) for i in range(n) for j in range(i + 1, n)], "fn string, i string, j string, value double")


def test_noise_levels_are_nested_and_counted(spark):
    rows = noise.select(matrix(spark), [0.0, 0.25, 0.5], 2).collect()
    picked = {(level, t): {(r.i, r.j) for r in rows if r.level == level and r.trial == t and r.replaced} for level in (0.0, 0.25, 0.5) for t in (0, 1)}
    assert [len(picked[x, 0]) for x in (0.0, 0.25, 0.5)] == [0, 3, 5] and picked[0.25, 0] < picked[0.5, 0]


def test_noise_values(spark):
    mat = matrix(spark)
    nulls = spark.createDataFrame([("d2", k, "0", "1", 1000.0 + k) for k in range(3)], "fn string, replicate int, i string, j string, value double")
    for r in noise.from_nulls(noise.select(mat, [0.5]), nulls).collect():
        assert (1000 <= r.value <= 1002) == r.replaced
    clean = {(r.i, r.j): r.value for r in mat.collect()}
    for r in noise.additive(noise.select(mat, [0.5]), 7.0).collect():
        assert 0 <= r.value - clean[r.i, r.j] <= (7 if r.replaced else 0)


def test_losses_report_and_breakpoint(spark):
    scores = spark.createDataFrame([("d2", "nj", "rf", level, 0, s) for level, s in ((0.0, 20.0), (0.1, 22.0), (0.2, 30.0))] + [("d2", "upgma", "rf", level, 0, s) for level, s in ((0.0, 0.0), (0.1, 8.0))], "fn string, builder string, metric string, level double, trial int, score double")
    losses = noise.loss(scores)
    assert {(r.builder, r.level): r.pct for r in losses.collect()}["upgma", 0.1] == "Inf"
    assert {r.builder: r.shown for r in noise.report(losses).collect()} == {"nj": "-", "upgma": "Inf"}
    assert {r.builder: r.level for r in noise.breakpoint(losses).collect()} == {"nj": 0.1, "upgma": 0.1}


NAMES = ["a", "b", "c", "d", "e"]
TRUE = "(((a:2,b:2):1,c:3):2,(d:4,e:4):1);"


def distances(tree) -> np.ndarray:
    paths = {}

    def walk(n, above):
        if not n[2]:
            paths[n[0]] = above
        for k, c in enumerate(n[2]):
            walk(c, [*above, (len(above), k, id(c), c[1])])

    walk(tree, [])
    out = np.zeros((len(NAMES), len(NAMES)))
    for i, a in enumerate(NAMES):
        for j, b in enumerate(NAMES):
            out[i, j] = sum(x[3] for x in set(paths[a]) ^ set(paths[b]))
    return out


def test_builders_recover_trees():
    tree = trees.parse(TRUE)
    d = distances(tree)
    made = trees.upgma(NAMES, d)
    assert trees.robinson_foulds(made, tree) == 0 and dict(trees.heights(made))["a,b,c,d,e"] == 5
    unequal = trees.parse("(((a:1,b:5):1,c:3):2,(d:1,e:7):1);")
    nj = trees.neighbor_joining(NAMES, distances(unequal))
    assert trees.robinson_foulds(nj, unequal, rooted=False) == 0
    assert np.allclose(distances(nj), distances(unequal))
    assert np.allclose(distances(trees.root(nj)), distances(unequal))


def test_tree_distances():
    a, b = trees.parse(TRUE), trees.parse("(((a,c),b),(d,e));")
    assert trees.robinson_foulds(a, a) == trees.matching_cluster(a, a) == 0
    assert trees.robinson_foulds(a, b) == 2 and trees.matching_cluster(a, b) == 2
    star = trees.parse("(a,b,c,d,e);")
    assert trees.robinson_foulds(a, star) == 3 and trees.matching_cluster(a, star) == 2 + 3 + 2
    assert trees.leaves(trees.parse("('x y','it''s');")) == {"x y", "it's"}
    assert trees.parse(trees.newick(a)) == a


@pytest.mark.parametrize("seed", range(5))
def test_assignment_is_least(seed):
    cost = np.random.default_rng(seed).integers(0, 9, (5, 5)).astype(float)
    assert sum(cost[i, j] for i, j in enumerate(trees.assignment(cost))) == min(sum(cost[i, p[i]] for i in range(5)) for p in permutations(range(5)))


def test_midpoint_and_outgroup_roots():
    nj = trees.parse("(a:1,b:2,(c:1,d:6):1);")
    mid = trees.root(nj)
    depth = lambda n, above=0.0: {n[0]: above} if not n[2] else {k: v for c in n[2] for k, v in depth(c, above + c[1]).items()}
    top = sorted(depth(mid).values())
    assert top[-1] == pytest.approx(4.5) and trees.leaves(trees.root(nj, "outgroup", "a")[2][0]) == {"a"}


def test_zero_noise_has_no_loss_and_noise_rises(spark, small):
    from seqcompare.catalog import queries

    losses = queries()["loss_arithmetic"](spark, small).collect()
    assert all(r.delta == 0 for r in losses if r.level == 0) and any(r.level == 0.5 for r in losses)


def test_plans_agree_and_are_timed(spark, seq, monkeypatch):
    rows = experiments.strategies({"small": (seq, 2, "CVPSE")}, names=("d2",)).collect()
    assert {r.entries for r in rows} == {10} and all(r.seconds > 0 and r.shuffle_bytes > 0 and r.shuffle_records > 0 and r.sequences == 5 for r in rows)
    from seqcompare.plans import matrix as plans

    monkeypatch.setattr(plans, "MAX_TOTAL_ROWS", 1)
    assert [(r.strategy, r.seconds) for r in experiments.strategies({"small": (seq, 2, "CVPSE")}, ("total",), names=("d2",)).collect()] == [("total", None)]


def test_scaling_binds_its_workers(spark, seq):
    held = spark.conf.get("spark.sql.shuffle.partitions")
    rows = experiments.scaling(seq, (1, 2), k=4, size=20).collect()
    assert spark.conf.get("spark.sql.shuffle.partitions") == held and {(r.method, r.workers) for r in rows} == {(m, n) for m in ("spark", "process", "d2 binned") for n in (1, 2)}
    assert all(r.speedup == pytest.approx(1) for r in rows if r.workers == 1)


def test_a_main_module_that_ends_does_not_break_the_processes(tmp_path):
    main = tmp_path / "main.py"
    main.write_text(f"import os, sys\nif __name__ != '__main__': os._exit(1)\nsys.path.insert(0, {str(REPO)!r})\nfrom seqcompare import baselines\nt = {{n: 'ACGTTGCAACGTGGCATTACGATCGA'[i:] for i, n in enumerate('abc')}}\nassert baselines.local_spaced(t, '11011', threads=2) == baselines.local_spaced(t, '11011')\n")
    subprocess.run([sys.executable, str(main)], check=True)


def test_all_eighteen_are_tested_under_every_null_model(spark, small):
    from seqcompare.functions.library import EIGHTEEN

    rng = np.random.default_rng(5)
    a = "".join(rng.choice(list("ACGT"), 300))
    b = "".join(rng.choice(list("ACGT"), 300))
    rows = spark.createDataFrame([("a", 0, 0, a), ("a2", 0, 0, a[:290] + "ACGTACGTAC"), ("b", 0, 0, b), ("b2", 0, 0, "CC" + b[2:])], SEQ)
    out = experiments.reliability({"x": (rows, 3, "ACGT")}, (1, 4), 3, alpha=0.5).collect()
    assert {(r.q, r.fn) for r in out} == {(q, f) for q in (1, 4) for f in EIGHTEEN} and all(r.m == 6 and r.dataset == "x" for r in out)
    best = significance.consistent(spark.createDataFrame(out)).collect()
    assert {r.fn for r in best} == set(EIGHTEEN)


def test_a_null_similarity_is_the_farthest(spark):
    rows = spark.createDataFrame([(f, 0.0, 0, "a", b, v) for f in ("d2", "manhattan") for b, v in (("b", 10.0), ("c", None), ("d", 1.0))], "fn string, level double, trial int, i string, j string, value double")
    got = {(r.fn, r.j): r.value for r in experiments.as_distances(rows, ()).collect()}
    assert got == {("d2", "b"): 0, ("d2", "c"): 9, ("d2", "d"): 9, ("manhattan", "b"): 10, ("manhattan", "c"): 10, ("manhattan", "d"): 1}


def test_plans_have_no_nested_loop_over_text_and_no_window_over_all(spark, seq):
    from seqcompare.cost import plan_of
    from seqcompare.operators import stats
    from seqcompare.plans import matrix as plans

    drawn = plan_of(nullmodel.bootstrap(seq, 7, 2))
    assert "NestedLoopJoin" not in drawn.replace("BroadcastNestedLoopJoin BuildRight, Inner\n", "") or "residues" not in drawn.split("NestedLoopJoin")[1].split("\n")[0]
    mat = plans.compute(stats.counts(seq, 2), ["d2"], "none")
    for df in (noise.select(mat, [0.1]), noise.additive(noise.select(mat, [0.1])), plans.to_distance(mat)):
        for line in plan_of(df).split("\n"):
            if " Window [" in line:
                assert "range" in line.rsplit("], [", 2)[1] or "sum(n" in line, line


def test_imputation_and_taxonomy(spark):
    mat = matrix(spark).withColumn("value", F.when(F.col("i") == "0", F.lit(None)).otherwise(F.col("value")))
    assert all(r.value == 34 for r in trees.impute(mat).where("imputed").collect())
    assert trees.newick(trees.from_taxonomy([("x", "a"), ("x", "b"), ("y", "c")])) == "((a:1,b:1):1,(c:1):1);"


def test_users_are_tested_as_in_the_matrix_of_all_pairs(spark, small):
    seq = carriers.user_events(spark, small).where("cast(seq_id as bigint) < 12 or cast(seq_id as bigint) = 100")
    whole = {(r.fn, r.i, r.j): r.beaten for r in significance.matrix_test(seq, ["d2", "manhattan"], 3, 7, 2).collect()}
    asked = F.col("seq_id").cast("bigint") % 100 == 0
    found = significance.search_test(seq, asked, ["d2", "manhattan"], 3, 7, 2)
    rows = found.collect()
    assert rows and all(r.beaten == whole[r.fn, min(r.i, r.j), max(r.i, r.j)] for r in rows)
    assert "Join" not in cost.plan_of(found)  # neither pairs nor null values are joined


def test_families_of_tests_are_run_on_their_own(spark):
    """F16, F17: what is left for the last plan are tables that were made, no null dataset and no matrix."""
    rng = np.random.default_rng(9)
    seq = spark.createDataFrame([(n, 0, 0, "".join(rng.choice(list("ACGT"), 60))) for n in "abc"], "seq_id string, part_id bigint, offset bigint, residues string")
    tests = experiments.all_tests(seq, 2, "ACGT", (1,), 1)
    plan = tests._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" not in plan and "Join" not in plan and "Aggregate" not in plan


def test_consistent_set_has_null_datasets_enough_for_its_level(spark, small, monkeypatch):
    """with two replicates an entry passed by beating two null values, which one in three unrelated ones does."""
    from inspect import signature

    from seqcompare import catalog

    asked = []

    def recorded(seq, *args, **options):
        given = signature(all_tests).bind(seq, *args, **options)
        given.apply_defaults()
        asked.append(given.arguments)
        return spark.createDataFrame([(1, "d2", True)], "q int, fn string, reject boolean")

    all_tests = experiments.all_tests
    monkeypatch.setattr(experiments, "all_tests", recorded)
    catalog.queries()["consistent_set"](spark, small).collect()
    assert len(asked) == 2
    for a in asked:
        assert tuple(a["qs"]) == (1, 7, 10) and a["replicates"] * a["alpha"] >= 1
