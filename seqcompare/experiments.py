"""The experiments, re-expressed on the given tables: reliability, noise curves, plans against each other, scaling."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, cost
from .cost import timed
from .functions import sketch, spaced
from .functions.library import HISTOGRAM, get
from .operators import noise, significance, stats, trees
from .plans import matrix
from .sources import carriers
from .stages import settled

LEVELS = (0.0, 0.02, 0.04, 0.06, 0.08, 0.10, 0.2, 0.5, 0.9)
QS = (1, 7, 10)
PATTERN = "1100101100101011"
#: Functions of the robustness study: those that hold on all datasets, and the two nearest to them.
ROBUST = ("d2", "d2s", "d2z", "d2star")


def histogram_functions(words: int, names: tuple[str, ...] = HISTOGRAM) -> list:
    return [get(n, words=words) if n == "d2z" else get(n) for n in names]


def sketch_values(seq: DataFrame, k: int, size: int, keys: tuple[str, ...] = ()) -> DataFrame:
    found = sketch.matrix(sketch.sketches(seq, k, size, canonical=False, keys=keys), k, size, keys)
    return found.select(*keys, F.lit("minhash").alias("fn"), "i", "j", "value")


def spaced_values(seq: DataFrame, patterns: list[str], alphabet: str = "ACGT", keys: tuple[str, ...] = (), **options) -> DataFrame:
    found = spaced.distance(seq, patterns, alphabet=alphabet, keys=keys, **options)
    return found.select(*keys, F.lit("spaced").alias("fn"), "i", "j", "value")


def all_tests(seq: DataFrame, k: int, alphabet: str, qs: tuple[int, ...] = QS, replicates: int = 100, alpha: float = 0.01, seed: int = 1, sketch_k: int = 8, size: int = 256, patterns: tuple[str, ...] = (PATTERN,), strategy: str = "binned", **options) -> DataFrame:
    """(q, fn, i, j, t, beaten, p, level, reject): every entry of all eighteen functions under every null model.

    Histogram functions share one plan for all null models and replicates; the sketch and the spaced-word distance have
    theirs, on the same synthetic sequences. Each plan is run on its own, so that the driver never holds one of all of them.
    """
    entries = significance.entries_of(seq)
    histogram = significance.matrix_test(seq, histogram_functions(len(alphabet) ** k), k, qs, replicates, alpha, seed, strategy, alphabet=alphabet)
    tests = [settled(histogram)]
    for values, span in (
        (lambda s, keys: sketch_values(s, sketch_k, size, keys), sketch_k),
        (lambda s, keys: spaced_values(s, list(patterns), alphabet, keys, **options), max(map(len, patterns))),
    ):
        made, inner = significance.synthesised(seq, qs, replicates, seed, overlap=span - 1)
        made = settled(made)
        p = significance.pvalues(settled(values(seq, ())), settled(values(made, inner)), replicates, keys=("q",))
        tests.append(settled(significance.bonferroni(p, entries, alpha)))
    return reduce(lambda a, b: a.unionByName(b.select(a.columns)), tests)


def reliability(datasets: dict[str, tuple[DataFrame, int, str]], qs: tuple[int, ...] = QS, replicates: int = 100, alpha: float = 0.01, **options) -> DataFrame:
    """(dataset, q, fn, m, passed, share, class): every function on every dataset (sequences, k, alphabet) under every null model."""
    tests = [all_tests(seq, k, alphabet, qs, replicates, alpha, **options).withColumn("dataset", F.lit(name)) for name, (seq, k, alphabet) in datasets.items()]
    return significance.summary(reduce(DataFrame.unionByName, tests), keys=("dataset", "q", "fn"))


def taxonomy_newick(rows: DataFrame) -> str:
    """Rows of (group, leaf) as a gold tree; leaves are few, a row each in the result."""
    return trees.newick(trees.from_taxonomy(sorted(tuple(r) for r in rows.distinct().collect())))


def group_taxonomy(seq: DataFrame) -> str:
    """Groups named before the slash of a sequence's name."""
    return taxonomy_newick(seq.select(F.split("seq_id", "/")[0].alias("group"), "seq_id"))


def noise_study(seq: DataFrame, gold: str, names: tuple[str, ...] = ROBUST, k: int = 4, qs: tuple[int, ...] = QS, levels: tuple[float, ...] = LEVELS, trials: int = 3, replicates: int = 2, seed: int = 1, patterns: tuple[str, ...] = (PATTERN,), with_spaced: bool = True) -> DataFrame:
    """(q, fn, builder, metric, level, trial, score): tree distances from the gold tree as entries turn to noise.

    Entries of histogram functions take values of the null matrices of q; those of the spaced-word distance, whose null
    matrices have gaps, gain a uniform value instead, the same for every q.
    """
    spark, functions = seq.sparkSession, histogram_functions(4**k, names)
    models = F.broadcast(spark.createDataFrame([(q,) for q in qs], "q int"))
    observed = settled(matrix.compute(settled(stats.counts(seq, k)), functions, "binned", k=k))
    nulls = significance.null_matrix(seq, functions, k, qs, replicates, seed, strategy="binned")
    chosen = noise.select(observed, list(levels), trials, seed).join(models, F.lit(True))
    noisy = noise.from_nulls(chosen, settled(nulls), seed, ("q",)).select("q", "fn", "level", "trial", "i", "j", "value")
    if with_spaced:
        own = noise.additive(noise.select(settled(spaced_values(seq, list(patterns))), list(levels), trials, seed), seed=seed).join(models, F.lit(True))
        noisy = noisy.unionByName(own.select(noisy.columns))
    return curve_scores(settled(noisy), gold, ("q",))


def as_distances(noisy: DataFrame, keys: tuple[str, ...], kinds: dict[str, str] | None = None) -> DataFrame:
    """Similarities become the largest of their matrix less the value; then null ones the largest distance of it."""
    similar = F.col("fn").isin([f for f in [*HISTOGRAM, "minhash", "spaced"] if significance.kind_of(f, kinds) == "similarity"])
    by = [*keys, "fn", "level", "trial"]
    range_of = noisy.groupBy(*by).agg(F.max("value").alias("top"), F.min("value").alias("low"))
    far = F.when(similar, F.col("top") - F.col("value")).otherwise(F.col("value"))
    farthest = F.coalesce(F.when(similar, F.col("top") - F.col("low")).otherwise(F.col("top")), F.lit(1.0))
    return noisy.join(range_of, by).select(*by, "i", "j", F.coalesce(far, farthest).alias("value"))


def curve_scores(noisy: DataFrame, gold: str, keys: tuple[str, ...] = ()) -> DataFrame:
    built = trees.build(as_distances(noisy, keys), [*keys, "fn", "level", "trial"])
    return trees.scores(built, gold)


@contextmanager
def workers(spark: SparkSession, n: int) -> Iterator[None]:
    """No more than n tasks at a time: shuffles of n partitions, which are not split or dealt anew. For eager actions only."""
    wanted = {"spark.sql.shuffle.partitions": str(n), "spark.sql.adaptive.enabled": "false"}
    held = {k: spark.conf.get(k) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)


def strategies(datasets: dict[str, tuple[DataFrame, int, str]], plans: tuple[str, ...] = ("none", "binned", "total"), q: int = 1, replicates: int = 1, names: tuple[str, ...] = HISTOGRAM) -> DataFrame:
    """(dataset, sequences, strategy, seconds, entries, shuffle_bytes, shuffle_records): one significance instance of all
    histogram functions under each plan, with what it shuffled. Null where a plan refuses the size."""
    rows, spark = [], None
    for name, (seq, k, alphabet) in datasets.items():
        spark = seq.sparkSession
        n = seq.select("seq_id").distinct().count()
        for plan in plans:
            run = lambda seq=seq, k=k, alphabet=alphabet, plan=plan: significance.matrix_test(seq, histogram_functions(len(alphabet) ** k, names), k, q, replicates, strategy=plan, alphabet=alphabet).where("p is not null").count()
            try:
                took = cost.measured(spark, run)
                rows.append((name, n, plan, took.seconds, int(took.result), took.shuffle_bytes, took.shuffle_records))
            except ValueError:
                rows.append((name, n, plan, None, None, None, None))
    return spark.createDataFrame(rows, "dataset string, sequences bigint, strategy string, seconds double, entries bigint, shuffle_bytes bigint, shuffle_records bigint")


def scaling(seq: DataFrame, counts: tuple[int, ...] = (1, 2, 4), fn: str = "minhash", k: int = 21, size: int = 1000, pattern: str = PATTERN, plan: str = "binned") -> DataFrame:
    """(method, workers, seconds, speedup, efficiency): a distance here with so many tasks at a time, and in one process.

    ``process`` is the stand-in of a tool for one machine; it is given the whole residues, so the sequences must be of a
    moderate size. ``plan`` is that of the D2 matrix, which is timed beside the distance as the platform's own work.
    """
    spark = seq.sparkSession
    rows: list[tuple] = []
    base: dict[str, float] = {}
    texts = {r.seq_id: r.residues for r in seq.groupBy("seq_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("part_id", "residues"))), lambda x: x.residues), "N").alias("residues")).toLocalIterator()}
    for n in counts:
        with workers(spark, n):
            dealt = seq.repartition(n)
            if fn == "minhash":
                actions: tuple[tuple[str, Callable], ...] = (("spark", lambda dealt=dealt: sketch.matrix(sketch.sketches(dealt, k, size), k, size).count()), ("process", lambda n=n: len(baselines.local_sketch(texts, k, size, n))))
            else:
                actions = (("spark", lambda dealt=dealt: spaced.distance(dealt, [pattern]).count()), ("process", lambda n=n: len(baselines.local_spaced(texts, pattern, threads=n))))
            for method, action in (*actions, (f"d2 {plan}", lambda dealt=dealt, n=n: matrix.compute(stats.counts(dealt, 4), ["d2"], plan, bins=n).count())):
                seconds, _ = timed(action)
                first = base.setdefault(method, seconds * n)  # as if with one worker
                rows.append((method, n, seconds, first / seconds, first / seconds / n))
    return spark.createDataFrame(rows, "method string, workers int, seconds double, speedup double, efficiency double")


def mixed_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(carrier, sequences, rows, strategy, entries): many short and few long sequences, each under the plan that is chosen for it."""
    out = []
    for name, seq in (("benchmark_items", carriers.benchmark_items(spark, sf_dir)), ("language_sources", carriers.language_sources(spark, sf_dir))):
        stat = stats.counts(seq, 6)
        plan, options = matrix.plan_for(stat)
        entries = matrix.compute(stat, ["d2"], plan, **options).where("value is not null").count()
        out.append((name, seq.select("seq_id").distinct().count(), stat.count(), plan, entries))
    return spark.createDataFrame(out, "carrier string, sequences bigint, rows bigint, strategy string, entries bigint")


def local_spaced_agreement(seq: DataFrame, pattern: str) -> float:
    """The largest difference between the spaced-word distances here and in one process, over pairs of both."""
    texts = {r.seq_id: r.residues for r in seq.toLocalIterator()}
    here = {(r.i, r.j): r.value for r in spaced.distance(seq, [pattern]).toLocalIterator()}
    there = baselines.local_spaced(texts, pattern)
    return float(np.max([abs((here[p] or 0.0) - (v or 0.0)) for p, v in there.items()] or [0.0]))
