"""Monte Carlo tests of pairs and matrices against null values, with family-wise correction."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.library import REGISTRY, get
from ..plans import matrix, search
from ..stages import settled
from . import nullmodel, stats


def kind_of(fn: str, kinds: dict[str, str] | None = None) -> str:
    if kinds and fn in kinds:
        return kinds[fn]
    return {"minhash": "distance", "spaced": "distance"}.get(fn) or get(fn, **({"words": 1} if fn in ("d2z", "jeffrey") else {})).kind


def _distances(kinds: dict[str, str] | None) -> list[str]:
    return [f for f in {*REGISTRY, "minhash", "spaced", *(kinds or {})} if kind_of(f, kinds) == "distance"]


def null_matrix(seq: DataFrame, functions: list, k: int, q: int | tuple[int, ...], replicates: int, seed: int = 1, model: str = "bootstrap", strategy: str = "none", keys: tuple[str, ...] = (), only: DataFrame | None = None, alphabet: str = "ACGT", **options) -> DataFrame:
    """(keys, fn, replicate, i, j, value): the functions on every synthetic dataset, all replicates in one plan.

    With several q there is a column q, too, and all null models are in that plan. ``only`` (i, j): just these pairs are
    compared, and just their sequences made.
    """
    synthetic, inner = synthesised(seq, q, replicates, seed, model, keys, k - 1, only, **options)
    pairs = None
    if only is not None:
        copies = synthetic.select(*inner).distinct()
        pairs = only.join(copies, list(keys)) if keys else only.join(F.broadcast(copies), F.lit(True))
    out = matrix.compute(settled(stats.keyed_counts(synthetic, k, inner)), functions, strategy, keys=inner, k=k, alphabet=alphabet, only=pairs)
    return out.select(*inner, "fn", "i", "j", "value")


def synthesised(seq: DataFrame, q: int | tuple[int, ...], replicates: int, seed: int = 1, model: str = "bootstrap", keys: tuple[str, ...] = (), overlap: int = 0, only: DataFrame | None = None, **options) -> tuple[DataFrame, tuple[str, ...]]:
    """Synthetic sequences of one or several null models, and the columns that tell their datasets apart."""
    if model != "bootstrap":
        return nullmodel.generate(seq, model, replicates, seed, **options), (*keys, "replicate")
    ends = None
    if only is not None:
        ends = only.select(*keys, F.col("i").alias("seq_id")).unionByName(only.select(*keys, F.col("j").alias("seq_id"))).distinct()
    sizes = nullmodel.sized(seq, keys)
    made = [(n, nullmodel.bootstrap(seq, n, replicates, seed, keys=keys, overlap=overlap, only=ends, sizes=sizes)) for n in (q if isinstance(q, tuple) else (q,))]
    if not isinstance(q, tuple):
        return made[0][1], (*keys, "replicate")
    return reduce(DataFrame.unionByName, (df.withColumn("q", F.lit(n)) for n, df in made)), (*keys, "q", "replicate")


def pvalues(observed: DataFrame, nulls: DataFrame, replicates: int, kinds: dict[str, str] | None = None, plus_one: bool = False, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, fn, i, j, t, beaten, p): ``beaten`` null values are strictly less similar than the observed one, and p = 1 - beaten / replicates.

    An observed value of null has p = 1. A null value of null is as unrelated as can be. Keys that only the null values
    have (a null model) are tests of their own.
    """
    far = F.col("fn").isin(_distances(kinds))
    n, t = F.col("null_value"), F.col("t")
    beats = F.when(t.isNull(), False).when(far, F.coalesce(n, F.lit(float("inf"))) > t).otherwise(F.coalesce(n, F.lit(float("-inf"))) < t)
    mine = [k for k in keys if k in observed.columns]
    own = observed.select(*mine, "fn", "i", "j", F.col("value").alias("t"))
    theirs = nulls.select(*keys, "fn", "i", "j", F.col("value").alias("null_value"))
    joined = own.join(theirs, [*mine, "fn", "i", "j"], "left" if len(mine) == len(keys) else "inner")
    counted = joined.groupBy(*keys, "fn", "i", "j").agg(F.max("t").alias("t"), F.sum(beats.cast("bigint")).alias("beaten"))
    p = (replicates - F.col("beaten") + 1) / F.lit(replicates + 1.0) if plus_one else 1 - F.col("beaten") / F.lit(float(replicates))
    return counted.select(*keys, "fn", "i", "j", "t", "beaten", p.alias("p"))


def standardised(observed: DataFrame, nulls: DataFrame) -> DataFrame:
    """(fn, i, j, value): values less the mean of the pair's null values, over their deviation; 0 where these don't vary."""
    moments = nulls.groupBy("fn", "i", "j").agg(F.avg("value").alias("mean"), F.stddev_pop("value").alias("sd"))
    return observed.join(moments, ["fn", "i", "j"]).select("fn", "i", "j", F.when(F.col("sd") > 0, (F.col("value") - F.col("mean")) / F.col("sd")).otherwise(0.0).alias("value"))


def bonferroni(p: DataFrame, entries: int, alpha: float = 0.01) -> DataFrame:
    level = alpha / entries
    return p.select("*", F.lit(level).alias("level"), (F.col("p") <= level + 1e-15).alias("reject"))


def entries_of(seq: DataFrame) -> int:
    n = seq.select("seq_id").distinct().count()
    return max(1, n * (n - 1) // 2)


def matrix_test(seq: DataFrame, functions: list, k: int, q: int | tuple[int, ...], replicates: int = 100, alpha: float = 0.01, seed: int = 1, strategy: str = "none", plus_one: bool = False, alphabet: str = "ACGT", **options) -> DataFrame:
    """(fn, i, j, t, beaten, p, level, reject): every entry at alpha / entries. With several q, a test for each."""
    observed = matrix.compute(settled(stats.counts(seq, k)), functions, strategy, k=k, alphabet=alphabet)
    nulls = null_matrix(seq, functions, k, q, replicates, seed, strategy=strategy, alphabet=alphabet, **options)
    return bonferroni(pvalues(observed, nulls, replicates, plus_one=plus_one, keys=("q",) if isinstance(q, tuple) else ()), entries_of(seq), alpha)


def search_test(seq: DataFrame, asked: Column, functions: list, k: int, q: int, replicates: int = 100, alpha: float = 0.01, seed: int = 1) -> DataFrame:
    """(fn, i, j, t, beaten, p, level, reject): the test of every query i (where ``asked`` holds) against every other sequence.

    A task has both sequences of a pair in all synthetic datasets, so that null values are compared where they are made.
    The level is for all pairs that are tested, each counted once.
    """
    made = settled(nullmodel.bootstrap(seq, q, replicates, seed, overlap=k - 1))
    columns = ["copy", "seq_id", "part_id", "offset", "residues"]
    both = seq.withColumn("copy", F.lit(0)).select(columns).unionByName(made.withColumn("copy", (F.col("replicate") + 1).cast("int")).select(columns))
    count = lambda rows: stats.unkeyed(stats.KmerCount(k).extract(stats.keyed(rows, ("copy",))), ("copy",), both)
    found = search.values(count(both.where(asked)), count(both), functions, replicates + 1)
    tests = []
    for f in functions:
        t = F.col(f"{f}_0")
        beats = [F.col(f"{f}_{n}") > t if kind_of(f) == "distance" else F.col(f"{f}_{n}") < t for n in range(1, replicates + 1)]
        tests.append(F.struct(F.lit(f).alias("fn"), t.alias("t"), reduce(lambda a, b: a + b, (b.cast("bigint") for b in beats)).alias("beaten")))
    p = found.select("i", "j", F.explode(F.array(*tests)).alias("r")).select("r.fn", "i", "j", "r.t", "r.beaten", (1 - F.col("r.beaten") / F.lit(float(replicates))).alias("p"))
    n, many = (df.select("seq_id").distinct().count() for df in (seq, seq.where(asked)))
    return bonferroni(p, max(1, many * (n - 1) - many * (many - 1) // 2), alpha)


def pair_scope_test(seq: DataFrame, functions: list, k: int, q: int, pairs: DataFrame, replicates: int = 100, seed: int = 1) -> DataFrame:
    """(fn, i, j, t, beaten, p): the same with each pair's own q-mers as the source of its null values.

    ``pairs`` (i, j) are scopes: each takes its two sequences along, and all of them go through one plan.
    """
    scoped = pairs.select(F.concat_ws("|", "i", "j").alias("scope"), F.explode(F.array("i", "j")).alias("seq_id"))
    two = seq.join(scoped, "seq_id").select("scope", "seq_id", "part_id", "offset", "residues")
    observed = matrix.compute(stats.keyed_counts(two, k, ("scope",)), functions, "none", keys=("scope",), k=k)
    return pvalues(observed, null_matrix(two, functions, k, q, replicates, seed, keys=("scope",)), replicates, keys=("scope",)).drop("scope")


def early_stop(seq: DataFrame, functions: list, k: int, q: int, batches: int, each: int, alpha: float = 0.01, seed: int = 1) -> DataFrame:
    """Entries that still can pass after each batch of replicates: with fewer replicates than entries / alpha, a single
    null value that is not beaten fails an entry. The next batches make and compare only what is left."""
    observed = matrix.compute(stats.counts(seq, k), functions, "none", k=k)
    live, n = observed.select("fn", "i", "j", "value"), seq.select("seq_id").distinct().count()
    if batches * each >= n * (n - 1) / 2 / alpha:
        raise ValueError("so many replicates allow an entry to miss some: test all of them")
    for batch in range(batches):
        only = live.select("i", "j").distinct() if batch else None
        nulls = null_matrix(seq, functions, k, q, each, seed + batch, only=only)
        live = pvalues(live, nulls, each).where("p = 0").select("fn", "i", "j", F.col("t").alias("value"))
        live = settled(live)
    return live


def summary(sig: DataFrame, green: float = 0.75, keys: tuple[str, ...] = ("fn",)) -> DataFrame:
    """(keys, m, passed, share, class): green from ``green`` on, red where none passes, else yellow."""
    out = sig.groupBy(*keys).agg(F.count("*").alias("m"), F.sum(F.col("reject").cast("bigint")).alias("passed"))
    share = F.col("passed") / F.col("m")
    return out.select(*keys, "m", "passed", share.alias("share"), F.when(share >= green, "green").when(F.col("passed") == 0, "red").otherwise("yellow").alias("class"))


def in_range(summaries: DataFrame, least: float = 0.95) -> Column:
    return F.col("share") >= least


def consistent(summaries: DataFrame, share: float = 0.75) -> DataFrame:
    """(fn, min_share, consistent): functions whose share is high on all datasets and null models."""
    return summaries.groupBy("fn").agg(F.min("share").alias("min_share")).withColumn("consistent", F.col("min_share") >= share)


def resolution(entries: int, replicates: int, alpha: float = 0.01) -> dict:
    """The least p above zero, and whether an entry passes only by beating every null value."""
    return {"min_attainable_p": 1 / replicates, "needs_strict_max": replicates < entries / alpha}
