"""All-pairs evaluation under interchangeable plans that give the same matrix (fn, i, j, value), i < j.

``none``: every shared feature of a pair is a row of a self-join, summed in each task before the last shuffle.
``binned``: features are dealt into bins, and each bin's partial values are worked out together by numpy, pairs of blocks of
sequences at a time where there are many.
``postings``: a feature's sequences as one list, its pairs made inside the row.
``blocks``: the self-join tiled over blocks of sequences, for very many.
``total``: everything in one task, for small statistics only.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.library import PairFunction, Side, classes, get
from ..operators.stats import class_histogram

#: Statistics of more rows don't go through one task.
MAX_TOTAL_ROWS = 2_000_000
#: A feature in more sequences isn't made a list.
MAX_POSTING = 20_000
#: Sequences of a block, where pairs are dealt out by blocks.
TILE = 512
#: Pairs of sequences whose values are held in dense arrays; beyond, only pairs that are met are held.
MAX_DENSE = 1 << 21


def _held(df: DataFrame, whole: bool) -> DataFrame:
    """A row for each sequence: broadcast where the result has a row for each pair, so that it is the square root of that;
    with chosen pairs only, or keys that multiply the rows, the join is left to the optimizer."""
    return F.broadcast(df) if whole else df


def totals(stat: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    v = F.col("value").cast("double")
    return stat.groupBy(*keys, "seq_id").agg(
        F.sum(v).alias("total"), F.count("*").alias("distinct"), F.sum(v * v).alias("sumsq"), F.sum(F.sqrt(v)).alias("sumsqrt"), F.sum(v * v * v).alias("sumcube"),
        F.sum(F.log(v + 1)).alias("sumlog"), F.sum(v * F.log(v + 1)).alias("sumxlog"),
    )


def with_shares(stat: DataFrame, marg: DataFrame, keys: tuple[str, ...], whole: bool = True, back: DataFrame | None = None, alphabet: str = "") -> DataFrame:
    """Values as doubles, their share of the sequence's total, and with ``back`` (symbol shares) what is expected of them."""
    own = marg.select(*keys, "seq_id", "total")
    e = F.lit(0.0)
    if back is not None:
        own = own.join(back, [*keys, "seq_id"])
        count = {s: F.length("feature") - F.length(F.replace("feature", F.lit(s))) for s in alphabet}
        e = reduce(lambda x, s: x * F.pow(F.col(f"share_{s}"), count[s]), alphabet, F.col("total").cast("double"))
    joined = stat.join(_held(own, whole), [*keys, "seq_id"])
    return joined.select(*keys, "seq_id", "feature", F.col("value").cast("double").alias("v"), (F.col("value") / F.col("total")).alias("p"), e.alias("e"))


def _all_terms(functions: list[PairFunction], x: Column, y: Column, p: Column, q: Column, e: Column, f: Column) -> dict[str, tuple[str, Column]]:
    out: dict[str, tuple[str, Column]] = {}
    for fn in functions:
        for name, c in fn.terms(x, y, p, q, e, f).items():
            out[f"{fn.reduce}_{name}"] = (fn.reduce, c)
    return out


def _shared_terms(functions: list[PairFunction]) -> dict[str, tuple[str, Column]]:
    return _all_terms(functions, *(F.col(c) for c in "xypqef"))


def _reduced(terms: dict[str, tuple[str, Column]]) -> list[Column]:
    return [(F.sum if how == "sum" else F.max)(c).alias(name) for name, (how, c) in terms.items()]


def shared_pairs(rows: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(keys, feature, i, j, x, y, p, q, e, f): the self-join on the feature."""
    a = rows.select(*keys, "feature", F.col("seq_id").alias("i"), F.col("v").alias("x"), "p", "e")
    b = rows.select(*keys, "feature", F.col("seq_id").alias("j"), F.col("v").alias("y"), F.col("p").alias("q"), F.col("e").alias("f"))
    return a.join(b, [*keys, "feature"]).where("i < j")


def partial_none(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...] = (), **_) -> DataFrame:
    return shared_pairs(rows, keys).groupBy(*keys, "i", "j").agg(*_reduced(_shared_terms(functions)))


def _tiled(rows: DataFrame, blocks: int) -> DataFrame:
    """Each row goes to the tiles (r, c) of its block's row or column; ``own`` is its block."""
    own = F.pmod(F.xxhash64("seq_id"), F.lit(blocks)).cast("int")
    every = F.sequence(F.lit(0), F.lit(blocks - 1))
    each = rows.withColumn("own", own).select("*", F.explode(F.transform(every, lambda o: F.struct(F.least("own", o).alias("r"), F.greatest("own", o).alias("c")))).alias("tile"))
    return each.select(*rows.columns, "own", "tile.r", "tile.c")


def partial_blocks(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...] = (), blocks: int = 4, **_) -> DataFrame:
    """No join key holds more than two blocks' sequences."""
    tiled = _tiled(rows, blocks)
    a = tiled.select(*keys, "feature", "r", "c", F.col("own").alias("own_a"), F.col("seq_id").alias("i"), F.col("v").alias("x"), "p", "e")
    b = tiled.select(*keys, "feature", "r", "c", F.col("own").alias("own_b"), F.col("seq_id").alias("j"), F.col("v").alias("y"), F.col("p").alias("q"), F.col("e").alias("f"))
    pairs = a.join(b, [*keys, "feature", "r", "c"]).where("i < j and least(own_a, own_b) = r and greatest(own_a, own_b) = c")
    return pairs.groupBy(*keys, "i", "j").agg(*_reduced(_shared_terms(functions)))


def partial_postings(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...] = (), **_) -> DataFrame:
    lists = rows.groupBy(*keys, "feature").agg(F.sort_array(F.collect_list(F.struct("seq_id", "v", "p", "e"))).alias("l"), F.count("*").alias("df"))
    lists = lists.where(F.when(F.col("df") > MAX_POSTING, F.raise_error(F.lit("a feature is in too many sequences for lists: use binned"))).otherwise(F.lit(True)).isNotNull())
    pair = lambda a, b: F.struct(a.seq_id.alias("i"), b.seq_id.alias("j"), a.v.alias("x"), b.v.alias("y"), a.p.alias("p"), b.p.alias("q"), a.e.alias("e"), b.e.alias("f"))
    pairs = F.flatten(F.transform("l", lambda a, k: F.transform(F.slice("l", k + 2, F.size("l")), lambda b: pair(a, b))))
    each = lists.select(*keys, F.explode_outer(pairs).alias("r")).where("r is not null").select(*keys, "r.*")
    return each.groupBy(*keys, "i", "j").agg(*_reduced(_shared_terms(functions)))


class _Sums:
    """Reduced terms by pair of sequences: dense arrays for few, and for many the pairs that were met."""

    def __init__(self, n: int):
        self.n, self.dense = n, n * n <= MAX_DENSE
        self.seen, self.held = (np.zeros(n * n, bool), {}) if self.dense else (np.zeros(0, np.int64), {})

    def add(self, cell: np.ndarray, terms: dict[str, np.ndarray]) -> None:
        if self.dense:
            self.seen[cell] = True
        else:
            kinds, cell = np.unique(cell, return_inverse=True)
            both = np.union1d(self.seen, kinds)
            old, cell = np.searchsorted(both, self.seen), np.searchsorted(both, kinds)[cell]
            for k, x in self.held.items():
                self.held[k] = np.zeros(len(both))
                self.held[k][old] = x
            self.seen = both
        many = len(self.seen)
        for k, t in terms.items():
            held = self.held.setdefault(k, np.zeros(many))
            if k.startswith("sum_"):
                held += np.bincount(cell, t, many)
            else:
                np.maximum.at(held, cell, t)

    def found(self) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
        cell = np.flatnonzero(self.seen) if self.dense else self.seen
        return cell // self.n, cell % self.n, {k: x[cell] if self.dense else x for k, x in self.held.items()}


def _block_values(ids: np.ndarray, feature: np.ndarray, columns: tuple[np.ndarray, ...], functions: list[PairFunction], own: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """Reduced terms of all pairs that share a feature of a batch of rows; with ``own`` (blocks) only those of two blocks."""
    names, at = np.unique(ids, return_inverse=True)
    feature = np.unique(feature, return_inverse=True)[1]
    order = np.lexsort((at, feature))
    at, feature = at[order], feature[order]
    v, p, e = (c[order] for c in columns)
    block = own[order] if own is not None else None
    starts = np.flatnonzero(np.append(True, feature[1:] != feature[:-1]))
    sizes = np.diff(np.append(starts, len(feature)))
    sums = _Sums(len(names))
    for size in np.unique(sizes[sizes > 1]):  # features of equally many sequences at a time
        r, c = np.triu_indices(size, 1)
        step = max(1, 1_000_000 // len(r))
        mine = starts[sizes == size]
        for lo in range(0, len(mine), step):
            a = (mine[lo : lo + step, None] + r).ravel()
            b = (mine[lo : lo + step, None] + c).ravel()
            if block is not None:
                apart = block[a] != block[b]
                a, b = a[apart], b[apart]
            terms = {f"{f.reduce}_{name}": t for f in functions for name, t in f.numpy_terms(v[a], v[b], p[a], p[b], e[a], e[b]).items()}
            sums.add(at[a] * len(names) + at[b], terms)
    i, j, values = sums.found()
    return names[i], names[j], values


def _grouped(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...], group: list[str], tiles: bool = False) -> DataFrame:
    names = list(_all_terms(functions, *(F.lit(1.0) for _ in range(6))))
    kinds = {f.name: f.dataType for f in rows.schema}

    def work(table: pa.Table) -> pa.Table:
        between = tiles and table.column("r")[0].as_py() != table.column("c")[0].as_py()
        own = table.column("own").to_numpy() if between else None
        i, j, values = _block_values(*(table.column(c).to_numpy() for c in ("seq_id", "feature")), tuple(table.column(c).to_numpy() for c in ("v", "p", "e")), functions, own)
        key = {k: pa.array([table.column(k)[0].as_py()] * len(i), table.schema.field(k).type) for k in keys}
        return pa.table({**key, "i": pa.array(i, pa.string()), "j": pa.array(j, pa.string()), **{k: pa.array(values.get(k, np.zeros(len(i))), pa.float64()) for k in names}})

    schema = ", ".join([f"`{k}` {kinds[k].simpleString()}" for k in keys] + ["i string", "j string"] + [f"`{n}` double" for n in names])
    return rows.groupBy(*keys, *group).applyInArrow(work, schema)


def partial_binned(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...] = (), bins: int | None = None, blocks: int = 1, **_) -> DataFrame:
    """Rows of a bin, and with ``blocks`` of a pair of blocks of sequences, go to one step of numpy."""
    spark = rows.sparkSession
    bins = bins or max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = rows.withColumn("bin", F.pmod(F.xxhash64("feature"), F.lit(bins)).cast("int"))
    if blocks > 1:
        parts = _grouped(_tiled(dealt, blocks), functions, keys, ["bin", "r", "c"], tiles=True)
    else:
        parts = _grouped(dealt, functions, keys, ["bin"])
    again = [(F.max if n.startswith("max_") else F.sum)(n).alias(n) for n in parts.columns if n not in (*keys, "i", "j")]
    return parts.groupBy(*keys, "i", "j").agg(*again)


def partial_total(rows: DataFrame, functions: list[PairFunction], keys: tuple[str, ...] = (), **_) -> DataFrame:
    if rows.limit(MAX_TOTAL_ROWS + 1).count() > MAX_TOTAL_ROWS:
        raise ValueError("this statistic is too large for one task: use binned, none or blocks")
    return _grouped(rows.withColumn("one", F.lit(1)), functions, keys, ["one"])


STRATEGIES = {"none": partial_none, "binned": partial_binned, "postings": partial_postings, "blocks": partial_blocks, "total": partial_total}


def plan_for(stat: DataFrame) -> tuple[str, dict]:
    """One task for small statistics; bins where features are in many sequences on average, or one is in very many; else a row each.

    Blocks of sequences grow in number with the sequences that the commonest feature is in.
    """
    df = stat.groupBy("feature").agg(F.count("*").alias("df")).agg(F.sum("df"), F.max("df"), F.avg("df")).first()
    rows, top, mean = (float(x or 0) for x in df)
    if rows <= 20_000:
        return "total", {}
    blocks = max(1, -(-int(top) // TILE))
    if mean > 50 or top > 4 * TILE:
        return "binned", {"blocks": blocks if top > 4 * TILE else 1}
    return "none", {}


def choose(stat: DataFrame) -> str:
    return plan_for(stat)[0]


def grid(marg: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """All pairs of sequences, so that pairs which share no feature are in the matrix. Quadratic, as the result is."""
    a = marg.select(*keys, F.col("seq_id").alias("i"))
    b = marg.select(*keys, F.col("seq_id").alias("j"))
    return a.join(F.broadcast(b), list(keys)).where("i < j") if keys else a.join(F.broadcast(b), F.col("i") < F.col("j"))


def _sides(pairs: DataFrame, marg: DataFrame, keys: tuple[str, ...], whole: bool = True) -> DataFrame:
    columns = [c for c in marg.columns if c not in (*keys, "seq_id")]
    for side, name in (("a", "i"), ("b", "j")):
        own = marg.select(*keys, F.col("seq_id").alias(name), *(F.col(c).alias(f"{side}_{c}") for c in columns))
        pairs = pairs.join(_held(own, whole), [*keys, name])
    return pairs


def _alone(rows: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(keys, i, j, a_alone, b_alone): the largest value of each of a pair that the other lacks.

    Features are ranked by value within a sequence. The first rank that a pair doesn't share has the largest value that is
    alone. Shared ranks are bits of words of 62, put together in each task before the shuffle; then the first gap is looked for.
    """
    by_value = Window.partitionBy(*keys, "seq_id").orderBy(F.col("v").desc(), "feature")
    ranked = rows.select(*keys, "seq_id", "feature", "v", (F.row_number().over(by_value) - 1).alias("rank"))
    a = ranked.select(*keys, "feature", F.col("seq_id").alias("i"), F.col("rank").alias("ra"))
    b = ranked.select(*keys, "feature", F.col("seq_id").alias("j"), F.col("rank").alias("rb"))
    pairs = a.join(b, [*keys, "feature"]).where("i < j")
    pair = [*keys, "i", "j"]
    sides = F.explode(F.array(*(F.struct(F.lit(s).alias("side"), F.floor(F.col(r) / 62).cast("int").alias("word"), F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col(r) % 62).cast("int")).alias("bit")) for s, r in (("a", "ra"), ("b", "rb")))))
    bits = pairs.select(*pair, sides.alias("s")).groupBy(*pair, "s.side", "s.word").agg(F.bit_or("s.bit").alias("bits"))
    lists = bits.groupBy(*pair, "side").agg(F.sort_array(F.collect_list(F.struct("word", "bits"))).alias("words"))
    # words before the first that is missing or not full are full; in that one, the lowest bit that is not set
    full = F.lit((1 << 62) - 1)
    runs = F.aggregate("words", F.struct(F.lit(0).alias("at"), F.lit(0).cast("bigint").alias("bits"), F.lit(False).alias("done")), lambda s, w: F.when(s.done | (w.word != s.at), F.struct(s.at.alias("at"), s.bits.alias("bits"), F.lit(True).alias("done"))).when(w.bits == full, F.struct((s.at + 1).alias("at"), F.lit(0).cast("bigint").alias("bits"), F.lit(False).alias("done"))).otherwise(F.struct(s.at.alias("at"), w.bits.alias("bits"), F.lit(True).alias("done"))))
    clear = F.bitwise_not(F.col("run.bits"))
    low = F.bit_count(clear.bitwiseAND(-clear) - 1)
    found = lists.select(*pair, "side", runs.alias("run")).select(*pair, "side", (F.col("run.at") * 62 + low).cast("int").alias("rank"))
    wanted = found.select(*pair, "side", "rank", F.when(F.col("side") == "a", F.col("i")).otherwise(F.col("j")).alias("seq_id"))
    values = wanted.join(ranked.select(*keys, "seq_id", "rank", "v"), [*keys, "seq_id", "rank"], "left")
    return values.groupBy(*pair).agg(*(F.max(F.when(F.col("side") == s, F.col("v"))).alias(f"{s}_alone") for s in "ab"))


def symbol_shares(comp: DataFrame, alphabet: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, seq_id, share_A, ...) from rows of (seq_id, symbol, p)."""
    return comp.groupBy(*keys, "seq_id").agg(*(F.coalesce(F.sum(F.when(F.col("symbol") == s, F.col("p"))), F.lit(0.0)).alias(f"share_{s}") for s in alphabet))


def background_rest(stat: DataFrame, back: DataFrame, marg: DataFrame, functions: list[PairFunction], keys: tuple[str, ...], alphabet: str, k: int, blocks: int = 1) -> DataFrame:
    """(keys, i, j, <function>_rest): what all words add to a pair but for what shared ones add beyond being in one.

    Words of one composition have one expectation, so that a sequence is a list of (composition, value, words) and a vector
    of expectations. Pairs of blocks of sequences meet in one step of numpy.
    """
    kinds = classes(alphabet, k)
    times = np.array([[kind.count(s) for s in alphabet] for kind, _ in kinds])
    words = np.array([n for _, n in kinds], float)
    place = {kind: n for n, (kind, _) in enumerate(kinds)}
    hist = class_histogram(stat, keys).groupBy(*keys, "seq_id").agg(F.collect_list(F.struct("class", F.col("value").cast("double").alias("value"), "n_words")).alias("hist"))
    own = marg.select(*keys, "seq_id", F.col("total").cast("double").alias("total")).join(back, [*keys, "seq_id"]).join(hist, [*keys, "seq_id"], "left")
    each = _tiled(own, blocks)
    types = {f.name: f.dataType for f in each.schema}

    def work(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        names, block = table.column("seq_id").to_numpy(), table.column("own").to_numpy()
        r, c = table.column("r")[0].as_py(), table.column("c")[0].as_py()
        order = np.argsort(names)
        names, block = names[order], block[order]
        share = np.array([table.column(f"share_{s}").to_numpy() for s in alphabet]).T[order]
        expected = table.column("total").to_numpy()[order, None] * np.prod(share[:, None, :] ** times[None], axis=2)
        lists = [table.column("hist")[int(x)].as_py() or [] for x in order]
        own = [(np.array([place[h["class"]] for h in x], int), np.array([h["value"] for h in x]), np.array([h["n_words"] for h in x], float)) for x in lists]
        n, out = len(names), {f.name: np.zeros((len(names), len(names))) for f in functions}
        for i in range(n):
            kind, value, many = own[i]
            e, f = expected[i], expected
            for fn in functions:
                none = fn.gain(np.zeros(1), np.zeros(1), e[None, :], f)
                # of all words as if in neither, once for each pair; of the own ones what they add, for each of the two
                out[fn.name][i] += 0.5 * (none @ words)
                out[fn.name][:, i] += 0.5 * (none @ words)
                if len(kind):
                    alone = fn.gain(value[None, :], np.zeros(1), e[kind][None, :], f[:, kind]) - none[:, kind]
                    gained = alone @ many
                    out[fn.name][i] += gained
                    out[fn.name][:, i] += gained
        i, j = np.triu_indices(n, 1)
        if r != c:
            apart = block[i] != block[j]
            i, j = i[apart], j[apart]
        key = {x: pa.array([table.column(x)[0].as_py()] * len(i), table.schema.field(x).type) for x in keys}
        return pa.table({**key, "i": pa.array(names[i], pa.string()), "j": pa.array(names[j], pa.string()), **{f"{fn.name}_rest": out[fn.name][i, j] for fn in functions}})

    schema = ", ".join([f"`{x}` {types[x].simpleString()}" for x in keys] + ["i string", "j string"] + [f"{fn.name}_rest double" for fn in functions])
    return each.groupBy(*keys, "r", "c").applyInArrow(work, schema)


def compute(stat: DataFrame, functions: list[str | PairFunction], strategy: str = "auto", keys: tuple[str, ...] = (), comp: DataFrame | None = None, alphabet: str = "ACGT", k: int | None = None, only: DataFrame | None = None, **options) -> DataFrame:
    """The matrix of several functions in one pass: (keys, fn, i, j, value) for all pairs i < j, or those of ``only``.

    Functions with a background need ``k``, and ``comp`` unless it can be taken from the words themselves.
    """
    made = [f if isinstance(f, PairFunction) else get(f) for f in functions]
    if strategy == "auto":
        strategy, planned = plan_for(stat)
        options = {**planned, **options}
    marg = totals(stat, keys)
    whole = only is None and not keys
    with_background = [f for f in made if f.background]
    back = None
    if with_background:
        if k is None:
            raise ValueError("functions with a background need k")
        back = symbol_shares(comp if comp is not None else composition_of(stat, keys), alphabet, keys)
    rows = with_shares(stat, marg, keys, whole, back, alphabet)
    pair = [*keys, "i", "j"]
    if only is not None:  # sequences in no chosen pair meet nobody
        ends = only.select(*keys, F.col("i").alias("seq_id")).unionByName(only.select(*keys, F.col("j").alias("seq_id"))).distinct()
        rows = rows.join(ends, [*keys, "seq_id"], "left_semi")
    partial = STRATEGIES[strategy](rows, made, keys, **options)
    wide = _sides((only if only is not None else grid(marg, keys)).join(partial, pair, "left"), marg, keys, whole)
    wide = wide.fillna(0.0, [c for c in partial.columns if c not in pair])
    if any(f.extreme for f in made):
        top = rows.groupBy(*keys, "seq_id").agg(F.max("v").alias("top"))
        wide = _sides(wide.join(_alone(rows, keys).withColumn("met", F.lit(True)), pair, "left"), top, keys, whole)
        # a pair that shares no feature has no row there: all of both is alone
        alone = lambda s: F.when(F.col("met").isNull(), F.col(f"{s}_top")).otherwise(F.coalesce(f"{s}_alone", F.lit(0.0)))
        wide = wide.withColumns({f"{s}_alone": alone(s) for s in "ab"})
    if with_background:
        wide = wide.join(background_rest(stat, back, marg, with_background, keys, alphabet, k, options.get("blocks", 1) if strategy == "binned" else 1), pair, "left")
    a, b = Side("a"), Side("b")
    values = []
    for f in made:
        t = {n: F.col(f"{f.reduce}_{n}") for n in f.terms(*(F.lit(1.0) for _ in range(6)))}
        values.append(F.struct(F.lit(f.name).alias("fn"), f.finish(t, a, b).cast("double").alias("value")))
    return wide.select(*pair, F.explode(F.array(*values)).alias("r")).select(*keys, "r.fn", "i", "j", "r.value")


def composition_of(stat: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Symbol shares by the words' own symbols: (seq_id, symbol, p)."""
    each = stat.select(*keys, "seq_id", F.explode(F.split("feature", "")).alias("symbol"), "value").groupBy(*keys, "seq_id", "symbol").agg(F.sum("value").alias("n"))
    return each.withColumn("p", F.col("n") / F.sum("n").over(Window.partitionBy(*keys, "seq_id"))).drop("n")


def self_values(stat: DataFrame, function: str) -> DataFrame:
    """(seq_id, value): a function of each sequence with itself, for functions of shared terms and totals."""
    f, marg = get(function), totals(stat)
    rows = with_shares(stat, marg, ())
    terms = _all_terms([f], *(F.col(c) for c in "vvppee"))
    own = rows.groupBy(F.col("seq_id").alias("i"), F.col("seq_id").alias("j")).agg(*_reduced(terms))
    wide = _sides(own, marg, ())
    t = {n: F.col(f"{f.reduce}_{n}") for n in f.terms(*(F.lit(1.0) for _ in range(6)))}
    return wide.select(F.col("i").alias("seq_id"), f.finish(t, Side("a"), Side("b")).alias("value"))


def mirror(mat: DataFrame, own: DataFrame) -> DataFrame:
    """The full square of one function: both triangles and the diagonal."""
    upper = mat.select("i", "j", "value")
    return upper.unionByName(upper.select(F.col("j").alias("i"), F.col("i").alias("j"), "value")).unionByName(own.select(F.col("seq_id").alias("i"), F.col("seq_id").alias("j"), "value"))


def to_wide(square: DataFrame, names: list[str]) -> DataFrame:
    return square.groupBy("i").pivot("j", names).agg(F.first("value"))


def to_distance(mat: DataFrame, mode: str = "max", own: DataFrame | None = None) -> DataFrame:
    """Similarities as distances: max less value, 1 - cosine of self values, or -ln of it."""
    if mode == "max":
        top = mat.groupBy("fn").agg(F.max("value").alias("top"))
        return mat.join(F.broadcast(top), "fn").withColumn("value", F.col("top") - F.col("value")).drop("top")
    a, b = own.select(F.col("seq_id").alias("i"), F.col("value").alias("ii")), own.select(F.col("seq_id").alias("j"), F.col("value").alias("jj"))
    share = F.col("value") / F.sqrt(F.col("ii") * F.col("jj"))
    value = 1 - share if mode == "cosine" else -F.log(share)
    return mat.join(F.broadcast(a), "i").join(F.broadcast(b), "j").withColumn("value", value).drop("ii", "jj")

