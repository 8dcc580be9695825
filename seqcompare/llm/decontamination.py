"""Benchmark decontamination by spaced seeds, in DataFrame functions only.

A seed is the hash of the tokens at a mask's places within a span; the places left out may hold any token. Seeds of test
items and of documents are joined on their hash. Each hit fixes how item and document lie on each other; along that
diagonal the best-scoring run of tokens is found (a match counts 1, a substitution -2), and a document is contaminated by
an item where the run scores ``MIN_SCORE`` or more, or for a short item ``SHORT_SHARE`` of its tokens. Items of fewer tokens
than a span have one seed, of all their tokens, and match only whole.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

#: Places of a span of ten that count: two masks of six.
MASKS = ((0, 1, 3, 5, 6, 9), (0, 2, 3, 4, 7, 9))
SPAN = 10
MIN_SCORE = 10
#: Of an item's tokens: a run that scores so many is enough where the item is short.
SHORT_SHARE = 0.6
SUBSTITUTION = -2
#: Test seeds up to this many (16 bytes each, with ids) are broadcast; beyond, both sides are shuffled by seed.
MAX_BROADCAST_SEEDS = 2_000_000
#: So many hits (three numbers each) let only the documents that have one be shuffled; beyond, the semi-join is shuffled too.
MAX_BROADCAST_HITS = 500_000
_BREAKS = r"[^\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    """Hashes of the lower-cased runs of letters and digits."""
    return F.transform(F.array_remove(F.split(F.lower(text), _BREAKS), ""), lambda w: F.xxhash64(w))


def seeds(h: Column) -> Column:
    """Seeds of all masks: those of the first mask at places 0, 1, ..., then those of the next."""
    last = F.size(h) - SPAN

    def of(k: int, mask: tuple[int, ...]) -> Column:
        return F.transform(F.sequence(F.lit(0), last), lambda i: F.xxhash64(F.lit(k), *(F.get(h, i + o) for o in mask)))

    return F.when(last >= 0, F.concat(*(of(k, m) for k, m in enumerate(MASKS)))).otherwise(F.array().cast("array<bigint>"))


def whole_seeds(h: Column, size: int) -> Column:
    """Hashes of so many consecutive tokens, for items that are no longer."""
    starts = F.sequence(F.lit(0), F.size(h) - size)
    return F.when(F.size(h) >= size, F.transform(starts, lambda i: F.xxhash64(F.lit(-size), *(F.get(h, i + o) for o in range(size))))).otherwise(F.array().cast("array<bigint>"))


def short_seeded(rows: DataFrame, key: str, sizes: list[int], exact: bool) -> DataFrame:
    """(key, seed, at): seeds of whole short items; ``exact`` takes the items themselves, else all places of a text."""
    hashed = rows.where(F.col("text").isNotNull()).select(key, tokens(F.col("text")).alias("h"))
    parts = []
    for n in sizes:
        mine = hashed.where(F.size("h") == n) if exact else hashed
        parts.append(mine.select(key, F.posexplode_outer(whole_seeds(F.col("h"), n)).alias("at", "seed")).where(F.col("seed").isNotNull()).select(key, "seed", "at"))
    return reduce(DataFrame.unionByName, parts)


def seeded(rows: DataFrame, key: str) -> DataFrame:
    """(key, seed, at) for every seed of every text."""
    hashed = rows.where(F.col("text").isNotNull()).select(key, tokens(F.col("text")).alias("h"))
    made = hashed.select(key, F.size("h").alias("many"), seeds(F.col("h")).alias("seeds"))
    # the outer form: the optimizer would push a filter on the plain form's array below all projections, and work it out there again
    each = made.select(key, "many", F.posexplode_outer("seeds").alias("place", "seed")).where(F.col("seed").isNotNull())
    return each.select(key, "seed", F.pmod("place", F.col("many") - SPAN + 1).alias("at"))


def _best_run(shift: Column) -> Column:
    """The best run on the diagonal: its score and matches, and the first and last of its tokens in the document."""
    low = F.greatest(F.lit(0), -shift)
    many = F.least(F.size("item"), F.size("h") - shift) - low
    pairs = F.zip_with(F.slice("h", shift + low + 1, many), F.slice("item", low + 1, many), lambda a, b: a == b)
    names = ("now", "start", "same", "best", "matched", "first", "last")
    zero = F.struct((shift + low).alias("at"), *(F.lit(0).alias(n) for n in names))

    def step(s: Column, same: Column) -> Column:
        now = F.greatest(s.now + F.when(same, 1).otherwise(SUBSTITUTION), F.lit(0))
        count = F.when(s.now == 0, 0).otherwise(s.same) + same.cast("int")
        start = F.when(s.now == 0, s.at).otherwise(s.start)
        new = (now, start, count)
        kept = F.when(now > s.best, F.struct(now.alias("best"), count.alias("matched"), start.alias("first"), s.at.alias("last"))).otherwise(F.struct(s.best.alias("best"), s.matched.alias("matched"), s.first.alias("first"), s.last.alias("last")))
        return F.struct((s.at + 1).alias("at"), *(c.alias(n) for c, n in zip(new, names, strict=False)), *(kept[n].alias(n) for n in names[3:]))

    return F.aggregate(pairs, zero, step, lambda s: F.struct(s.best.alias("score"), s.matched.alias("matched"), s.first.alias("first_token"), s.last.alias("last_token")))


def overlaps(docs: DataFrame, benchmark: DataFrame, min_score: int = MIN_SCORE) -> DataFrame:
    """doc_id, item_id, score, matched, first_token, last_token: the best overlap of each contaminated document and item.

    Tokens are numbered from 0 in the document. Null and empty texts match nothing; nor do rows without an id. An item of fewer
    tokens than a span is found where a document has all of it. Of rows that share an id, the best overlap counts. Ties go to the later place.
    Other columns of either table are not read. An empty table on either side gives no rows.
    """
    docs, benchmark = docs.where(F.col("doc_id").isNotNull()), benchmark.where(F.col("item_id").isNotNull())
    items = seeded(benchmark, "item_id").withColumnRenamed("at", "item_at")
    side = F.broadcast(items) if items.count() <= MAX_BROADCAST_SEEDS else items
    short = [r[0] for r in benchmark.select(F.size(tokens(F.col("text"))).alias("n")).where(F.col("n").between(1, SPAN - 1)).distinct().orderBy("n").collect()]
    hits = seeded(docs, "doc_id").join(side, "seed")
    if short:  # at most SPAN - 1 sizes
        brief = short_seeded(benchmark, "item_id", short, exact=True).withColumnRenamed("at", "item_at")
        hits = hits.unionByName(short_seeded(docs, "doc_id", short, exact=False).join(brief, "seed").select(hits.columns))
    met = hits.groupBy("doc_id", "item_id", (F.col("at") - F.col("item_at")).alias("shift")).agg(F.count("*").alias("hits"))
    met = written(met.select("doc_id", "item_id", "shift"), "seed-hits")
    whole = benchmark.select("item_id", tokens(F.col("text")).alias("item"))
    asked = met.join(whole, "item_id")
    few = met.count() <= MAX_BROADCAST_HITS
    laid = docs.join(F.broadcast(met.select("doc_id").distinct()) if few else met.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", tokens(F.col("text")).alias("h"))
    run = _best_run(F.col("shift"))
    needed = F.least(F.lit(min_score), F.ceil(F.size("item") * SHORT_SHARE).cast("int"))
    needed = F.when(F.size("item") < SPAN, F.size("item")).otherwise(needed)
    best = asked.join(laid, "doc_id").select("doc_id", "item_id", needed.alias("needed"), run.alias("best")).where("best.score >= needed")
    return best.groupBy("doc_id", "item_id").agg(F.max("best").alias("best")).select("doc_id", "item_id", "best.*")


def clean(docs: DataFrame, benchmark: DataFrame, min_score: int = MIN_SCORE) -> DataFrame:
    """The rows of docs that no item contaminates, as they are. Rows without a doc_id stay."""
    dirty = written(overlaps(docs, benchmark, min_score).select("doc_id").distinct(), "contaminated")
    side = F.broadcast(dirty) if dirty.count() <= MAX_BROADCAST_HITS else dirty
    return docs.join(side, "doc_id", "left_anti").select(docs.columns)
