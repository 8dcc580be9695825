"""N-gram Jaccard join by chosen paths: pairs of documents whose sets of word shingles are similar enough.

A document's set stands embedded in a fixed number of coordinates, each the smallest shingle hash of one bin. A bucket is
a path of chosen coordinates and their values: at each level a document follows each coordinate with chance 1 / (threshold
* FOLLOW * coordinates), drawn from the path alone, so that two similar documents go on together in more than one expected
child.
Buckets of at most ``LIMIT`` documents are compared in full; larger ones are split again, down to ``LEVELS`` or until
splitting no longer parts them, and what stays large is compared in blocks. The runs that reach ``RECALL`` at the threshold
in buckets of the deepest level all go at once: the run is part of the path. A bucket's pairs are first judged by their coordinates, then verified exactly on the whole shingle sets; a pair
that shares several buckets counts in the smallest of them. Documents with equal sets are one class, never compared.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, batch, grams, mixed, packed, signed, starts_of, steps, tidy, unpacked, written
from .components import components

WORDS = 5
THRESHOLD = 0.8
RECALL = 0.999
COORDINATES = 64
#: The smaller, the more children two similar documents share at each level: 1 / FOLLOW at the threshold.
FOLLOW = 0.7
LIMIT = 256
LEVELS = 4
#: A large bucket that keeps this share of its parent's documents holds near copies: splitting it again would not part them.
TIGHT = 0.8
#: Documents of a block, where a leaf is compared in blocks.
BLOCK = 512
#: The texts of so many documents with likely partners are picked by a broadcast of ids (32 MB); beyond, texts are shuffled.
MAX_BROADCAST_IDS = 1_000_000
#: Coordinates that agree, less so much, still let a pair through to the exact comparison: four deviations.
SLACK = 4 * math.sqrt(0.8 * 0.2 / COORDINATES)
_EMPTY = np.uint32(0xFFFFFFFF)


def shingles(w: Words, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of each row's distinct shingles, ordered; a shorter text with words has one, made of all of them."""
    h = w.hashes()
    at = starts_of(w, words)
    row, hashed = w.row[at], grams(h, words)[at]
    short = np.flatnonzero((w.counts > 0) & (w.counts < words))
    if len(short):
        whole = [mixed(np.array([np.uint64(w.counts[r])]) ^ np.bitwise_xor.reduce(mixed(h[w.bounds[r] : w.bounds[r + 1]] + np.arange(w.counts[r], dtype=np.uint64))))[0] for r in short]
        row, hashed = np.concatenate([row, short]), np.concatenate([hashed, np.array(whole, np.uint64)])
    order = np.lexsort((hashed, row))
    row, hashed = row[order], hashed[order]
    first = np.ones(len(row), bool)
    first[1:] = (row[1:] != row[:-1]) | (hashed[1:] != hashed[:-1])
    return row[first], hashed[first]


def embedded(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, size, a, b, bins): the set's size, its 128-bit digest and its coordinates, for every row of docs."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            for lo, hi in steps(part):
                w = Words(part.column("text").slice(lo, hi - lo))
                row, h = shingles(w, words)
                size = np.bincount(row, minlength=w.rows)
                a, b = np.zeros(w.rows, np.uint64), np.zeros(w.rows, np.uint64)
                bins = np.full((w.rows, COORDINATES), _EMPTY, np.uint32)
                if len(row):
                    some = np.flatnonzero(size)
                    at = np.searchsorted(row, some)
                    a[some] = np.add.reduceat(mixed(h + np.uint64(11)), at)
                    b[some] = np.bitwise_xor.reduceat(mixed(h * np.uint64(0x9FB21C651E98DF25) + np.uint64(7)), at)
                    cell = row * COORDINATES + (h >> np.uint64(58)).astype(np.int64)
                    start = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))  # hashes ascend within a row, so within its bins
                    bins.reshape(-1)[cell[start]] = (mixed(h[start]) >> np.uint64(33)).astype(np.uint32)
                yield batch(doc_id=part.column("doc_id").slice(lo, hi - lo), size=size.astype(np.int32), a=signed(a), b=signed(b), bins=pa.array([r.tobytes() for r in bins], pa.binary()))

    return docs.select("doc_id", "text").mapInArrow(tidy(step), "doc_id bigint, size int, a bigint, b bigint, bins binary")


def _chosen(path: np.ndarray, bins: np.ndarray, chance: float) -> tuple[np.ndarray, np.ndarray]:
    """(which document, child path) for documents' coordinates on their paths."""
    draw = mixed(path[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(1, COORDINATES + 1, dtype=np.uint64)[None, :])
    who, at = np.nonzero((draw < np.uint64(int(chance * 2**64))) & (bins != _EMPTY))
    return who, mixed(draw[who, at] ^ mixed(bins[who, at].astype(np.uint64) + np.uint64(1)))


def _chance(threshold: float, many: int) -> float:
    return min(1 - 2**-30, 1 / (threshold * FOLLOW * many))


def _root(run: int) -> np.uint64:
    return mixed(np.array([run + 1], np.uint64))[0]


def runs_for(recall: float, threshold: float = THRESHOLD, levels: int = LEVELS) -> int:
    """Runs in which a pair at the threshold meets in a bucket of the deepest level with chance ``recall`` or more.

    Fewer pairs stay together the deeper a bucket is. Which coordinates the root follows is the same for all documents, so
    these are counted as drawn; the chances below it are means over the number of coordinates that agree.
    """
    agree = np.arange(COORDINATES + 1)
    weight = np.array([math.comb(COORDINATES, int(k)) * threshold**k * (1 - threshold) ** (COORDINATES - k) for k in agree.tolist()])
    chance, lives = _chance(threshold, COORDINATES), np.ones(COORDINATES + 1)
    for _ in range(levels - 1):
        lives = 1 - (1 - chance * lives) ** agree
    missed, runs, any_bin = np.ones(COORDINATES + 1), 0, np.zeros((1, COORDINATES), np.uint32)
    while not runs or (weight * missed).sum() > 1 - recall:
        followed = len(_chosen(np.array([_root(runs)]), any_bin, chance)[0])
        missed = missed * (1 - agree / COORDINATES * lives) ** followed
        runs += 1
    return runs


def _descend(rows: DataFrame, threshold: float, runs: int | None) -> DataFrame:
    """(doc_id, path, above): children of rows (doc_id, bins, path, n), of the root in each run where ``runs`` is given.

    ``above`` is the parent's number of documents.
    """

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, len(b), 2000):
                part = b.slice(lo, 2000)
                ids = part.column("doc_id").to_numpy(zero_copy_only=False)
                bins = np.frombuffer(b"".join(part.column("bins").to_pylist()), np.uint32).reshape(-1, COORDINATES)
                filled = (bins != _EMPTY).sum(1)
                above = np.full(len(part), np.iinfo(np.int32).max, np.int32) if runs else part.column("n").to_numpy(zero_copy_only=False)
                paths = [np.full(len(part), _root(k)) for k in range(runs)] if runs else [part.column("path").to_numpy(zero_copy_only=False).view(np.uint64)]
                for path in paths:
                    # short sets fill few coordinates; each of these is then followed more often
                    for many in np.unique(filled):
                        mine = np.flatnonzero(filled == many)
                        if many:
                            who, child = _chosen(path[mine], bins[mine], _chance(threshold, many))
                            yield batch(doc_id=ids[mine][who], path=signed(child), above=above[mine][who])

    return rows.mapInArrow(tidy(step), "doc_id bigint, path bigint, above int")


def buckets(reps: DataFrame, threshold: float, recall: float, limit: int, levels: int) -> DataFrame:
    """(path, doc_id, n): leaves with more than one document, n their number of documents."""
    leaves, front = [], reps.select("doc_id", "bins")
    for level in range(levels):
        rows = written(_descend(front, threshold, runs_for(recall, threshold, levels) if not level else None).distinct(), f"paths-{level}")
        counts = rows.groupBy("path").agg(F.count("*").cast("int").alias("n"), F.max("above").alias("above")).where("n > 1")
        stays = F.lit(True) if level == levels - 1 else (F.col("n") <= limit) | (F.col("n") >= TIGHT * F.col("above"))
        counts = written(counts.select("path", "n", stays.alias("stays")), f"path-counts-{level}")
        leaves.append(rows.select("path", "doc_id").join(counts.where("stays").select("path", "n"), "path"))
        split = counts.where("not stays").select("path", "n")
        if level == levels - 1 or split.limit(1).count() == 0:
            break
        front = rows.select("path", "doc_id").join(split, "path").join(reps.select("doc_id", "bins"), "doc_id")
    out = leaves[0]
    for more in leaves[1:]:
        out = out.unionByName(more)
    return out.select("path", "doc_id", "n")


def in_blocks(leaves: DataFrame, limit: int) -> DataFrame:
    """Leaf rows with the pair of blocks (i <= j) they are compared in; a leaf within the limit is one block."""
    blocks = F.ceil(F.col("n") / limit).cast("int")
    own = F.pmod(F.xxhash64("doc_id", "path"), blocks).cast("int")
    split = leaves.withColumns({"blocks": blocks, "own": own})
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    return split.select("path", "doc_id", "own", other).select("path", "doc_id", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))


def _first_shared(leaves: np.ndarray, bounds: np.ndarray, path: int) -> np.ndarray:
    """Whether ``path`` is the smallest leaf that two documents share, for all pairs."""
    n = len(bounds) - 1
    earlier = leaves < path
    who = np.repeat(np.arange(n), np.diff(bounds))[earlier]
    if not len(who):
        return np.ones((n, n), bool)
    kinds, at = np.unique(leaves[earlier], return_inverse=True)
    met = np.zeros((n, n), bool)
    order = np.argsort(at, kind="stable")
    at, who = at[order], who[order]
    for lo in range(0, len(kinds), 2048):
        a, b = np.searchsorted(at, (lo, lo + 2048))
        sets = np.zeros((n, min(2048, len(kinds) - lo)), np.float32)
        sets[who[a:b], at[a:b] - lo] = 1
        met |= sets @ sets.T > 0
    return ~met


def _likely(bins: np.ndarray, least: float) -> np.ndarray:
    out = np.zeros((len(bins), len(bins)), bool)
    full = bins != _EMPTY
    for i in range(len(bins)):
        either = (full[i] | full[i + 1 :]).sum(1)
        same = ((bins[i] == bins[i + 1 :]) & full[i]).sum(1)
        # a set of few bins says less, so it is always compared
        out[i, i + 1 :] = (same >= least * either) | (either < COORDINATES // 2)
    return out


def _pairs_of(own: np.ndarray, i: int, j: int) -> np.ndarray:
    """Pairs that belong to the pair of blocks: within a block only where it is paired with itself."""
    return np.ones((len(own), len(own)), bool) if i == j else own[:, None] != own[None, :]


def candidates(leaves: DataFrame, reps: DataFrame, threshold: float, limit: int) -> DataFrame:
    """(path, i, j, doc_id, own, leaves): leaf rows that share a likely pair."""
    bins = leaves.groupBy("doc_id").agg(F.sort_array(F.collect_set("path")).alias("leaves")).join(reps.select("doc_id", "bins"), "doc_id")
    rows = in_blocks(leaves, max(limit, BLOCK)).join(bins, "doc_id")

    def compare(key: tuple, group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        path, i, j = (k.as_py() for k in key)
        own = group.column("own").to_numpy()
        lists = group.column("leaves").combine_chunks()
        bounds = lists.offsets.to_numpy() - lists.offsets[0].as_py()
        sets = np.frombuffer(b"".join(group.column("bins").to_pylist()), np.uint32).reshape(-1, COORDINATES)
        pairs = _likely(sets, threshold - SLACK) & _first_shared(lists.flatten().to_numpy(), bounds, path) & _pairs_of(own, i, j)
        some = np.flatnonzero(pairs.any(0) | pairs.any(1))
        kept = group.take(some)
        return pa.table([kept.column("path"), kept.column("i"), kept.column("j"), kept.column("doc_id"), kept.column("own"), kept.column("leaves").cast(pa.list_(pa.int64()))], names=["path", "i", "j", "doc_id", "own", "leaves"])

    return rows.groupBy("path", "i", "j").applyInArrow(compare, "path bigint, i int, j int, doc_id bigint, own int, leaves array<bigint>")


def _roots(near: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """The least id that each document's links lead to, within the group."""
    root, top = ids.copy(), np.iinfo(np.int64).max
    while True:
        low = np.minimum(root, np.where(near, root[None, :], top).min(1))
        if (low == root).all():
            return root
        root = low


def links(docs: DataFrame, reps: DataFrame, found: DataFrame, threshold: float, words: int) -> DataFrame:
    """(doc_id, other, links, copies): verified links of each representative in one bucket, and the least id they lead to.

    ``links`` counts linked representatives, ``copies`` the documents of their classes.
    """
    wanted = written(found.select("doc_id").distinct().join(reps.select("doc_id", "a"), "doc_id"), "wanted")
    few = wanted.count() <= MAX_BROADCAST_IDS

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, len(b), 100):
                part = b.slice(lo, 100)
                row, h = shingles(Words(part.column("text") if few else unpacked(part.column("z"))), words)
                bounds = np.searchsorted(row, np.arange(len(part) + 1))
                held = [h[bounds[k] : bounds[k + 1]] for k in range(len(part))]
                a = signed(np.array([np.add.reduce(mixed(x + np.uint64(11))) for x in held], np.uint64))
                same = pa.array(a == part.column("a").to_numpy(zero_copy_only=False))  # of rows that share an id, the one that stands for a class
                rows = batch(doc_id=part.column("doc_id"), shingles=pa.array([x.tobytes() for x in held], pa.binary()))
                yield rows.filter(same)

    if few:
        texts = docs.join(F.broadcast(wanted), "doc_id").select("doc_id", "a", "text")
    else:
        texts = packed(docs, "doc_id").join(wanted, "doc_id").select("doc_id", "a", "z")
    whole = written(texts.mapInArrow(tidy(sets), "doc_id bigint, shingles binary"), "shingles")
    rows = found.join(whole, "doc_id").join(reps.select("doc_id", "members"), "doc_id")

    def verify(key: tuple, group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        group = group.take(np.unique(group.column("doc_id").to_numpy(), return_index=True)[1])  # repeated rows of docs
        path, i, j = (k.as_py() for k in key)
        ids, own, members = (group.column(c).to_numpy() for c in ("doc_id", "own", "members"))
        lists = group.column("leaves").combine_chunks()
        bounds = lists.offsets.to_numpy() - lists.offsets[0].as_py()
        held = [np.frombuffer(x, np.uint64) for x in group.column("shingles").to_pylist()]
        size = np.array([len(x) for x in held])
        kinds, at, times = np.unique(np.concatenate(held), return_inverse=True, return_counts=True)
        who = np.repeat(np.arange(len(held)), size)
        shared = times[at] > 1  # only shingles of two or more sets can be in common
        kept, at = np.unique(at[shared], return_inverse=True)
        who = who[shared]
        common = np.zeros((len(held), len(held)), np.float32)
        order = np.argsort(at, kind="stable")
        at, who = at[order], who[order]
        for lo in range(0, len(kept), 2048):
            a, b = np.searchsorted(at, (lo, lo + 2048))
            part = np.zeros((len(held), min(2048, len(kept) - lo)), np.float32)
            part[who[a:b], at[a:b] - lo] = 1
            common += part @ part.T
        near = common >= threshold * (size[:, None] + size[None, :] - common) - 1e-6
        near &= _first_shared(lists.flatten().to_numpy(), bounds, path) & _pairs_of(own, i, j)
        np.fill_diagonal(near, False)
        root = _roots(near, ids)
        some = np.flatnonzero(near.any(1))
        return pa.table({"doc_id": ids[some], "other": root[some], "links": near[some].sum(1).astype(np.int64), "copies": (near[some] @ members).astype(np.int64)})

    return rows.groupBy("path", "i", "j").applyInArrow(verify, "doc_id bigint, other bigint, links bigint, copies bigint")


def joined(docs: DataFrame, threshold: float = THRESHOLD, words: int = WORDS, recall: float = RECALL, limit: int = LIMIT, levels: int = LEVELS) -> DataFrame:
    """doc_id, rep_id, class_id, n_links for every row of docs.

    rep_id is the smallest doc_id with an equal set of shingles, class_id the smallest that links lead to, and n_links the
    number of other rows with a similarity of ``threshold`` or more, copies included. Texts of fewer words than a shingle
    have one shingle, of all their words. A null or empty text is like no other, nor like another empty one: it is its own
    class without links. A row with a null doc_id has a null class and no links. A repeated row is a copy of its like.
    """
    sets = written(embedded(docs, words), "sets")
    real = sets.where("size > 0 and doc_id is not null")
    classes = real.groupBy("a", "b").agg(F.min("doc_id").alias("rep_id"), F.count("*").alias("members"))
    member = sets.select("doc_id", "size", "a", "b").join(classes, ["a", "b"], "left")
    own = real.join(classes.withColumnRenamed("rep_id", "doc_id"), ["a", "b", "doc_id"]).dropDuplicates(["doc_id"])
    reps = written(own.select("doc_id", "a", "bins", "members"), "set-classes")
    leaves = written(buckets(reps, threshold, recall, limit, levels), "leaves")
    found = written(candidates(leaves, reps, threshold, limit), "likely")
    near = written(links(docs.where(F.col("doc_id").isNotNull()), reps, found, threshold, words), "links")
    roots = components(near.select("doc_id", "other"))
    counts = near.groupBy("doc_id").agg(F.sum("copies").alias("copies"))
    of_rep = reps.select(F.col("doc_id").alias("rep_id")).join(counts.withColumnRenamed("doc_id", "rep_id"), "rep_id", "left").join(roots.withColumnRenamed("doc_id", "rep_id"), "rep_id", "left")
    joined = member.join(of_rep, "rep_id", "left")
    rep = F.when(F.col("size") > 0, F.col("rep_id"))
    return joined.select(
        "doc_id",
        F.coalesce(F.when(F.col("doc_id").isNotNull(), rep), "doc_id").alias("rep_id"),
        F.when(F.col("doc_id").isNotNull(), F.coalesce("root", rep, "doc_id")).alias("class_id"),
        F.when(F.col("doc_id").isNotNull() & (F.col("size") > 0), F.coalesce("copies", F.lit(0)) + F.col("members") - 1).otherwise(0).alias("n_links"),
    )


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that stand first in their class, with all their columns; of rows that share an id, one.

    Rows without an id stay.
    """
    groups = written(joined(docs, **options).select("doc_id", "class_id"), "groups")
    gone = groups.where("doc_id != class_id").select("doc_id").distinct()
    side = F.broadcast(gone) if gone.count() <= MAX_BROADCAST_IDS else gone
    kept = docs.join(side, "doc_id", "left_anti").select(docs.columns)
    again = groups.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    if again.limit(1).count() == 0:
        return kept
    again = written(again, "repeated-ids")
    return kept.join(again, "doc_id", "left_anti").select(docs.columns).unionByName(kept.join(again, "doc_id", "left_semi").select(docs.columns).dropDuplicates(["doc_id"]))
