"""Filtered spaced-word distance: words matched at a pattern's 1 places, scored and filtered by their free symbols."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import windows
from ..operators.stats import SpacedWord

#: Words are dealt into so many buckets, or as many as a shuffle has partitions.
BUCKETS = 64
#: Windows that are coded at once.
SLICE = 1 << 19
#: Pairs of occurrences that are scored at once; where a word has more in two sequences, occurrences with equal symbols are one.
CELLS = 1 << 22
#: Pairs of sequences with a common word that are held at once.
RUNS = 1 << 20
#: Sizes that the numbers of occurrences are rounded up to, so that many words go through one step.
_LADDER = np.unique(np.round(1.4 ** np.arange(100)).astype(np.int64))
Scores = dict[tuple[str, str], int]


def scored(free_i: Column, free_j: Column, places: int, match: int, mismatch: int, scores: Scores | None) -> tuple[Column, Column]:
    """Score of the free symbols, and how many differ. ``scores`` has the score of a pair of symbols, either way round;
    pairs that it lacks score ``match`` or ``mismatch``."""
    at = [(F.substring(free_i, n + 1, 1), F.substring(free_j, n + 1, 1)) for n in range(places)]
    differ = reduce(lambda x, y: x + y, ((a != b).cast("int") for a, b in at), F.lit(0))
    if not scores:
        return (places - differ) * match + differ * mismatch, differ
    table = F.create_map(*(F.lit(x) for (a, b), s in {**{(b, a): s for (a, b), s in scores.items()}, **scores}.items() for x in (a + b, int(s))))
    each = (F.coalesce(F.try_element_at(table, F.concat(a, b)), F.when(a == b, match).otherwise(mismatch)) for a, b in at)
    return reduce(lambda x, y: x + y, each, F.lit(0)), differ


def matches(seq: DataFrame, pattern: str, threshold: int = 0, match: int = 1, mismatch: int = -1, max_occurrences: int | None = None, scores: Scores | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Pairs of occurrences of a spaced word in two sequences whose free symbols score ``threshold`` or more.

    ``scores`` is a substitution matrix. ``lone`` marks words that each of the two sequences has once.
    ``max_occurrences`` leaves out words more frequent in a sequence; it is off unless asked for.
    """
    found = SpacedWord(pattern).occurrences(seq, keys)
    times = found.groupBy(*keys, "seq_id", "word").agg(F.count("*").alias("n"))
    if max_occurrences is not None:
        times = times.where(F.col("n") <= max_occurrences)
    found = found.join(times, [*keys, "seq_id", "word"])
    side = lambda s: found.select(*keys, "word", F.col("seq_id").alias(s), F.col("n").alias(f"n_{s}"), F.col("part_id").alias(f"part_{s}"), F.col("place").alias(f"place_{s}"), F.col("free").alias(f"free_{s}"))
    score, differ = scored(F.col("free_i"), F.col("free_j"), pattern.count("0"), match, mismatch, scores)
    pairs = side("i").join(side("j"), [*keys, "word"]).where("i < j").withColumns({"score": score.cast("int"), "differ": differ.cast("int"), "lone": F.expr("n_i = 1 and n_j = 1")})
    return pairs.where(F.col("score") >= threshold).select(*keys, "i", "j", "word", "place_i", "place_j", "part_i", "part_j", "score", "differ", "lone")


def one_to_one(pdf: pd.DataFrame) -> np.ndarray:
    """Best first: a match stands if neither of its occurrences is in a better one. Ties go by part and place."""
    order = pdf.sort_values(["score", "part_i", "place_i", "part_j", "place_j"], ascending=[False, True, True, True, True]).index
    left, right, keep = set(), set(), []
    for at, w, pi, i, pj, j in zip(order, *(pdf.loc[order, c] for c in ("word", "part_i", "place_i", "part_j", "place_j")), strict=True):
        if (w, pi, i) not in left and (w, pj, j) not in right:
            left.add((w, pi, i))
            right.add((w, pj, j))
            keep.append(at)
    return np.array(keep, int)


def dealt(seq: DataFrame, pattern: str, buckets: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, seq_id, bucket, data): a sequence's occurrences of the words of a bucket, compressed; a row for each batch."""
    at = [n for mark in "10" for n, c in enumerate(pattern) if c == mark]
    ones, span = pattern.count("1"), len(pattern)
    powers = np.array([pow(0x9E3779B97F4A7C15, n + 1, 1 << 64) for n in range(ones)], np.uint64)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column("residues")
            data, bounds = windows.symbols(texts)
            if len(data) and data.max() > 127:
                coded = [np.frombuffer((x or "").encode("utf-32-le"), "<u4") for x in texts.to_pylist()]
                data, bounds = np.concatenate(coded), np.cumsum([0, *map(len, coded)])
            many = np.maximum(np.diff(bounds) - span + 1, 0)
            first, part_id, offset = np.cumsum(many) - many, b.column("part_id").to_numpy(), b.column("offset").to_numpy()
            names = list(zip(*(b.column(c).to_pylist() for c in (*keys, "seq_id")), strict=True))
            number: dict[tuple, int] = {}
            own = np.array([number.setdefault(n, len(number)) for n in names], np.int64)
            an_own = {own[n]: n for n in reversed(range(len(names)))}
            done = 0
            for part, starts, rows in windows.steps(data, bounds, span):
                for lo in range(0, len(starts), SLICE):
                    start, row = starts[lo : lo + SLICE], rows[lo : lo + SLICE]
                    marked = np.empty((len(start), span), part.dtype)
                    code = np.zeros(len(start), np.uint64)
                    for c, n in enumerate(at):
                        marked[:, c] = part[start + n]
                        if c < ones:
                            code += (marked[:, c].astype(np.uint64) + np.uint64(1)) * powers[c]
                    bucket = (windows.mixed(code) % np.uint64(buckets)).astype(np.int64)
                    place = offset[row] + np.arange(done, done + len(row)) - first[row]
                    done += len(row)
                    to = own[row] * buckets + bucket
                    order = np.argsort(to, kind="stable")
                    ends = np.append(np.flatnonzero(np.diff(to[order])) + 1, len(order))
                    firsts = np.append(0, ends[:-1])
                    held = [zlib.compress(bytes([part.itemsize]) + part_id[row[x]].astype("<i8").tobytes() + place[x].astype("<i8").tobytes() + marked[x].tobytes(), 1) for x in np.split(order, ends[:-1])]
                    source = pa.array([an_own[n] for n in (to[order[firsts]] // buckets).tolist()], pa.int64())
                    yield pa.RecordBatch.from_arrays([*(b.column(c).take(source) for c in (*keys, "seq_id")), pa.array((to[order[firsts]] % buckets).astype(np.int32)), pa.array(held, pa.binary())], names=[*keys, "seq_id", "bucket", "data"])

    kinds = dict(seq.dtypes)
    schema = "".join(f"`{k}` {kinds[k]}, " for k in keys) + "seq_id string, bucket int, data binary"
    return seq.where(F.length("residues") >= span).select(*keys, "seq_id", "part_id", "offset", "residues").mapInArrow(work, schema)


class Free:
    """The free symbols of occurrences, and what two of them score: ``levels`` of those that reach the threshold, best first."""

    def __init__(self, symbols: np.ndarray, threshold: int, match: int, mismatch: int, scores: Scores | None):
        kinds, code = np.unique(symbols, return_inverse=True)
        self.code, self.places, self.threshold = code.reshape(symbols.shape), symbols.shape[1], threshold
        bits = max(0, len(kinds) - 1).bit_length()
        self.planes, self.table = None, None
        if scores:
            both = {**{(b, a): s for (a, b), s in scores.items()}, **scores}
            names = [chr(k) for k in kinds]
            self.table = np.array([[int(both.get((a, b), match if a == b else mismatch)) for b in names] for a in names], np.int64)
        elif self.places <= 64:
            wide = next(k for k, n in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.uint64, 64)) if self.places <= n)
            self.planes = [np.bitwise_or.reduce([((self.code[:, n] >> p) & 1).astype(wide) << wide(n) for n in range(self.places)] or [np.zeros(len(symbols), wide)]) for p in range(bits)]
        differ = np.arange(self.places + 1)
        score = (self.places - differ) * match + differ * mismatch
        good = np.unique(score[score >= threshold])[::-1]
        self.many = len(good)
        self.level = np.where(score >= threshold, len(good) - np.searchsorted(good[::-1], score, "right"), len(good)).astype(np.uint16)

    def between(self, one: np.ndarray, two: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """(levels, differing symbols, how many levels) of occurrences that broadcast against each other; a level that is not counted is none."""
        shape = np.broadcast_shapes(one.shape, two.shape)
        if self.planes is not None:
            apart = np.zeros(shape, np.uint8)
            if self.planes:
                x = self.planes[0][one] ^ self.planes[0][two]
                for p in self.planes[1:]:
                    x |= p[one] ^ p[two]
                apart = np.bitwise_count(x)
            return self.level[apart], apart, self.many
        apart, score = np.zeros(shape, np.int32), np.zeros(shape, np.int64)
        for n in range(self.places):
            a, b = self.code[one, n], self.code[two, n]
            apart += a != b
            if self.table is not None:
                score += self.table[a, b]
        if self.table is None:
            return self.level[apart], apart, self.many
        top = self.places * int(self.table.max(initial=0))
        many = max(0, top - self.threshold + 1)
        return np.where(score >= self.threshold, top - score, many), apart, many


def _best_first(level: np.ndarray, apart: np.ndarray, many: int) -> tuple[np.ndarray, np.ndarray]:
    """(matches, differing symbols) of many pairs at once; axes: occurrence in i, pair, occurrence in j."""
    _, pairs, there = level.shape
    open_j, n, differ, each = np.ones((pairs, there), bool), np.zeros(pairs, np.int64), np.zeros(pairs, np.int64), np.arange(pairs)
    open_i = np.ones(level.shape[:2], bool)
    for now in range(many) if many <= 16 else np.unique(level[level < many]).tolist():
        for x, here in enumerate(level):
            can = here == now
            can &= open_j
            to = can.argmax(1)
            hit = np.flatnonzero(can[each, to] & open_i[x])
            if len(hit):
                to = to[hit]
                open_j[hit, to], open_i[x, hit] = False, False
                n[hit] += 1
                differ[hit] += apart[x, hit, to]
    return n, differ


def _best_first_classes(free: Free, one: np.ndarray, two: np.ndarray) -> tuple[int, int]:
    """The same for one pair with very many occurrences: those of j with equal symbols stand in a queue."""
    kind_i, of_i = np.unique(free.code[one], axis=0, return_index=True, return_inverse=True)[1:]
    kind_j, of_j = np.unique(free.code[two], axis=0, return_index=True, return_inverse=True)[1:]
    of_i, queue = of_i.ravel(), np.argsort(of_j.ravel(), kind="stable")
    size = np.bincount(of_j.ravel())
    end = np.cumsum(size)
    head, left, n, differ, now, many = end - size, np.arange(len(one)), 0, 0, 0, 1
    few = len(kind_i) * len(kind_j) <= 4 * CELLS
    rows: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    while now < many:
        rest = []
        for x in left.tolist():
            kind = int(of_i[x])
            if kind in rows:
                level, apart = rows[kind]
            else:
                level, apart, many = free.between(one[kind_i[kind]], two[kind_j])
                if few:
                    rows[kind] = level, apart
            can = np.flatnonzero((level == now) & (head < end))
            if len(can):
                to = can[np.argmin(queue[head[can]])]
                head[to] += 1
                n += 1
                differ += int(apart[to])
            else:
                rest.append(x)
        left, now = np.array(rest, np.int64), now + 1
    return n, differ


def _chosen(table: pa.Table, keys: tuple[str, ...], ones: int, span: int, max_occurrences: int | None, scoring: tuple) -> pa.Table:
    """(keys, i, j, n_match, differ) of a bucket's words: occurrences are matched best first, one to one; ties go by part and place."""
    names = sorted(set(table.column("seq_id").to_pylist()))
    number, raw = {s: n for n, s in enumerate(names)}, [zlib.decompress(x.as_py()) for x in table.column("data")]
    many = [(len(x) - 1) // (16 + span * x[0]) for x in raw]
    seq = np.repeat([number[s] for s in table.column("seq_id").to_pylist()], many)
    part = np.concatenate([np.frombuffer(x, "<i8", n, 1) for x, n in zip(raw, many, strict=True)])
    place = np.concatenate([np.frombuffer(x, "<i8", n, 1 + 8 * n) for x, n in zip(raw, many, strict=True)])
    marked = np.concatenate([np.frombuffer(x, np.uint8 if x[0] == 1 else "<u4", n * span, 1 + 16 * n).reshape(n, span) for x, n in zip(raw, many, strict=True)])
    _, word = np.unique(np.ascontiguousarray(marked[:, :ones]).view(f"V{ones * marked.itemsize}").ravel(), return_inverse=True) if ones else (None, np.zeros(len(marked), np.int64))
    order = np.lexsort((place, part, seq, word))
    seq, word = seq[order], word[order]
    free = Free(marked[order, ones:], *scoring)
    first = np.flatnonzero(np.append(True, (word[1:] != word[:-1]) | (seq[1:] != seq[:-1])))
    size = np.diff(np.append(first, len(word)))
    if max_occurrences is not None:
        first, size = first[size <= max_occurrences], size[size <= max_occurrences]
    own, after = seq[first], np.searchsorted(word[first], word[first], "right") - np.arange(len(first)) - 1
    upto, found = np.cumsum(after), []
    lo = 0
    while lo < len(first):
        hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + RUNS, "right")))
        one = np.repeat(np.arange(lo, hi), after[lo:hi])
        two = one + 1 + np.arange(len(one)) - np.repeat(upto[lo:hi] - after[lo:hi] - (upto[lo - 1] if lo else 0), after[lo:hi])
        lo = hi
        n, differ = np.zeros(len(one), np.int64), np.zeros(len(one), np.int64)
        long = size[one] * size[two] > CELLS
        for x in np.flatnonzero(long):
            n[x], differ[x] = _best_first_classes(free, *(first[s[x]] + np.arange(size[s[x]]) for s in (one, two)))
        here, there = (_LADDER[np.searchsorted(_LADDER, size[s])] for s in (one, two))
        by = np.lexsort((there, here))
        by = by[~long[by]]
        cuts = np.append(np.flatnonzero((np.diff(here[by]) != 0) | (np.diff(there[by]) != 0)) + 1, len(by)).tolist()
        for start, stop in zip([0, *cuts[:-1]], cuts, strict=True):
            if start == stop:
                continue
            a, b = int(here[by[start]]), int(there[by[start]])
            for at in range(start, stop, step := max(1, CELLS // (a * b))):
                x = by[at : min(stop, at + step)]
                i, j = np.arange(a)[:, None], np.arange(b)
                level, apart, levels = free.between(np.minimum(first[one[x]] + i, len(seq) - 1)[:, :, None], np.minimum(first[two[x]][:, None] + j, len(seq) - 1)[None])
                level[(i >= size[one[x]])[:, :, None] | (j >= size[two[x]][:, None])[None]] = levels
                n[x], differ[x] = _best_first(level, apart, levels)
        pair, at = np.unique(own[one] * len(names) + own[two], return_inverse=True)
        total, apart = np.zeros(len(pair), np.int64), np.zeros(len(pair), np.int64)
        np.add.at(total, at, n)
        np.add.at(apart, at, differ)
        found.append((pair[total > 0], total[total > 0], apart[total > 0]))
    pair, total, apart = (np.concatenate([f[n] for f in found] or [np.zeros(0, np.int64)]) for n in range(3))
    all_names = pa.array(names, pa.string())
    same = [pa.array([table.column(k)[0].as_py()] * len(pair), table.schema.field(k).type) for k in keys]
    return pa.table([*same, all_names.take(pa.array(pair // len(names))), all_names.take(pa.array(pair % len(names))), pa.array(total), pa.array(apart)], names=[*keys, "i", "j", "n_match", "differ"])


def _choosing(*how) -> Callable[[pa.Table], pa.Table]:
    """``_chosen`` as a function of a table only."""

    def work(table: pa.Table) -> pa.Table:
        return _chosen(table, *how)

    return work


def distance(seq: DataFrame, patterns: list[str], threshold: int = 0, alphabet: str = "ACGT", keys: tuple[str, ...] = (), match: int = 1, mismatch: int = -1, max_occurrences: int | None = None, scores: Scores | None = None) -> DataFrame:
    """(keys, i, j, n_match, value) for all pairs; null where no match survives, or too many symbols differ to tell.

    Matches of several patterns are pooled. Within a pair and word they are chosen best first, one to one. Words are dealt
    into buckets, whose occurrences are scored and chosen by numpy in one task: neither an occurrence nor a match is a row.
    """
    pair, parts = [*keys, "i", "j"], []
    kinds = dict(seq.dtypes)
    schema = "".join(f"`{k}` {kinds[k]}, " for k in keys) + "i string, j string, n_match bigint, differ bigint"
    buckets = max(BUCKETS, int(seq.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    for pattern in patterns:
        ones, span, scoring = pattern.count("1"), len(pattern), (threshold, match, mismatch, scores)
        chosen = dealt(seq, pattern, buckets, keys).groupBy(*keys, "bucket").applyInArrow(_choosing(keys, ones, span, max_occurrences, scoring), schema)
        parts.append(chosen.withColumn("free", F.col("n_match") * pattern.count("0")))
    total = reduce(DataFrame.unionByName, parts).groupBy(*pair).agg(*(F.sum(c).alias(c) for c in ("n_match", "differ", "free")))
    ids = seq.select(*keys, "seq_id").distinct()
    one, two = ids.withColumnRenamed("seq_id", "i"), ids.withColumnRenamed("seq_id", "j")
    grid = one.join(F.broadcast(two), list(keys)).where("i < j") if keys else one.join(F.broadcast(two), F.col("i") < F.col("j"))
    limit = (len(alphabet) - 1) / len(alphabet)
    rate = F.col("differ") / F.col("free")
    value = F.when(rate < limit, -limit * F.log(1 - rate / limit))
    return grid.join(total, pair, "left").select(*pair, F.coalesce("n_match", F.lit(0)).alias("n_match"), value.alias("value"))
