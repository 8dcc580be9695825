"""Substring deduplication: repeated windows of words are removed, all but the first in reading order.

A count-min sketch goes ahead of the exact grouping. What it counts is, for each window, the anchor: the smallest hash
among the window's shorter grams. Equal windows have equal anchors at different places, so the count of an anchor's cell
is never below the count of any window it stands for; a window whose cell was counted once can't be repeated. Each
partition makes its own sparse sketch (cell, counted once or more), and the partitions' sketches are merged by adding. The
sketch has one row of 2^40 cells, kept sparse: at that width a second row would double the traffic and reject next to
nothing more. What the merge leaves is a bitmap of fixed size, so it may be broadcast at any input; where it fills up,
more windows reach the second pass and none is lost. The second pass groups what passed by a 128-bit hash of the words.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, batch, bundled, grams, mixed, packed, signed, starts_of, steps, tidy, unbundled, unpacked, written

WINDOW = 20
GRAM = 8
#: Columns of a result.
COLUMNS = ("doc_id", "n_words", "n_removed", "kept_sha256", "text")
CELL_BITS = 40
BITMAP_BITS = 26
#: Cells that a task holds before it hands a sketch on.
FLUSH = 4_000_000
_BLOCK = 1 << 20
_CELL_SHIFT = np.uint64(24)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_PLACE = np.uint64((1 << 24) - 1)


def anchors(words: Words, h: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows of a run of words: their starts, their anchors' cells, and the anchors' places."""
    at = starts_of(words, window)
    cells, places = [], []
    g, span = grams(h, gram), window - gram + 1
    for lo in range(0, len(g), _BLOCK):  # places within a block fit the low bits, so that the leftmost of ties wins
        part = g[lo : lo + _BLOCK + span - 1]
        v = (part & ~_PLACE) | np.arange(len(part), dtype=np.uint64)
        best, have = v, 1
        while have < span:
            step = min(have, span - have)
            best, have = np.minimum(best[: max(0, len(best) - step)], best[step:]), have + step
        mine = at[np.searchsorted(at, lo) : np.searchsorted(at, lo + _BLOCK)] - lo
        got = best[mine]
        cells.append(got >> _CELL_SHIFT)
        places.append((got & _PLACE).astype(np.int64) + lo)
    if not cells:
        return at, np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return at, np.concatenate(cells), np.concatenate(places)


def heavy_cells(docs: DataFrame, window: int, gram: int) -> np.ndarray:
    """The merged sketch: a bitmap of the cells counted twice or more, ``BITMAP_BITS`` long at any input.

    A partition's sketch goes in segments of ascending cells, as differences; a segment's merge adds up what all partitions
    counted. The bitmap holds a cell by its leading bits: more cells than it has bits only let more windows through.
    """
    spark = docs.sparkSession
    segments = 256
    while segments < 4 * int(spark.conf.get("spark.sql.shuffle.partitions")):
        segments *= 2
    span = CELL_BITS - (segments.bit_length() - 1)

    def flushed(parts: list[np.ndarray]) -> pa.RecordBatch:
        cell, n = np.unique(np.concatenate(parts), return_counts=True)
        edges = np.searchsorted(cell >> np.uint64(span), np.arange(segments + 1, dtype=np.uint64))
        some = np.flatnonzero(np.diff(edges))
        press = zstandard.ZstdCompressor(level=1)
        own = cell & np.uint64((1 << span) - 1)
        coded = [press.compress(np.diff(own[edges[k] : edges[k + 1]], prepend=np.uint64(0)).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()) for k in some]
        twice = [np.packbits(n[edges[k] : edges[k + 1]] > 1).tobytes() for k in some]
        return batch(segment=some.astype(np.int32), cells=pa.array(coded, pa.binary()), twice=pa.array(twice, pa.binary()))

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for b in batches:
            for lo, hi in steps(b):
                w = Words(b.column("text").slice(lo, hi - lo))
                _, cells, places = anchors(w, w.hashes(), window, gram)
                parts.append(cells[np.unique(places, return_index=True)[1]])
                held += len(parts[-1])
                if held > FLUSH:
                    yield flushed(parts)
                    parts, held = [], 0
        if held:
            yield flushed(parts)

    def merge(group: pa.Table) -> pa.Table:
        press = zstandard.ZstdDecompressor()
        once, more = [], []
        for cells, twice in zip(group.column("cells").to_pylist(), group.column("twice").to_pylist(), strict=True):
            raw = np.frombuffer(press.decompress(cells), np.uint8)
            own = np.cumsum(np.ascontiguousarray(raw.reshape(4, -1).T).view("<u4").ravel(), dtype=np.uint64)
            once.append(own)
            more.append(own[np.unpackbits(np.frombuffer(twice, np.uint8))[: len(own)] > 0])
        cell, n = np.unique(np.concatenate(once), return_counts=True)
        flags = np.zeros((1 << BITMAP_BITS) // segments, bool)
        for found in (cell[n > 1], *more):
            flags[(found >> np.uint64(CELL_BITS - BITMAP_BITS)).astype(np.int64)] = True
        bits = zstandard.ZstdCompressor(level=1).compress(np.packbits(flags).tobytes())
        return pa.table({"segment": group.column("segment")[:1], "bits": pa.array([bits], pa.binary())})

    rows = docs.select("text").mapInArrow(tidy(step), "segment int, cells binary, twice binary")
    bitmap = np.zeros((segments, (1 << BITMAP_BITS) // segments // 8), np.uint8)
    for r in rows.groupBy("segment").applyInArrow(merge, "segment int, bits binary").collect():
        bitmap[r.segment] = np.frombuffer(zstandard.ZstdDecompressor().decompress(bytes(r.bits)), np.uint8)
    return bitmap.ravel()


def runs(docs: DataFrame, window: int, gram: int) -> DataFrame:
    """(doc_id, at, n, g, r): runs of n windows that share an anchor whose cell was counted twice or more.

    g is the anchor's hash and r that of all the run's words; together, of 128 bits, they tell runs apart.
    """
    shared = docs.sparkSession.sparkContext.broadcast(heavy_cells(docs, window, gram))

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column("doc_id").to_numpy(zero_copy_only=False)
            for lo, hi in steps(b):
                w = Words(b.column("text").slice(lo, hi - lo))
                h = w.hashes()
                at, cells, places = anchors(w, h, window, gram)
                bit = (cells >> np.uint64(CELL_BITS - BITMAP_BITS)).astype(np.int64)
                kept = np.flatnonzero(shared.value[bit >> 3] >> (7 - (bit & 7)).astype(np.uint8) & 1)
                if not len(kept):
                    continue
                at, places = at[kept], places[kept]
                new = np.ones(len(at), bool)
                new[1:] = (places[1:] != places[:-1]) | (at[1:] != at[:-1] + 1)
                first = np.flatnonzero(new)
                n = np.diff(np.append(first, len(at)))
                whole = grams(h, window)
                r = mixed(whole[at[first]] * _ODD + whole[at[first + n - 1]]) + n.astype(np.uint64)
                g = grams(w.hashes(1), gram)[places[first]]
                row = w.row[at[first]]
                yield batch(doc_id=ids[lo:hi][row], at=(at[first] - w.bounds[row]).astype(np.int32), n=n.astype(np.int32), g=signed(g), r=signed(r))

    return docs.select("doc_id", "text").mapInArrow(tidy(step), "doc_id bigint, at int, n int, g bigint, r bigint")


def windows(texts: DataFrame, chosen: DataFrame, window: int, gram: int) -> DataFrame:
    """(doc_id, at, g, r): single windows of the chosen runs, by hash of anchor and words."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column("doc_id").to_numpy(zero_copy_only=False)
            runs_of = b.column("runs")
            for i in range(len(b)):
                w = Words(unpacked(b.column("z").slice(i, 1)))
                h = w.hashes()
                at, _, places = anchors(w, h, window, gram)
                run = runs_of[i].values.to_numpy()
                keep = np.zeros(len(at) + 1, np.int64)
                np.add.at(keep, run >> 8, 1)
                np.add.at(keep, (run >> 8) + (run & 255), -1)
                mine = np.flatnonzero(np.cumsum(keep)[:-1])
                yield batch(doc_id=np.full(len(mine), ids[i]), at=at[mine].astype(np.int32), g=signed(grams(w.hashes(1), gram)[places[mine]]), r=signed(grams(h, window)[at[mine]]))

    per_doc = chosen.groupBy("doc_id").agg(F.collect_list(_run("at", "n")).alias("runs"))
    rows = texts.join(per_doc, "doc_id")  # with all columns of the texts, so that their shuffle is one with the last join's
    return rows.mapInArrow(tidy(step), "doc_id bigint, at int, g bigint, r bigint")


def _run(at: str, n: str) -> Column:
    return F.shiftleft(F.col(at).cast("bigint"), 8) + F.col(n)


def repeats(docs: DataFrame, texts: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(doc_id, runs): where windows start whose words also start earlier, as place * 256 + number of windows.

    Earlier: in a document of smaller doc_id, or in the same one before. Rows of docs that share a doc_id count as one
    place, so copies of a row aren't repeats of each other. Runs with equal words are settled first; only anchors with
    runs of different words, as at the ends of a passage, are looked at window by window.
    """
    found = written(runs(docs, window, gram), "repeat-runs")
    first = found.groupBy("g", "r").agg(F.min(F.struct("doc_id", "at", "n")).alias("first"), F.count("*").alias("times"))
    first = written(first.select("g", "r", "first.*", "times"), "repeat-first")
    again = first.where("times > 1").select("g", "r", F.struct("doc_id", "at").alias("first"))
    whole = found.join(again, ["g", "r"]).where(F.struct("doc_id", "at") != F.col("first")).select("doc_id", "at", "n")
    mixed_ends = first.groupBy("g").agg(F.count("*").alias("kinds")).where("kinds > 1").select("g")
    single = windows(texts, first.join(mixed_ends, "g", "left_semi"), window, gram)
    earliest = single.groupBy("g", "r").agg(F.min(F.struct("doc_id", "at")).alias("first"), F.count("*").alias("times")).where("times > 1").select("g", "r", "first")
    later = single.join(earliest, ["g", "r"]).where(F.struct("doc_id", "at") != F.col("first")).select("doc_id", "at", F.lit(1).alias("n"))
    return whole.unionAll(later).groupBy("doc_id").agg(F.collect_list(_run("at", "n")).alias("runs"))


def deduplicated(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, keep: tuple[str, ...] = (), keep_text: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, the columns of ``keep`` (of docs), and with ``keep_text`` also ``text``.

    The digest is that of the kept words joined by one space. That is also the text, but for a text that loses no word:
    it stays as it is. A null or empty text has no words: n_words and n_removed are 0, and the digest is that of the empty
    text. Documents of fewer words than a window lose none. A null doc_id is kept, but its windows neither remove nor are
    removed. Columns of docs that aren't named are not read.
    """
    docs, names = bundled(docs, keep), keep
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema}
    keep = ("_kept",) if keep else ()

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cuts_of = b.column("runs")
            words, removed, digests, texts = [], [], [], []
            for i, text in enumerate(unpacked(b.column("z")).to_pylist()):
                parts = text.encode().split()  # bytes split at these six white spaces only
                words.append(len(parts))
                cut = 0
                if cuts_of[i].is_valid:
                    gone = np.zeros(len(parts) + 1, np.int64)
                    run = cuts_of[i].values.to_numpy()
                    np.add.at(gone, run >> 8, 1)
                    np.add.at(gone, np.minimum((run >> 8) + (run & 255) - 1 + window, len(parts)), -1)
                    stay = np.cumsum(gone)[:-1] == 0
                    cut = len(parts) - int(stay.sum())
                    parts = [parts[k] for k in np.flatnonzero(stay)]
                kept = b" ".join(parts)
                removed.append(cut)
                digests.append(hashlib.sha256(kept).hexdigest())
                if keep_text:
                    texts.append(kept.decode() if cut else text)
            out = {"doc_id": b.column("doc_id"), "n_words": pa.array(words, pa.int64()), "n_removed": pa.array(removed, pa.int64()), "kept_sha256": pa.array(digests, pa.string())}
            yield batch(**out, **{k: b.column(k) for k in keep}, **({"text": pa.array(texts, pa.string())} if keep_text else {}))

    texts = packed(docs, "doc_id", *keep)
    cuts = repeats(docs.where(F.col("doc_id").isNotNull()), texts, window, gram)
    rows = texts.join(cuts, "doc_id", "left")
    more = "".join(f", `{k}` {kinds[k]}" for k in keep) + (", text string" if keep_text else "")
    return unbundled(rows.mapInArrow(tidy(step), "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string" + more), names)
