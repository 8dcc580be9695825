"""Quality rules: fixed rules on document statistics, then gradient-boosted trees over them.

The trees are grown on binned statistics with a logistic loss, and flattened into arrays of nodes that score a batch of
documents a level at a time. Chosen statistics are held monotonic: a split that would let quality rise with them is not
taken, and the two sides of a split keep to either side of its middle further down.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, batch, grams, mixed, starts_of, steps, tidy
from .labelled import MAX_TRAINING_ROWS, training_rows

SYMBOLS = b"#*$%&|<>"
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("n_words", "mean_chars", "symbols", "dup_lines", "repeats", "upper", "exclaims", "digits", "distinct", "line_words")
#: Statistics that quality may not rise with (-1).
MONOTONE = {"symbols": -1, "dup_lines": -1, "repeats": -1, "exclaims": -1}
TREES, DEPTH, BINS, RATE = 60, 3, 32, 0.2
MIN_WORDS = 50


def _flags(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_SYMBOL, _UPPER, _EXCLAIM, _DIGIT = _flags(SYMBOLS), _flags(bytes(range(65, 91))), _flags(b"!"), _flags(b"0123456789")


def statistics(texts: pa.Array) -> dict[str, np.ndarray]:
    """Exact statistics of each text (null: empty) and the features made of them."""
    w = Words(texts)
    data = w.bytes[: int(w.offsets[-1])]

    def per_row(flag: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0], np.cumsum(flag, dtype=np.int64)])
        return sums[w.offsets[1:]] - sums[w.offsets[:-1]]

    h = w.hashes()
    covered = np.zeros(len(h) + 3, bool)
    at = starts_of(w, 3)
    if len(at):
        key = mixed(grams(h, 3)[at] ^ mixed(w.row[at].astype(np.uint64) + np.uint64(1)))
        order = np.argsort(key)
        same = key[order][1:] == key[order][:-1]
        twice = np.zeros(len(at), bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        for k in range(3):
            covered[at[twice] + k] = True
    repeated = np.concatenate([[0], np.cumsum(covered[: len(h)], dtype=np.int64)])
    order = np.lexsort((h, w.row))
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[order][1:] != h[order][:-1]) | (w.row[order][1:] != w.row[order][:-1])
    kinds = np.bincount(w.row[order][fresh], minlength=w.rows)
    lines, dup = _lines(w, data)
    inside = per_row((data & 0xC0) != 0x80) - per_row((data == 32) | ((data >= 9) & (data <= 13)))
    n = w.counts
    out = {"n_words": n, "word_chars": inside, "n_symbols": per_row(_SYMBOL[data]), "n_dup_lines": dup, "n_repeat_words": repeated[w.bounds[1:]] - repeated[w.bounds[:-1]]}
    share = lambda x, of: x / np.maximum(of, 1)
    out["features"] = np.stack([n, share(inside, n), share(out["n_symbols"], inside), share(dup, lines), share(out["n_repeat_words"], n), share(per_row(_UPPER[data]), inside), share(per_row(_EXCLAIM[data]), n), share(per_row(_DIGIT[data]), inside), share(kinds, n), share(n, lines)], axis=1).astype(np.float64)
    return out


def _lines(w: Words, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lines with a word in each text, and how many of them equal an earlier line."""
    breaks = np.flatnonzero(data == 10)
    starts = np.unique(np.concatenate([w.offsets[:-1], breaks + 1]))
    starts = starts[starts < len(data)]
    ends = np.minimum(np.append(starts[1:], len(data)), len(data))
    ends = ends - ((ends > starts) & (data[np.maximum(ends - 1, 0)] == 10) if len(data) else 0)
    row = np.searchsorted(w.offsets, starts, "right") - 1
    worded = np.searchsorted(w.starts, ends) > np.searchsorted(w.starts, starts)
    starts, ends, row = starts[worded], ends[worded], row[worded]
    view = Words.__new__(Words)
    view.bytes, view.starts, view.ends = w.bytes, starts, ends
    h = view.hashes(2)
    order = np.lexsort((h, row))
    again = (h[order][1:] == h[order][:-1]) & (row[order][1:] == row[order][:-1])
    return np.bincount(row, minlength=w.rows), np.bincount(row[order][1:][again], minlength=w.rows)


@dataclass
class Forest:
    """All trees' nodes in flat arrays: a node's children are ``left`` and ``left + 1``; leaves point to themselves."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    start: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        at = np.tile(self.roots, (len(x), 1))
        rows = np.arange(len(x))[:, None]
        for _ in range(DEPTH):
            inner = self.left[at] != at
            right = x[rows, self.feature[at]] > self.threshold[at]
            at = np.where(inner, self.left[at] + right, at)
        return 1 / (1 + np.exp(-(self.start + self.value[at].sum(1))))


def grow(x: np.ndarray, y: np.ndarray, monotone: dict[int, int], trees: int = TREES, depth: int = DEPTH, rate: float = RATE) -> Forest:
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(x.shape[1])]
    bins = np.stack([np.searchsorted(c, x[:, j], "left") for j, c in enumerate(cuts)], axis=1)
    base = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    start = float(np.log(base / (1 - base)))
    raw = np.full(len(y), start)
    feature, threshold, left, value, roots = [], [], [], [], []

    def node() -> int:
        for column, what in ((feature, 0), (threshold, 0.0), (left, len(left)), (value, 0.0)):
            column.append(what)
        return len(left) - 1

    for _ in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = p - y, p * (1 - p)
        roots.append(node())
        open_nodes = [(roots[-1], np.arange(len(y)), 0, -np.inf, np.inf)]
        while open_nodes:
            at, rows, level, low, high = open_nodes.pop()
            best = _best_split(bins, g, h, rows, cuts, monotone, low, high) if level < depth else None
            if best is None:
                value[at] = rate * float(np.clip(_weight(g[rows].sum(), h[rows].sum()), low, high))
                raw[rows] += value[at]
                continue
            j, cut, middle = best
            feature[at], threshold[at], left[at] = j, float(cuts[j][cut]), node()
            node()
            right = bins[rows, j] > cut
            sign = monotone.get(j, 0)
            sides = ((low, high), (low, high)) if not sign else ((low, middle), (middle, high)) if sign > 0 else ((middle, high), (low, middle))
            for k, (lo, hi) in enumerate(sides):
                open_nodes.append((left[at] + k, rows[right == bool(k)], level + 1, lo, hi))
    return Forest(*(np.array(c) for c in (feature, threshold, left, value, roots)), start)


def _weight(g: float, h: float) -> float:
    return -g / (h + 1.0)


def _best_split(bins, g, h, rows, cuts, monotone, low, high) -> tuple[int, int, float] | None:
    best, found = 1e-3, None
    total_g, total_h = g[rows].sum(), h[rows].sum()
    for j, c in enumerate(cuts):
        if not len(c):
            continue
        gs = np.cumsum(np.bincount(bins[rows, j], g[rows], len(c) + 1))[:-1]
        hs = np.cumsum(np.bincount(bins[rows, j], h[rows], len(c) + 1))[:-1]
        n = np.cumsum(np.bincount(bins[rows, j], minlength=len(c) + 1))[:-1]
        a = np.clip(-gs / (hs + 1), low, high)
        b = np.clip(-(total_g - gs) / (total_h - hs + 1), low, high)
        gain = gs**2 / (hs + 1) + (total_g - gs) ** 2 / (total_h - hs + 1) - total_g**2 / (total_h + 1)
        gain = np.where((n < 5) | (len(rows) - n < 5) | ((b - a) * monotone.get(j, 0) < 0), -np.inf, gain)
        k = int(np.argmax(gain))
        if gain[k] > best:
            best, found = gain[k], (j, k, float(a[k] + b[k]) / 2)
    return found


def fit(docs: DataFrame, labels: DataFrame, most: int = MAX_TRAINING_ROWS) -> Forest | None:
    """Trees on at most ``most`` labelled rows outside the fold kept for tests; None where labels hold one class or none."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in steps(b):
                x = statistics(b.column("text").slice(lo, hi - lo))["features"]
                yield batch(doc_id=b.column("doc_id").slice(lo, hi - lo), label=b.column("label").slice(lo, hi - lo), x=pa.array([r.tobytes() for r in x], pa.binary()))

    got = training_rows(docs, labels, "quality", most).mapInArrow(tidy(step), "doc_id bigint, label int, x binary").toPandas().sort_values("doc_id")
    y = got.label.to_numpy(np.float64)
    if not len(y) or y.min() == y.max():
        return None
    x = np.stack([np.frombuffer(v) for v in got.x])
    return grow(x, y, {FEATURES.index(k): v for k, v in MONOTONE.items()})


def judged(docs: DataFrame, forest: Forest | None, threshold: float = 0.5) -> DataFrame:
    """doc_id, the base statistics, base_failed, kept and the trees' score for every row of docs.

    A null or empty text has no words, so the base rules fail it. Without a forest the base rules alone decide, and the
    score is null. Repeated rows are judged each; other columns are not read.
    """

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in steps(b):
                s = statistics(b.column("text").slice(lo, hi - lo))
                score = pa.array(forest.scores(s["features"])) if forest else pa.nulls(hi - lo, pa.float64())
                yield batch(doc_id=b.column("doc_id").slice(lo, hi - lo), **{k: s[k].astype(np.int64) for k in BASE}, score=score)

    rows = docs.select("doc_id", "text").mapInArrow(tidy(step), "doc_id bigint, " + ", ".join(f"{k} bigint" for k in BASE) + ", score double")
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.select("doc_id", *BASE, failed.alias("base_failed"), (~failed & F.coalesce(F.col("score") >= threshold, F.lit(True))).alias("kept"), "score")
