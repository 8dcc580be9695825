"""Quality classifier: random-indexing word vectors pooled per document, then a small calibrated network.

Every token has a fixed sparse ternary index vector; the vector of a token is the sum of the index vectors of its
neighbours in the training texts. A word stands for two tokens: its letters, hashed into a fixed number of buckets, and
its shape: the kinds of characters in it, and whether it repeats the word before. A document is the mean of its words' vectors, letters and shapes apart, which
two dense layers score; the logit is divided by a temperature fitted on texts kept out of the training.
The classifier, vectors included, is fitted on a bounded sample of labelled rows (``MAX_TRAINING_ROWS``).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, batch, fold, mixed, packed, steps, tidy, unpacked
from .labelled import MAX_TRAINING_ROWS, sample

BUCKETS = 1 << 14
SHAPES = 512
DIMENSIONS = 32
NONZERO = 4
REACH = 2
HIDDEN = 24
#: Parts the bounded sample is dealt into while vectors are summed.
SAMPLE_PARTS = 8


def _kinds() -> np.ndarray:
    kind = np.zeros(256, np.uint8)
    kind[97:123], kind[65:91], kind[48:58], kind[128:] = 1, 2, 4, 1
    for k, chars in ((8, b".,;:?'\"()-"), (16, b"#*$%&"), (32, b"|<>"), (64, b"!"), (128, b"@/\\_=+~^`[]{}")):
        kind[list(chars)] = k
    return kind


_KIND = _kinds()


def tokens(w: Words) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and shape of each word; the shape's highest bit tells an echo of the word before."""
    h = w.hashes()
    letters = (h % np.uint64(BUCKETS)).astype(np.int64)
    shapes = np.bitwise_or.reduceat(_KIND[w.bytes], w.starts).astype(np.int64) if len(w.starts) else np.zeros(0, np.int64)
    shapes[1:] += 256 * ((h[1:] == h[:-1]) & (w.row[1:] == w.row[:-1]))
    return letters, shapes


def index_vectors() -> np.ndarray:
    """A sparse ternary vector for each bucket and shape, by hash."""
    n = BUCKETS + SHAPES
    out = np.zeros((n, DIMENSIONS), np.float32)
    for k in range(NONZERO):
        h = mixed(np.arange(n, dtype=np.uint64) * np.uint64(NONZERO) + np.uint64(k + 1))
        out[np.arange(n), (h % np.uint64(DIMENSIONS)).astype(np.int64)] += np.where(h >> np.uint64(40) & np.uint64(1), 1.0, -1.0)
    return out


@dataclass
class Model:
    vectors: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float

    def logits(self, pooled: np.ndarray) -> np.ndarray:
        hidden = np.tanh((pooled - self.mean) / self.scale @ self.w1 + self.b1)
        return hidden @ self.w2 + self.b2

    def scores(self, texts: pa.Array) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(pooled(texts, self.vectors)) / self.temperature, -30, 30)))


def pooled(texts: pa.Array, vectors: np.ndarray) -> np.ndarray:
    """A row for each text; zeros for one without words."""
    w = Words(texts)
    letters, shapes = tokens(w)
    out = np.zeros((w.rows, 2 * DIMENSIONS), np.float32)
    some = np.flatnonzero(w.counts)
    if len(some):
        out[some, :DIMENSIONS] = np.add.reduceat(vectors[letters], w.bounds[:-1][some], axis=0)
        counts = np.bincount(w.row * SHAPES + shapes, minlength=w.rows * SHAPES).reshape(w.rows, SHAPES)
        out[:, DIMENSIONS:] = counts.astype(np.float32) @ vectors[BUCKETS:]
        out[some] /= w.counts[some, None]
    return out


def context_sums(z: Iterator[pa.Array]) -> np.ndarray:
    """Sums of neighbours' index vectors for each bucket and shape."""
    index = index_vectors()
    sums = np.zeros_like(index)
    n = len(index)
    for part in z:
        w = Words(unpacked(part))
        letters, shapes = tokens(w)
        for near in range(1, REACH + 1):
            same = np.flatnonzero(w.row[near:] == w.row[:-near]) if len(w.row) > near else np.zeros(0, np.int64)
            for own in (letters, shapes + BUCKETS):
                for other in (letters, shapes + BUCKETS):
                    for a, b in ((own[same], other[same + near]), (own[same + near], other[same])):
                        pair, times = np.unique(a * n + b, return_counts=True)
                        np.add.at(sums, pair // n, index[pair % n] * times[:, None].astype(np.float32))
    return sums


def fit(docs: DataFrame, labels: DataFrame, most: int = MAX_TRAINING_ROWS, seed: int = 7) -> Model | None:
    """None where the labels don't hold both classes."""
    ids = sample(labels, "quality", most=most)
    rows = packed(docs.join(F.broadcast(ids), "doc_id"), "doc_id", "label").repartition(SAMPLE_PARTS)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = context_sums(b.column("z").slice(i, 256) for b in batches for i in range(0, len(b), 256))
        yield batch(sums=pa.array([sums.tobytes()], pa.binary()))

    n = BUCKETS + SHAPES
    sums = sum(np.frombuffer(r.sums, np.float32).reshape(n, DIMENSIONS) for r in rows.mapInArrow(tidy(partial), "sums binary").collect())
    vectors = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-6)
    vectors = vectors.astype(np.float32)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, len(b), 256):
                part = b.slice(i, 256)
                x = pooled(unpacked(part.column("z")), vectors)
                yield batch(doc_id=part.column("doc_id"), label=part.column("label"), x=pa.array([r.tobytes() for r in x], pa.binary()))

    got = rows.mapInArrow(tidy(features), "doc_id bigint, label int, x binary").toPandas().sort_values("doc_id")
    y = got.label.to_numpy(np.float64)
    if not len(y) or y.min() == y.max():
        return None
    return train(np.stack([np.frombuffer(v, np.float32) for v in got.x]).astype(np.float64), y, vectors, seed)


def train(x: np.ndarray, y: np.ndarray, vectors: np.ndarray, seed: int) -> Model:
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    cut = max(1, len(y) // 5)
    check, use = order[:cut], order[cut:] if len(y) > 5 else order
    mean, scale = x[use].mean(0), x[use].std(0) + 1e-4
    z = (x - mean) / scale
    p = {"w1": rng.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], HIDDEN)), "b1": np.zeros(HIDDEN), "w2": rng.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN), "b2": np.zeros(1)}
    first, second = ({k: np.zeros_like(v) for k, v in p.items()} for _ in range(2))
    t, size = 0, 256
    for _ in range(40 if len(use) > 4000 else 200):
        for at in np.array_split(rng.permutation(use), max(1, len(use) // size)):
            t += 1
            h = np.tanh(z[at] @ p["w1"] + p["b1"])
            d = (1 / (1 + np.exp(-(h @ p["w2"] + p["b2"][0]))) - y[at]) / len(at)
            back = np.outer(d, p["w2"]) * (1 - h * h)
            grads = {"w1": z[at].T @ back + 1e-4 * p["w1"], "b1": back.sum(0), "w2": h.T @ d + 1e-4 * p["w2"], "b2": np.array([d.sum()])}
            for k, g in grads.items():
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                p[k] = p[k] - 0.005 * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.999**t)) + 1e-8)
    model = Model(vectors, mean, scale, p["w1"], p["b1"], p["w2"], float(p["b2"][0]), 1.0)
    logit = model.logits(x[check])
    choices = np.exp(np.linspace(np.log(0.25), np.log(8), 64))
    loss = [np.mean(np.logaddexp(0, -logit / c * (2 * y[check] - 1))) for c in choices]
    model.temperature = float(choices[int(np.argmin(loss))])
    return model


def scored(docs: DataFrame, model: Model | None, threshold: float = 0.3, folds: int = 5, held: int = 0) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs.

    A null or empty text is scored as a document without words. Without a model (no labels, or labels of one class) every
    score is 0.5. Rows are scored one by one: repeated rows give repeated results. A null doc_id is kept, with a null fold.
    """

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in steps(b):
                texts = b.column("text").slice(lo, hi - lo)
                s = model.scores(texts) if model else np.full(hi - lo, 0.5)
                yield batch(doc_id=b.column("doc_id").slice(lo, hi - lo), score=s.astype(np.float64))

    rows = docs.select("doc_id", "text").mapInArrow(tidy(step), "doc_id bigint, score double")
    return rows.select("doc_id", (fold("doc_id", folds) == held).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def accepted(docs: DataFrame, model: Model | None, threshold: float = 0.3) -> DataFrame:
    """The rows of docs, with all their columns, that score ``threshold`` or more; all of them without a model."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in steps(b):
                part = b.slice(lo, hi - lo)
                yield part.filter(pa.array(model.scores(part.column("text")) >= threshold))

    return docs.mapInArrow(tidy(step), docs.schema) if model else docs
