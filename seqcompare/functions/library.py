"""Histogram pair functions in sparse form: sums over shared features, totals of each sequence, and for two of them a
correction for absent words by symbol composition. So one inner self-join serves all of them, several in one pass.

Names, and whether a value is a distance (less is closer) or a similarity, are in ``REGISTRY``. Only some of the eighteen
are named by the methods' source; the others are common ones of the literature.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from math import comb, factorial, log

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

Terms = dict[str, Column]


@dataclass(frozen=True)
class PairFunction:
    """``terms``: for each shared feature, from values x, y, shares p, q and expectations e, f (only functions with a
    background use these); ``finish`` makes the value from their sums t and the totals a, b of both sequences.
    ``numpy_terms`` are the same for vectorised plans. ``reduce`` of terms is sum or max. With a background, ``gain`` is what
    any word adds, and what words outside a pair's shared ones add is worked out by composition (``plans.matrix``).
    """

    name: str
    kind: str
    terms: Callable[..., Terms]
    finish: Callable[[Terms, "Side", "Side"], Column]
    numpy_terms: Callable[..., dict[str, np.ndarray]]
    reduce: str = "sum"
    background: bool = False
    extreme: bool = False
    gain: Callable | None = None
    options: dict = field(default_factory=dict)


class Side:
    """Totals of one sequence of a pair: ``a.total`` is a column of the joined rows."""

    def __init__(self, prefix: str):
        self.prefix = prefix

    def __getattr__(self, name: str) -> Column:
        return F.col(f"{self.prefix}_{name}").cast("double")


REGISTRY: dict[str, Callable[..., PairFunction]] = {}


def register_function(name: str, kind: str, **more):
    """Register a pair function by a maker of (terms, finish); terms are written once, for columns and for numpy arrays.

    ``terms(m, x, y, p, q)`` gets the module of functions: ``m.least``, ``m.sqrt``, ``m.log``, ``m.abs``. With
    ``background=True`` it is ``gain(m, x, y, e, f)`` that is given in its place, with expectations e and f.
    """

    def put(make: Callable) -> Callable:
        def build(**options) -> PairFunction:
            terms, finish = make(**options)
            if more.get("background"):
                gain = terms
                # what a shared word adds beyond what it adds where it is in one of the two, or in none
                beyond = lambda m, x, y, e, f: {name: gain(m, x, y, e, f) - gain(m, x, m.zero(y), e, f) - gain(m, m.zero(x), y, e, f) + gain(m, m.zero(x), m.zero(y), e, f)}
                return PairFunction(name, kind, lambda x, y, p, q, e, f: beyond(_Columns, x, y, e, f), finish, lambda x, y, p, q, e, f: beyond(_Arrays, x, y, e, f), gain=lambda x, y, e, f: gain(_Arrays, x, y, e, f), options=options, **more)
            return PairFunction(name, kind, lambda x, y, p, q, e, f: terms(_Columns, x, y, p, q), finish, lambda x, y, p, q, e, f: terms(_Arrays, x, y, p, q), options=options, **more)

        REGISTRY[name] = build
        return make

    return put


class _Columns:
    least, sqrt, log, abs = staticmethod(F.least), staticmethod(F.sqrt), staticmethod(F.log), staticmethod(F.abs)

    @staticmethod
    def ones(x: Column) -> Column:
        return F.when(x.isNotNull(), 1.0)

    @staticmethod
    def zero(x: Column) -> Column:
        return F.lit(0.0)

    @staticmethod
    def over(value: Column, size: Column) -> Column:
        return F.when(size > 0, value / size).otherwise(0.0)


class _Arrays:
    least, sqrt, log, abs = np.minimum, np.sqrt, np.log, np.abs

    @staticmethod
    def ones(x: np.ndarray) -> np.ndarray:
        return np.ones_like(x)

    @staticmethod
    def zero(x: np.ndarray) -> np.ndarray:
        return np.zeros_like(x)

    @staticmethod
    def over(value: np.ndarray, size: np.ndarray) -> np.ndarray:
        return np.divide(value, size, out=np.zeros(np.broadcast_shapes(np.shape(value), np.shape(size))), where=size > 0)


def get(name: str, **options) -> PairFunction:
    if name not in REGISTRY:
        raise KeyError(f"no pair function {name}; there are {', '.join(sorted(REGISTRY))}")
    return REGISTRY[name](**options)


def _or_zero(value: Column, divisor: Column) -> Column:
    return F.when(divisor != 0, value / divisor).otherwise(0.0)


@register_function("d2", "similarity")
def _d2(as_distance: bool = False):
    def finish(t, a, b):
        return -F.log(t["xy"] / F.sqrt(a.sumsq * b.sumsq)) if as_distance else t["xy"]

    return lambda m, x, y, p, q: {"xy": x * y}, finish


@register_function("d2z", "similarity")
def _d2z(words: int, moments: str = "words"):
    """Counts as z-scores, then their inner product.

    ``moments``: mean and deviation of a count over the dictionary of ``words`` words; ``iid``: those of a word's count where
    all words are equally likely at each of the sequence's places; ``null``: d2 is brought to the scale of its null values
    afterwards (``operators.significance.standardised``), so that here it is d2 itself.
    """
    if moments not in ("words", "iid", "null"):
        raise ValueError("moments are words, iid or null")

    def finish(t, a, b):
        if moments == "null":
            return t["xy"]
        mean_a, mean_b = a.total / words, b.total / words
        if moments == "iid":
            sd = F.sqrt(mean_a * (1 - 1 / words) * mean_b * (1 - 1 / words))
        else:
            sd = F.sqrt((a.sumsq / words - mean_a * mean_a) * (b.sumsq / words - mean_b * mean_b))
        return _or_zero(t["xy"] - mean_a * mean_b * words, sd)

    return lambda m, x, y, p, q: {"xy": x * y}, finish


@register_function("euclidean", "distance")
def _euclidean():
    return lambda m, x, y, p, q: {"xy": x * y}, lambda t, a, b: F.sqrt(F.greatest(a.sumsq + b.sumsq - 2 * t["xy"], F.lit(0.0)))


@register_function("sqeuclidean", "distance")
def _sqeuclidean():
    return lambda m, x, y, p, q: {"xy": x * y}, lambda t, a, b: a.sumsq + b.sumsq - 2 * t["xy"]


@register_function("manhattan", "distance")
def _manhattan():
    return lambda m, x, y, p, q: {"low": m.least(x, y)}, lambda t, a, b: a.total + b.total - 2 * t["low"]


@register_function("canberra", "distance")
def _canberra():
    return lambda m, x, y, p, q: {"both": m.ones(x), "off": m.abs(x - y) / (x + y)}, lambda t, a, b: a.distinct + b.distinct - 2 * t["both"] + t["off"]


@register_function("chisq", "distance")
def _chisq():
    return lambda m, x, y, p, q: {"harm": x * y / (x + y)}, lambda t, a, b: a.total + b.total - 4 * t["harm"]


@register_function("sqchord", "distance")
def _sqchord():
    return lambda m, x, y, p, q: {"root": m.sqrt(x * y)}, lambda t, a, b: a.total + b.total - 2 * t["root"]


@register_function("harmonic", "similarity")
def _harmonic():
    return lambda m, x, y, p, q: {"harm": x * y / (x + y)}, lambda t, a, b: 2 * t["harm"]


@register_function("intersection", "similarity")
def _intersection(bray_curtis: bool = False):
    return lambda m, x, y, p, q: {"low": m.least(x, y)}, lambda t, a, b: 1 - 2 * t["low"] / (a.total + b.total) if bray_curtis else t["low"]


@register_function("kulczynski2", "similarity")
def _kulczynski2():
    return lambda m, x, y, p, q: {"low": m.least(x, y)}, lambda t, a, b: (t["low"] / a.total + t["low"] / b.total) / 2


@register_function("jaccard", "similarity")
def _jaccard(weighted: bool = False):
    if weighted:
        return lambda m, x, y, p, q: {"low": m.least(x, y)}, lambda t, a, b: t["low"] / (a.total + b.total - t["low"])
    return lambda m, x, y, p, q: {"both": m.ones(x)}, lambda t, a, b: t["both"] / (a.distinct + b.distinct - t["both"])


@register_function("jsd", "distance")
def _jsd(sqrt: bool = False):
    def terms(m, x, y, p, q):
        return {"js": p * m.log(2 * p / (p + q)) + q * m.log(2 * q / (p + q)), "pq": p + q}

    def finish(t, a, b):
        value = 0.5 * t["js"] + 0.5 * log(2) * (2 - t["pq"])
        return F.sqrt(F.greatest(value, F.lit(0.0))) if sqrt else value

    return terms, finish


@register_function("cosine", "similarity")
def _cosine():
    return lambda m, x, y, p, q: {"xy": x * y}, lambda t, a, b: t["xy"] / F.sqrt(a.sumsq * b.sumsq)


@register_function("angle", "distance")
def _angle():
    return lambda m, x, y, p, q: {"xy": x * y}, lambda t, a, b: F.acos(F.least(t["xy"] / F.sqrt(a.sumsq * b.sumsq), F.lit(1.0)))


@register_function("containment", "similarity")
def _containment():
    return lambda m, x, y, p, q: {"both": m.ones(x)}, lambda t, a, b: t["both"] / a.distinct


@register_function("minkowski3", "distance")
def _minkowski3():
    """Order three: the sums of cubes outside what is shared are the totals less the shared part."""
    return lambda m, x, y, p, q: {"off3": m.abs(x - y) * m.abs(x - y) * m.abs(x - y), "x3": x * x * x, "y3": y * y * y}, lambda t, a, b: F.pow(a.sumcube - t["x3"] + b.sumcube - t["y3"] + t["off3"], 1 / 3)


@register_function("jeffrey", "distance")
def _jeffrey(words: int, epsilon: float = 1.0):
    """Symmetrised divergence of counts with ``epsilon`` added to each word of the dictionary.

    Words in one sequence only are its own sum less the shared part, words in neither all give one constant.
    """

    def terms(m, x, y, p, q):
        lx, ly = m.log(x + epsilon), m.log(y + epsilon)
        return {"x": x, "y": y, "lx": lx, "ly": ly, "xlx": x * lx, "yly": y * ly, "xly": x * ly, "ylx": y * lx, "both": m.ones(x)}

    def finish(t, a, b):
        na, nb = a.total + words * epsilon, b.total + words * epsilon
        c, le, shift = float(epsilon), log(epsilon), F.log(na) - F.log(nb)
        # sum over words of ((X+e)/na - (Y+e)/nb) (ln(X+e) - ln(Y+e) - shift)
        only_x = (a.sumxlog + c * a.sumlog) / na - le * (a.total + c * a.distinct) / na - c / nb * (a.sumlog - le * a.distinct)
        shared_x = (t["xlx"] + c * t["lx"]) / na - le * (t["x"] + c * t["both"]) / na - c / nb * (t["lx"] - le * t["both"])
        only_y = (b.sumxlog + c * b.sumlog) / nb - le * (b.total + c * b.distinct) / nb - c / na * (b.sumlog - le * b.distinct)
        shared_y = (t["yly"] + c * t["ly"]) / nb - le * (t["y"] + c * t["both"]) / nb - c / na * (t["ly"] - le * t["both"])
        shared = (t["xlx"] + c * t["lx"] - t["xly"] - c * t["ly"]) / na - (t["ylx"] + c * t["lx"] - t["yly"] - c * t["ly"]) / nb
        return only_x - shared_x + only_y - shared_y + shared  # the shift's factor sums to 0 over all words

    return terms, finish


@register_function("chebyshev", "distance", reduce="max", extreme=True)
def _chebyshev():
    """The largest difference: over shared words here; over the others in the plan, from ranks (``plans.matrix``)."""
    return lambda m, x, y, p, q: {"off": m.abs(x - y)}, lambda t, a, b: F.greatest(t["off"], F.col("a_alone"), F.col("b_alone"))


@register_function("d2s", "similarity", background=True)
def _d2s():
    """Products of counts less their expectation, over the root of the sum of squares; absent words by composition."""
    return lambda m, x, y, e, f: m.over((x - e) * (y - f), m.sqrt((x - e) * (x - e) + (y - f) * (y - f))), lambda t, a, b: t["d2s"] + F.col("d2s_rest")


@register_function("d2star", "similarity", background=True)
def _d2star():
    """Products of counts less their expectation, over the root of the product of expectations."""
    return lambda m, x, y, e, f: m.over((x - e) * (y - f), m.sqrt(e * f)), lambda t, a, b: t["d2star"] + F.col("d2star_rest")


def classes(alphabet: str, k: int) -> list[tuple[str, int]]:
    """Compositions of words of k symbols with their number of words."""
    out = []

    def put(at: int, left: int, counts: list[int]) -> None:
        if at == len(alphabet) - 1:
            n = [*counts, left]
            size = factorial(k)
            for c in n:
                size //= factorial(c)
            out.append(("".join(s * c for s, c in zip(sorted(alphabet), n, strict=True)), size))
            return
        for c in range(left + 1):
            put(at + 1, left - c, [*counts, c])

    put(0, k, [])
    assert len(out) == comb(k + len(alphabet) - 1, len(alphabet) - 1)
    return out


#: The eighteen of the library: these over histograms, then the sketch and the spaced-word distance.
HISTOGRAM = ("d2", "d2s", "d2star", "d2z", "chebyshev", "euclidean", "sqeuclidean", "manhattan", "canberra", "chisq", "sqchord", "harmonic", "intersection", "kulczynski2", "jaccard", "jsd")
EIGHTEEN = (*HISTOGRAM, "minhash", "spaced")
CONSISTENT = ("d2", "d2star", "spaced")
