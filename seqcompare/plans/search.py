"""Chosen sequences against all others: the values of the functions for every pair of a query and another sequence.

Sequences are dealt out by blocks, and a task sets each of its blocks against all queries at once, so that neither a shared
feature nor a pair is a row of a shuffle. The queries are a small share of the sequences and are sent to every task.
"""

from __future__ import annotations

import pickle
import re
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.library import PairFunction, Side, get

#: Pairs that a task holds of one block of sequences, and sequences of a block at most.
PAIRS, BLOCK = 400_000, 1024
#: Features that are laid out side by side at a time.
SPAN = 4096
#: Queries that are packed together.
TOGETHER = 256
#: The term that is one product of matrices.
PRODUCT = "sum_xy"

_TOTALS = {
    "total": lambda v: v, "distinct": np.ones_like, "sumsq": lambda v: v * v, "sumsqrt": np.sqrt, "sumcube": lambda v: v * v * v,
    "sumlog": lambda v: np.log(v + 1), "sumxlog": lambda v: v * np.log(v + 1),
}


def _coded(column: pa.ChunkedArray) -> tuple[pa.Array, np.ndarray]:
    coded = column.combine_chunks()
    coded = (coded.combine_chunks() if isinstance(coded, pa.ChunkedArray) else coded).dictionary_encode()
    return coded.dictionary, coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)


class _Block:
    """Statistics of some sequences in ``copies`` datasets, one row for each feature of (copy, sequence)."""

    def __init__(self, table: pa.Table, copies: int):
        (self.names, name), (self.features, feature) = (_coded(table.column(c)) for c in ("seq_id", "feature"))
        self.copies, self.n, many = copies, len(self.names), max(1, len(self.features))
        key, at = np.unique((table.column("copy").to_numpy() * self.n + name) * many + feature, return_inverse=True)
        self.value = np.bincount(at, table.column("value").to_numpy().astype(float), len(key))
        self.row, self.feature = (key // many).astype(np.int32), (key % many).astype(np.int32)
        self.total = self.sums("total")

    def sums(self, name: str) -> np.ndarray:
        with np.errstate(invalid="ignore", divide="ignore"):
            return np.bincount(self.row, _TOTALS[name](self.value), self.copies * self.n)

    def dense(self, copy: int, place: np.ndarray, lo: int, wide: int) -> tuple[np.ndarray, np.ndarray]:
        """Values and shares of a dataset's sequences over the features at places lo to lo + wide; not a number where there is none."""
        at = place[self.feature]
        mine = (self.row // self.n == copy) & (at >= lo) & (at < lo + wide)
        out = np.full((self.n, wide), np.nan)
        out[self.row[mine] % self.n, at[mine] - lo] = self.value[mine]
        own = self.total[copy * self.n : (copy + 1) * self.n, None]
        return out, np.divide(out, own, out=np.zeros_like(out), where=own > 0)

    def outside(self, copy: int, place: np.ndarray) -> np.ndarray:
        """The largest value of each sequence among features without a place."""
        out = np.zeros(self.n)
        mine = (self.row // self.n == copy) & (place[self.feature] < 0)
        np.maximum.at(out, self.row[mine] % self.n, self.value[mine])
        return out


def _terms(queries: _Block, rows: _Block, copy: int, functions: list[PairFunction], names: list[str]) -> dict[str, np.ndarray]:
    """Reduced terms, and the largest value that each of a pair has alone, of all queries and rows of a dataset."""
    shape = (queries.n, rows.n)
    where = {f: n for n, f in enumerate(queries.features.to_pylist())}
    theirs, own = np.array([where.get(f, -1) for f in rows.features.to_pylist()], np.int64), np.arange(len(where))
    out = {n: np.zeros(shape) for n in names}
    others = [f for f in functions if {f"{f.reduce}_{n}" for n in f.numpy_terms(*(np.ones(1) for _ in range(6)))} != {PRODUCT}]
    alone = any(f.extreme for f in functions)
    if alone:
        out |= {"a_alone": np.zeros(shape), "b_alone": np.repeat(rows.outside(copy, theirs)[None], queries.n, 0)}
    for lo in range(0, len(where), SPAN):
        wide = min(SPAN, len(where) - lo)
        (x, p), (y, q) = queries.dense(copy, own, lo, wide), rows.dense(copy, theirs, lo, wide)
        if PRODUCT in out:
            out[PRODUCT] += np.nan_to_num(x) @ np.nan_to_num(y).T
        if not others:
            continue
        there = ~np.isnan(y)
        step = max(1, (1 << 20) // max(1, wide))
        for at in range(0, rows.n, step):
            cut = slice(at, at + step)
            for n in range(queries.n):
                has = np.flatnonzero(~np.isnan(x[n]))
                yy, met = y[cut][:, has], there[cut][:, has]
                shape_of = yy.shape
                xx, pp, zero = np.broadcast_to(x[n, has], shape_of), np.broadcast_to(p[n, has], shape_of), np.zeros(shape_of)
                done = {PRODUCT}
                for f in others:
                    for name, t in f.numpy_terms(xx, yy, pp, q[cut][:, has], zero, zero).items():
                        name = f"{f.reduce}_{name}"
                        if name in done:
                            continue
                        done.add(name)
                        t = np.where(met, t, 0.0)
                        if f.reduce == "sum":
                            out[name][n, cut] += t.sum(axis=1)
                        elif len(has):
                            out[name][n, cut] = np.maximum(out[name][n, cut], t.max(axis=1))
                if alone:
                    if len(has):
                        out["a_alone"][n, cut] = np.maximum(out["a_alone"][n, cut], np.where(met, 0.0, xx).max(axis=1))
                    lacks = np.flatnonzero(np.isnan(x[n]))
                    if len(lacks):
                        out["b_alone"][n, cut] = np.maximum(out["b_alone"][n, cut], np.nan_to_num(y[cut][:, lacks]).max(axis=1))
    return out


def _ones() -> tuple[Column, ...]:
    return tuple(F.lit(1.0) for _ in range(6))


def _value(f: PairFunction, copy: int) -> Column:
    return f.finish({n: F.col(f"{f.reduce}_{n}_{copy}") for n in f.terms(*_ones())}, Side(f"a{copy}"), Side(f"b{copy}"))


def _totals_of(f: PairFunction, copy: int) -> list[str]:
    """Columns of totals that a function's value is made of."""
    return re.findall(rf"\b[ab]{copy}_(?:{'|'.join(_TOTALS)})\b", str(_value(f, copy)))


def values(chosen: DataFrame, stat: DataFrame, functions: list[str | PairFunction], copies: int = 1) -> DataFrame:
    """(i, j, <function>_<copy>, ...): a row for each query i and other sequence j, with the values in each dataset.

    ``chosen`` and ``stat`` are rows of (copy, seq_id, feature, value); rows of one feature are summed. Without a column
    ``copy`` there is one dataset, 0. Functions with a background aren't served here.
    """
    made = [f if isinstance(f, PairFunction) else get(f) for f in functions]
    if any(f.background for f in made):
        raise ValueError("functions with a background are for the matrix plans")
    if copies > 1 and any(f.extreme for f in made):
        raise ValueError("the largest difference is for one dataset at a time")
    spark = stat.sparkSession
    chosen, stat = (df if "copy" in df.columns else df.withColumn("copy", F.lit(0)) for df in (chosen, stat))
    chosen, stat = (df.select(F.col("copy").cast("bigint").alias("copy"), "seq_id", "feature", F.col("value").cast("double").alias("value")) for df in (chosen, stat))

    def pack(table: pa.Table) -> pa.Table:
        block = _Block(table, copies)
        return pa.table({"n": pa.array([block.n], pa.int64()), "block": pa.array([pickle.dumps(vars(block), 5)], pa.binary())})

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    asked = chosen.withColumn("deal", F.pmod(F.xxhash64("seq_id"), F.lit(max(1, -(-_sequences(chosen) // TOGETHER)))))
    packed = asked.groupBy("deal").applyInArrow(pack, "n bigint, block binary").collect()
    many = sum(r.n for r in packed)
    sent = spark.sparkContext.broadcast([bytes(r.block) for r in packed])
    size = max(16, min(BLOCK, PAIRS // max(1, many)))
    blocks = max(parts, -(-_sequences(stat) // size))
    names = [f"{f.reduce}_{n}" for f in made for n in f.terms(*_ones())]
    names = list(dict.fromkeys(names))
    alone = ["a_alone", "b_alone"] if any(f.extreme for f in made) else []
    sides = sorted({c for copy in range(copies) for f in made for c in _totals_of(f, copy)})
    terms = [f"{n}_{copy}" for copy in range(copies) for n in (*names, *alone)]

    def work(table: pa.Table) -> pa.Table:
        rows = _Block(table, copies)
        theirs = rows.names.to_pylist()
        out = []
        for block in sent.value:
            queries = _Block.__new__(_Block)
            vars(queries).update(pickle.loads(block))
            mine = queries.names.to_pylist()
            i, j = (x.ravel() for x in np.meshgrid(np.arange(queries.n), np.arange(rows.n), indexing="ij"))
            place = {n: k for k, n in enumerate(theirs)}
            same = np.array([k * rows.n + place[n] for k, n in enumerate(mine) if n in place], np.int64)
            kept = np.ones(len(i), bool)
            kept[same] = False
            i, j = i[kept], j[kept]
            found = {}
            for copy in range(copies):
                for n, x in _terms(queries, rows, copy, made, names).items():
                    found[f"{n}_{copy}"] = x.ravel()[kept]
            for c in sides:
                of, at = (queries, i) if c[0] == "a" else (rows, j)
                copy, name = c[1:].split("_", 1)
                found[c] = of.sums(name)[int(copy) * of.n + at]
            out.append(pa.table({"i": queries.names.take(pa.array(i)), "j": rows.names.take(pa.array(j)), **{c: pa.array(found[c]) for c in (*terms, *sides)}}))
        return pa.concat_tables(out) if out else pa.table({c: pa.array([], t) for c, t in (("i", pa.string()), ("j", pa.string()), *((c, pa.float64()) for c in (*terms, *sides)))})

    schema = ", ".join(["i string", "j string", *(f"`{c}` double" for c in (*terms, *sides))])
    wide = stat.withColumn("deal", F.pmod(F.xxhash64("seq_id"), F.lit(blocks))).groupBy("deal").applyInArrow(work, schema)
    base = wide.withColumns({c: F.col(f"{c}_0") for c in alone}) if alone else wide
    return base.select("i", "j", *(_value(f, copy).cast("double").alias(f"{f.name}_{copy}") for copy in range(copies) for f in made))


def _sequences(stat: DataFrame) -> int:
    return stat.select("seq_id").distinct().count()


def compute(chosen: DataFrame, stat: DataFrame, functions: list[str | PairFunction]) -> DataFrame:
    """(fn, i, j, value): every query i and every other sequence j."""
    made = [f if isinstance(f, PairFunction) else get(f) for f in functions]
    each = F.explode(F.array(*(F.struct(F.lit(f.name).alias("fn"), F.col(f"{f.name}_0").alias("value")) for f in made)))
    return values(chosen, stat, made).select("i", "j", each.alias("r")).select("r.fn", "i", "j", "r.value")
