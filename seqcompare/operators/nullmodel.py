"""Synthetic sequences of the same number and lengths: by drawing q-mers of the data, or from a simple source.

``keys`` are columns of the sequences (a scope, a dataset) within which everything happens apart; they go along.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..rng import draw
from ..stages import settled
from .windows import mixed, numbered_md5

#: Sequences are dealt into so many ranges of addresses, so that no window is over all of them.
RANGES = 1024
#: Addresses of a block, at most 65,536: what is drawn meets the text of its block only.
BLOCK = 1 << 16
#: Draws of a chunk: its parts are put together in one step.
CHUNK = 1 << 21
#: Symbols of a synthetic part.
PART = 1 << 16


def sized(seq: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, seq_id, part_id, len) of all parts, made once: what is asked of lengths doesn't make the residues again."""
    return settled(seq.select(*keys, "seq_id", "part_id", F.length("residues").cast("bigint").alias("len")))


def addressed(seq: DataFrame, sizes: DataFrame, q: int, keys: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """(keys, src, lo, hi) and (keys, total): the range of addresses of each part's q-mers, and its text, compressed.

    Addresses run in order of (range, seq_id, part_id); the range of a sequence is a hash of its name. So the prefix sums
    are windows over the parts of a range, and one over at most ``RANGES`` rows of each key.
    """
    n, range_of = (F.col("len") - q + 1).alias("n"), F.pmod(draw("range", F.col("seq_id")), F.lit(RANGES)).cast("int").alias("range")
    of_range = sizes.where(F.col("len") >= q).select(*keys, n, range_of).groupBy(*keys, "range").agg(F.sum("n").alias("all"))
    upto_range = F.sum("all").over(Window.partitionBy(*keys).orderBy("range") if keys else Window.orderBy("range"))
    before = of_range.select(*keys, "range", (upto_range - F.col("all")).alias("before"))
    total = of_range.groupBy(*keys).agg(F.sum("all").alias("total"))
    whole = packed(seq.where(F.length("residues") >= q), keys).select(*keys, "seq_id", "part_id", "src", n, range_of)
    upto = F.sum("n").over(Window.partitionBy(*keys, "range").orderBy("seq_id", "part_id"))
    placed = whole.withColumn("upto", upto).join(F.broadcast(before) if not keys else before, [*keys, "range"])
    return placed.select(*keys, "src", (F.col("before") + F.col("upto") - F.col("n")).alias("lo"), (F.col("before") + F.col("upto")).alias("hi")), total


def _keyed(df: DataFrame, keys: tuple[str, ...]) -> str:
    kinds = dict(df.dtypes)
    return "".join(f"`{k}` {kinds[k]}, " for k in keys)


def _packed(text: str) -> bytes:
    return zlib.compress(text.encode(), 1)


def _unpacked(data: bytes) -> str:
    return zlib.decompress(data).decode()


def packed(seq: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, seq_id, part_id, len, src): residues compressed, as they are shuffled twice."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column("residues").to_pylist()
            rest = [b.column(c) for c in (*keys, "seq_id", "part_id")]
            yield pa.RecordBatch.from_arrays([*rest, pa.array([len(t) for t in texts], pa.int64()), pa.array([_packed(t) for t in texts], pa.binary())], names=[*keys, "seq_id", "part_id", "len", "src"])

    return seq.select(*keys, "seq_id", "part_id", "residues").mapInArrow(work, f"{_keyed(seq, keys)}seq_id string, part_id bigint, len bigint, src binary")


def blocks_of(placed: DataFrame, q: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, address_block, lo, src): parts cut at the blocks of addresses, each with the q - 1 symbols after it."""
    block = BLOCK

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, at, first, cut = [], [], [], []
            for n, (lo, hi, src) in enumerate(zip(*(b.column(c).to_pylist() for c in ("lo", "hi", "src")), strict=True)):
                whole = lo // block == (hi - 1) // block
                text = "" if whole else _unpacked(src)
                for own in range(lo // block, (hi - 1) // block + 1):
                    low, high = max(lo, own * block), min(hi, (own + 1) * block)
                    rows.append(n), at.append(own), first.append(low)
                    cut.append(src if whole else _packed(text[low - lo : high - lo + q - 1]))
            yield pa.RecordBatch.from_arrays([*(b.column(k).take(pa.array(rows, pa.int64())) for k in keys), pa.array(at, pa.int64()), pa.array(first, pa.int64()), pa.array(cut, pa.binary())], names=[*keys, "address_block", "lo", "src"])

    return placed.select(*keys, "src", "lo", "hi").mapInArrow(work, f"{_keyed(placed, keys)}address_block bigint, lo bigint, src binary")


def lengths(seq: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    return seq.groupBy(*keys, "seq_id").agg(F.sum(F.length("residues")).cast("bigint").alias("len"))


def bootstrap(seq: DataFrame, q: int, replicates: int, seed: int = 1, first: int = 0, keys: tuple[str, ...] = (), overlap: int = 0, only: DataFrame | None = None, sizes: DataFrame | None = None) -> DataFrame:
    """(keys, replicate, seq_id, part_id, offset, residues): q-mers of the whole data, drawn with replacement, until each length is reached.

    Draws are made by numpy for chunks of parts. Those of a chunk that fall in one block of addresses are one row, which meets
    the block's text, and what is drawn goes back to its chunk, which makes its draws again to know their places. A sequence comes in parts of ``PART`` symbols, with
    ``overlap`` symbols of the next part after each, so that windows across parts aren't lost. Sequences shorter than q give
    no q-mers but are made at their length; an error where no part has q symbols. With ``only`` (seq_id), just those
    sequences are made, from the q-mers of all. ``sizes``: of ``sized``, where they are there.
    """
    sizes = sized(seq, keys) if sizes is None else sizes
    placed, totals = addressed(seq, sizes, q, keys)
    if not keys and not totals.first()["total"]:
        raise ValueError(f"no sequence has {q} symbols")
    a_part = max(1, PART // q)
    wanted = sizes.groupBy(*keys, "seq_id").agg(F.sum("len").alias("len")).where("len > 0")
    if only is not None:
        wanted = wanted.join(only, [c for c in only.columns if c in wanted.columns], "left_semi")
    every = F.explode(F.sequence(F.lit(first), F.lit(first + replicates - 1))).alias("replicate")
    parts = wanted.select(*keys, "seq_id", "len", every).select("*", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("len") - 1) / (a_part * q)))).alias("part_id"))
    parts = parts.join(F.broadcast(totals), list(keys)) if keys else parts.join(F.broadcast(totals), F.lit(True))
    own = F.least(F.lit(a_part * q).cast("bigint") + overlap, F.col("len") - F.col("part_id") * (a_part * q))
    prefix = F.concat_ws("|", F.lit(str(seed)), *(F.col(k).cast("string") for k in (*keys, "replicate", "seq_id")))
    rows = parts.select(*keys, "replicate", "seq_id", "part_id", own.alias("own"), "total", prefix.alias("prefix"))
    # few rows become very many draws, which no estimate of sizes knows: dealt out first, in an order that makes chunks the same whenever
    # they are made, and the text's side is the one that is held
    dealt = rows.repartition(int(seq.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys, "replicate", "seq_id", "part_id").sortWithinPartitions(*keys, "replicate", "seq_id", "part_id")
    keyed, cut = _keyed(rows, keys), (q, a_part, BLOCK)
    drawn = dealt.mapInArrow(lambda batches, most=CHUNK: _draws(batches, keys, cut, most), f"{keyed}chunk string, address_block bigint, at binary, parts binary")
    # a block's text is handed on with the first row that meets it
    turn = F.row_number().over(Window.partitionBy(*keys, "address_block").orderBy("chunk"))
    texts = blocks_of(placed, q, keys).groupBy(*keys, "address_block").agg(F.array_sort(F.collect_list(F.struct("lo", "src"))).alias("texts"))
    met = drawn.withColumn("turn", turn).join(texts.hint("shuffle_hash"), [*keys, "address_block"])
    shown = met.select(*keys, "address_block", "chunk", "at", "parts", F.when(F.col("turn") == 1, F.col("texts")).alias("texts"))
    found = shown.mapInArrow(lambda batches: _pieces(batches, keys, q), "chunk string, address_block bigint, pieces binary, parts binary")
    return found.groupBy("chunk").applyInArrow(lambda table: _parts(table, keys, cut), f"{keyed}replicate int, seq_id string, part_id bigint, offset bigint, residues string")


def _symbols(text: str) -> np.ndarray:
    return np.frombuffer(text.encode(), np.uint8) if text.isascii() else np.frombuffer(text.encode("utf-32-le"), "<u4")


def _text(symbols: np.ndarray) -> str:
    return symbols.tobytes().decode("ascii" if symbols.dtype == np.uint8 else "utf-32-le")


def _addresses(parts: pa.RecordBatch | pa.Table, q: int, a_part: int) -> tuple[np.ndarray, np.ndarray]:
    """What a chunk's parts draw, and in which order it is looked up."""
    rows = zip(*(parts.column(c).to_pylist() for c in ("prefix", "part_id", "own")), strict=True)
    numbers = np.concatenate([numbered_md5(prefix, n * a_part, n * a_part + (own - 1) // q + 1) for prefix, n, own in rows])
    address = numbers % parts.column("total")[0].as_py()
    return address, np.argsort(address, kind="stable")


def _draws(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...], cut: tuple[int, int, int], most: int) -> Iterator[pa.RecordBatch]:
    """For each chunk of parts and each block of addresses, the steps from draw to draw. A chunk's first row has its parts, too."""
    q, a_part, block = cut
    for b in batches:
        many = (b.column("own").to_numpy() - 1) // q + 1
        names = list(zip(*(b.column(c).to_pylist() for c in (*keys, "replicate", "seq_id", "part_id")), strict=True))
        # parts of one key, up to so many draws together
        ends, held = [], 0
        for n in range(len(names)):
            if n and (held + many[n] > most or names[n][: len(keys)] != names[n - 1][: len(keys)]):
                ends.append(n)
                held = 0
            held += many[n]
        for lo, hi in zip([0, *ends], [*ends, len(names)], strict=True):
            if lo == hi:
                continue
            parts = b.slice(lo, hi - lo)
            address, order = _addresses(parts, q, a_part)
            address = address[order]
            to = address // block
            firsts = np.flatnonzero(np.append(True, to[1:] != to[:-1]))
            steps = np.diff(address, prepend=0)
            steps[firsts] = address[firsts] - block * to[firsts]
            at = [zlib.compress(x.tobytes(), 1) for x in np.split(steps.astype("<u2"), firsts[1:])]
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, parts.schema) as out:
                out.write_batch(parts)
            key = [pa.array([x] * len(at), b.schema.field(k).type) for k, x in zip(keys, names[lo], strict=False)]
            whole = pa.array([zlib.compress(sink.getvalue().to_pybytes(), 1)] + [None] * (len(at) - 1), pa.binary())
            yield pa.RecordBatch.from_arrays([*key, pa.array([repr(names[lo])] * len(at)), pa.array(to[firsts]), pa.array(at, pa.binary()), whole], names=[*keys, "chunk", "address_block", "at", "parts"])


def _pieces(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...], q: int) -> Iterator[pa.RecordBatch]:
    """What is drawn from a block: its text comes with the first of its rows."""
    held, starts, symbols, span = None, np.zeros(0, np.int64), np.zeros(0, np.uint8), np.arange(q)
    for b in batches:
        names, found = list(zip(*(b.column(c).to_pylist() for c in (*keys, "address_block")), strict=True)), []
        for n, name in enumerate(names):
            if b.column("texts")[n].is_valid:
                texts = b.column("texts")[n].as_py()
                held, symbols = name, _symbols("".join(_unpacked(x["src"]) for x in texts))
                starts = np.array([x["lo"] for x in texts]) - texts[0]["lo"]
            elif held != name:
                raise RuntimeError("rows of a block came apart from its text")
            at = np.cumsum(np.frombuffer(zlib.decompress(b.column("at")[n].as_py()), "<u2"), dtype=np.int64)
            # each part's text has q - 1 symbols after its own addresses
            place = at + (np.searchsorted(starts, at, "right") - 1) * (q - 1)
            found.append(_packed(_text(symbols[place[:, None] + span])))
        yield pa.RecordBatch.from_arrays([b.column("chunk"), b.column("address_block"), pa.array(found, pa.binary()), b.column("parts")], names=["chunk", "address_block", "pieces", "parts"])


def _parts(table: pa.Table, keys: tuple[str, ...], cut: tuple[int, int, int]) -> pa.Table:
    """The synthetic parts of a chunk."""
    q, a_part, _ = cut
    table = table.sort_by("address_block")
    whole = next(x for x in table.column("parts") if x.is_valid)
    parts = pa.ipc.open_stream(zlib.decompress(whole.as_py())).read_all()
    own, part_id = parts.column("own").to_numpy(), parts.column("part_id").to_numpy()
    order = _addresses(parts, q, a_part)[1]
    pieces = _symbols("".join(_unpacked(x.as_py()) for x in table.column("pieces"))).reshape(-1, q)
    made = np.empty_like(pieces)
    made[order] = pieces
    flat, ends = made.ravel(), q * np.cumsum((own - 1) // q + 1)
    residues = [_text(flat[lo : lo + n]) for lo, n in zip([0, *ends[:-1].tolist()], own.tolist(), strict=True)]
    columns = [*(parts.column(c) for c in (*keys, "replicate", "seq_id", "part_id")), pa.array(part_id * (a_part * q)), pa.array(residues, pa.string())]
    return pa.table(columns, names=[*keys, "replicate", "seq_id", "part_id", "offset", "residues"])


def uniform(seq: DataFrame, alphabet: str, replicates: int, seed: int = 1) -> DataFrame:
    """Symbols of an even, independent source."""
    places = F.sequence(F.lit(0), F.col("len").cast("int") - 1)
    grid = lengths(seq).where("len > 0").select("seq_id", "len", F.explode(F.sequence(F.lit(0), F.lit(replicates - 1))).alias("replicate"))
    symbol = lambda i: F.substring(F.lit(alphabet), (F.pmod(draw(seed, F.col("replicate"), F.col("seq_id"), i), F.lit(len(alphabet))) + 1).cast("int"), F.lit(1))
    return grid.select("replicate", "seq_id", F.lit(0).cast("bigint").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), F.array_join(F.transform(places, symbol), "").alias("residues"))


def _chains(texts: list[str], names: list[str], order: int, replicates: int, seed: int) -> list[list[str]]:
    """Synthetic texts of each replicate: all chains take a step at once, each by its own text's transitions."""
    kinds = {c: i for i, c in enumerate(sorted({c for t in texts for c in t}))}
    many, size = max(1, len(kinds)), np.array([len(t) for t in texts])
    code = [np.array([kinds[c] for c in t], np.int64) for t in texts]
    contexts, follow = [], []
    for s, c in enumerate(code):
        state = np.full(max(0, len(c) - order), s, np.int64)
        for k in range(order):
            state = state * many + c[k : k + len(state)]
        contexts.append(state)
        follow.append(c[order:])
    context, nxt = np.concatenate(contexts), np.concatenate(follow)
    by = np.argsort(context, kind="stable")
    context, nxt = context[by], nxt[by]
    flat, first = np.concatenate(code), np.cumsum(size) - size
    who = np.tile(np.arange(len(texts)), replicates)
    salt = np.array([mixed(np.frombuffer(n.encode().ljust(8 * (1 + len(n.encode()) // 8), b"\0"), "<u8").astype(np.uint64)).sum(dtype=np.uint64) for n in names], np.uint64)
    own = mixed(salt[who] + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15) + np.repeat(np.arange(replicates, dtype=np.uint64), len(texts)) * np.uint64(0xD1B54A32D192ED03))
    top = int(size.max(initial=0))
    made = np.zeros((len(who), top), np.int64)
    for t in range(top):
        live = np.flatnonzero(size[who] > t)
        mine = who[live]
        if t < order:
            made[live, t] = flat[first[mine] + t]
            continue
        state = mine.copy()
        for k in range(order):
            state = state * many + made[live, t - order + k]
        lo, hi = np.searchsorted(context, state, "left"), np.searchsorted(context, state, "right")
        number = (mixed(own[live] + np.uint64(t + 1)) >> np.uint64(1)).astype(np.int64)
        seen = hi > lo
        made[live, t] = np.where(seen, nxt[np.minimum(lo + number % np.maximum(hi - lo, 1), max(0, len(nxt) - 1))] if len(nxt) else 0, flat[first[mine] + number % size[mine]])
    letters = np.array(list(kinds) or [""])
    return [["".join(letters[made[r * len(texts) + s, : size[s]]]) for s in range(len(texts))] for r in range(replicates)]


def markov(seq: DataFrame, order: int, replicates: int, seed: int = 1) -> DataFrame:
    """Each sequence's own transitions of the given order; unseen contexts fall back to its symbols."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, texts = b.column("seq_id").to_pylist(), b.column("residues").to_pylist()
            for lo in range(0, len(texts), 256):
                own = names[lo : lo + 256]
                for r, made in enumerate(_chains(texts[lo : lo + 256], own, order, replicates, seed)):
                    zero = pa.array(np.zeros(len(own), np.int64))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), r, np.int32)), pa.array(own), zero, zero, pa.array(made)], names=["replicate", "seq_id", "part_id", "offset", "residues"])

    return _whole(seq).mapInArrow(work, "replicate int, seq_id string, part_id bigint, offset bigint, residues string")


def shuffled(seq: DataFrame, replicates: int, seed: int = 1) -> DataFrame:
    """Each sequence's own symbols in another order."""
    grid = _whole(seq).select("seq_id", "residues", F.explode(F.sequence(F.lit(0), F.lit(replicates - 1))).alias("replicate"))
    tagged = F.transform(F.split("residues", ""), lambda c, i: F.struct(draw(seed, F.col("replicate"), F.col("seq_id"), i).alias("r"), c.alias("c")))
    return grid.select("replicate", "seq_id", F.lit(0).cast("bigint").alias("part_id"), F.lit(0).cast("bigint").alias("offset"), F.array_join(F.transform(F.array_sort(tagged), lambda x: x.c), "").alias("residues"))


def _whole(seq: DataFrame) -> DataFrame:
    """Sequences in one row each: a chain and a permutation go through a whole sequence."""
    parts = seq.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("part_id", "offset", "residues"))).alias("p"))
    return parts.select("seq_id", F.array_join(F.transform("p", lambda x: x.residues), "").alias("residues"))


def generate(seq: DataFrame, model: str = "bootstrap", replicates: int = 100, seed: int = 1, **options) -> DataFrame:
    """``bootstrap`` takes q, keys, overlap and only; ``uniform`` an alphabet, ``markov`` an order."""
    if model == "bootstrap":
        return bootstrap(seq, options.pop("q", 1), replicates, seed, **options)
    if model == "uniform":
        return uniform(seq, options.get("alphabet", "ACGT"), replicates, seed)
    return {"markov": lambda: markov(seq, options.get("order", 1), replicates, seed), "shuffle": lambda: shuffled(seq, replicates, seed)}[model]()

