"""Language-model scoring by a probabilistic suffix tree over words.

States of the tree are contexts of one to ``DEPTH`` preceding words. A context that was seen twice lists the words that
followed it twice or more, discounted; what is left over goes to the distribution of its suffix, and at the root to add-one
word counts. A context is kept where its next words diverge from its suffix's by more than the description of its list
costs. A token is scored in the longest kept state that its preceding words end in. What is enough doesn't depend on how
large the corpus is: whatever repeats is learned.

All contexts that end in one word, their next words and the tokens that are scored in them meet in one bucket, dealt by that
word, so that the tree is counted, judged and used there, and only sums for rows leave it. A task hands on the tokens of a
chunk as compressed blocks, with their preceding words as places in a dictionary of the block. A word with more tokens than
a bucket should have is dealt to several by the word before it; what follows just that word is counted before, and goes to
each of them. Words' counts are broadcast in parts of a bounded size, and a task holds one of them at a time.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, batch, fold, got, mixed, sent, signed, steps, tidy, written

#: Words' counts are broadcast in parts of about twice 1 / share words.
HEAD_SHARE = 1e-6
#: A next word is listed when it was seen so many times after a context, and a context is a candidate from so many times on.
JOINT_MIN = 2
CONTEXT_MIN = 2
DEPTH = 3
DISCOUNT = 0.5
#: Words with this share of the tokens are dealt to several buckets where they have more tokens than a bucket should.
HOT_SHARE = 1e-3
#: Words or pairs that a task counts before it hands them on, and tokens that it deals at once.
FLUSH, CHUNK = 4_000_000, 2_200_000
#: Compressed bytes of a bucket whose tokens are worked on at once.
PIECE = 7 << 20
#: The end of a document, and the mark before its first word, as words' hashes.
END = np.uint64(0xE5D0F7EC70000)
START = np.uint64(0x57A270000)
#: Words go by 48 bits of their hash: two of 50 million words share them some four times.
_LOW = np.uint64(16)
_ODD, _TAG = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD1B54A32D192ED03)


def token_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of lower-cased words with an end after each row's, and the rows' token counts."""
    w = Words(texts, lower=True)
    n = w.counts + 1
    out = np.full(int(n.sum()), END, np.uint64)
    ends = np.cumsum(n) - 1
    inner = np.ones(len(out), bool)
    inner[ends] = False
    out[inner] = w.hashes() >> _LOW << _LOW
    return out, n


def paired(context: np.ndarray, word: np.ndarray) -> np.ndarray:
    """The hash of a context and the word after it: the context of the word that follows."""
    return mixed(context * _ODD + word)


def spare_key(context: np.ndarray) -> np.ndarray:
    """Where a context's value for words that it doesn't list is kept."""
    return mixed(context ^ _TAG)


def contexts(tokens: np.ndarray, n: np.ndarray, depth: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each depth, the tokens that have a context of so many words, and those contexts. A text's first word follows the mark."""
    firsts = np.cumsum(n) - n
    place = np.arange(len(tokens)) - np.repeat(firsts, n)
    before = np.empty_like(tokens)
    before[1:] = tokens[:-1]
    before[firsts] = START
    at, context = np.arange(len(tokens)), before
    yield at, context
    for d in range(2, depth + 1):
        # the context of the token before, and that token
        long = np.flatnonzero(place >= d - 1)
        whole = np.empty_like(tokens)
        whole[at] = context
        at, context = long, paired(whole[long - 1], before[long])
        yield at, context


class Index:
    """Places of hashes among sorted ones: by their leading bits, then one step at a time."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        self.shift = np.uint64(64 - max(1, len(keys).bit_length()))
        self.first = np.searchsorted(keys, np.arange(1 << int(64 - self.shift), dtype=np.uint64) << self.shift).astype(np.int32)
        self.first = np.append(self.first, np.int32(len(keys)))
        self.most = int(np.diff(self.first).max(initial=0))

    def find(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), -1, np.int64)
        if not len(self.keys):
            return out
        bucket = (keys >> self.shift).astype(np.int64)
        at, end = self.first[bucket], self.first[bucket + 1]
        live = np.flatnonzero(at < end)
        at, end, own = at[live], end[live], keys[live]
        while len(live):
            hit = self.keys[at] == own
            out[live[hit]] = at[hit]
            more = ~hit & (at + 1 < end)
            live, at, end, own = live[more], at[more] + 1, end[more], own[more]
        return out


def _planes(x: np.ndarray, kind: str) -> bytes:
    """Numbers byte by byte: first all lowest bytes, then the next, so that they press well."""
    x = x.astype(kind)
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes()


def _unplaned(raw: bytes, kind: str, n: int, at: int) -> tuple[np.ndarray, int]:
    wide = np.dtype(kind).itemsize
    x = np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * wide, at).reshape(wide, n).T).view(kind).ravel()
    return x, at + n * wide


def _counted(context: np.ndarray, word: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
    """Distinct pairs, ordered, and how often each was there."""
    if word is None:
        kinds, n = np.unique(context, return_counts=True)
        return kinds, None, n
    order = np.lexsort((word, context))
    context, word = context[order], word[order]
    new = np.ones(len(context), bool)
    new[1:] = (context[1:] != context[:-1]) | (word[1:] != word[:-1])
    first = np.flatnonzero(new)
    return context[first], word[first], np.diff(np.append(first, len(context)))


def _blocks(context: np.ndarray, word: np.ndarray | None, n: np.ndarray, bucket: np.ndarray) -> pa.RecordBatch:
    """A block for each bucket: contexts as differences with how many pairs each has, words, counts."""
    order = np.argsort(bucket, kind="stable")  # contexts ascend within a bucket
    context, n, bucket = context[order], n[order], bucket[order]
    word = word[order] if word is not None else None
    names, starts = np.unique(bucket, return_index=True)
    press, blocks = zstandard.ZstdCompressor(level=1), []
    for lo, hi in zip(starts.tolist(), [*starts[1:].tolist(), len(bucket)], strict=True):
        first = np.flatnonzero(np.append(True, context[lo + 1 : hi] != context[lo : hi - 1]))
        parts = [len(first).to_bytes(4, "little"), (hi - lo).to_bytes(4, "little"), _planes(np.diff(context[lo:hi][first], prepend=np.uint64(0)), "<u8"), _planes(np.diff(np.append(first, hi - lo)), "<u4"), _planes(n[lo:hi], "<u4")]
        blocks.append(press.compress(b"".join(parts)) if word is None else len(x := press.compress(b"".join(parts))).to_bytes(4, "little") + x + word[lo:hi].tobytes())
    return batch(bucket=names.astype(np.int32), block=pa.array(blocks, pa.binary()))


def _opened(block: bytes, words: bool) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
    size = int.from_bytes(block[:4], "little") if words else 0
    raw = zstandard.ZstdDecompressor().decompress(block[4 : 4 + size] if words else block)
    many, n = int.from_bytes(raw[:4], "little"), int.from_bytes(raw[4:8], "little")
    steps_up, at = _unplaned(raw, "<u8", many, 8)
    runs, at = _unplaned(raw, "<u4", many, at)
    counts, _ = _unplaned(raw, "<u4", n, at)
    return np.repeat(np.cumsum(steps_up, dtype=np.uint64), runs), np.frombuffer(block, "<u8", n, 4 + size) if words else None, counts.astype(np.int64)


def tallied(train: DataFrame, pairs_of: Callable[[pa.Array], tuple[np.ndarray, np.ndarray | None]], words: bool, least: int = 1, hot: np.ndarray | None = None) -> DataFrame:
    """(key, n), or with ``words`` (context, word, key, n), of what ``pairs_of`` finds in texts ``least`` times or more.

    Contexts in ``hot`` are dealt out with their words, so that no task has all of a common one's.
    """
    parts = int(train.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    hot = np.zeros(0, np.uint64) if hot is None else hot

    def flushed(held: list[tuple]) -> pa.RecordBatch:
        context, word, n = _counted(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]) if words else None)
        dealt = mixed(context)
        if words and len(hot):
            wide = hot[np.minimum(np.searchsorted(hot, context), len(hot) - 1)] == context
            dealt[wide] = paired(context[wide], word[wide])
        return _blocks(context, word, n, (dealt % np.uint64(parts)).astype(np.int64))

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0
        for b in batches:
            for lo, hi in steps(b):
                held.append(pairs_of(b.column("text").slice(lo, hi - lo)))
                many += len(held[-1][0])
                if many > FLUSH:
                    yield flushed(held)
                    held, many = [], 0
        if many:
            yield flushed(held)

    def merged(blocks: list[bytes]) -> pa.RecordBatch:
        opened = [_opened(x, words) for x in blocks]
        context, n = np.concatenate([x[0] for x in opened]), np.concatenate([x[2] for x in opened])
        word = np.concatenate([x[1] for x in opened]) if words else None
        order = np.lexsort((word, context)) if words else np.argsort(context, kind="stable")
        context, n = context[order], n[order]
        new = np.append(True, context[1:] != context[:-1])
        if words:
            word = word[order]
            new[1:] |= word[1:] != word[:-1]
        first = np.flatnonzero(new)
        n = np.add.reduceat(n, first)
        first, n = first[n >= least], n[n >= least]
        if words:
            return batch(context=signed(context[first]), word=signed(word[first]), key=signed(paired(context[first], word[first])), n=n)
        return batch(key=signed(context[first]), n=n)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for b in batches:
            for bucket, block in zip(b.column("bucket").to_pylist(), b.column("block").to_pylist(), strict=True):
                if bucket != now and held:
                    yield merged(held)
                    held = []
                now = bucket
                held.append(block)
        if held:
            yield merged(held)

    blocks = train.select("text").mapInArrow(tidy(step), "bucket int, block binary").repartition(parts, "bucket").sortWithinPartitions("bucket")
    return blocks.mapInArrow(tidy(merge), "context bigint, word bigint, key bigint, n bigint" if words else "key bigint, n bigint")


@dataclass
class Tree:
    """``counts``: (key, n) of all training words by hash. ``hot``: (times, buckets, spare or None) by the hash of a word that
    is dealt to several buckets; ``lists``: (context, word, key, n, times, below, own) of what follows these, where there are any."""

    train: DataFrame
    tokens: int
    words: int
    counts: DataFrame
    depth: int
    context_min: int
    joint_min: int
    hot: dict[int, tuple[int, int, float | None]]
    lists: DataFrame | None

    @property
    def values(self) -> DataFrame:
        """(key, value, n), what kept contexts add to a token's log10 probability: by ``spare_key`` of the context for every
        word, and by the pair for a listed word besides that."""
        rows = self.train.select(F.lit(None).cast("bigint").alias("doc_id"), "text", F.lit(True).alias("trains"), F.lit(False).alias("asks"))
        out = _met(self, rows, lambda pieces, blocks: _values(pieces), "key bigint, value double, n bigint")
        spares = [(signed_int(c), float(x), int(times)) for c, (times, _, x) in self.hot.items() if x is not None]
        if spares:
            spare = self.train.sparkSession.createDataFrame(spares, "context bigint, spare double, times bigint")
            listed = self.lists.join(F.broadcast(spare.select("context", "spare")), "context")
            out = out.unionByName(listed.select("key", (F.col("own") - F.col("below") - F.col("spare")).alias("value"), "n")).unionByName(spare.mapInArrow(_spares, "key bigint, value double, n bigint"))
        return out


def signed_int(x: int | np.uint64) -> int:
    return int(signed(np.array([x], np.uint64))[0])


def _root(c: Column, tokens: int, words: int) -> Column:
    return F.log10((c + 1) / F.lit(float(tokens + words + 1)))


def learned(train: DataFrame, depth: int = DEPTH, context_min: int | None = None, joint_min: int | None = None) -> Tree:
    """The tree of rows with a text. Without any, no word is known and nothing is added.

    ``joint_min`` and ``context_min`` are the counts that are enough.
    """
    spark = train.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    counts = written(tallied(train, lambda texts: (token_hashes(texts)[0], None), False), "word-counts")
    tokens, words = (int(x) for x in counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first())
    joint_min, context_min = joint_min or JOINT_MIN, context_min or CONTEXT_MIN
    line = max(1, HOT_SHARE * tokens, tokens / parts)
    often = {int(np.int64(r.key).astype(np.uint64)): r.n for r in counts.where(F.col("n") > line).collect()}
    often[int(START)] = often.pop(int(END), 0)  # as many texts begin as end
    buckets = {c: (n, math.ceil(n * parts / tokens)) for c, n in often.items() if n > line}
    if not buckets:
        return Tree(train, tokens, words, counts, depth, context_min, joint_min, {}, None)
    hot = np.sort(np.array(list(buckets), np.uint64))

    def pairs(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        found, n = token_hashes(texts)
        at, context = next(contexts(found, n, 1))
        mine = hot[np.minimum(np.searchsorted(hot, context), len(hot) - 1)] == context
        return context[mine], found[at[mine]]

    times = spark.createDataFrame([(signed_int(c), n) for c, (n, _) in buckets.items() if n >= context_min], "context bigint, times bigint")
    below = counts.select(F.col("key").alias("word"), _root(F.col("n"), tokens, words).alias("below"))
    found = tallied(train, pairs, True, joint_min, hot).join(F.broadcast(times), "context").join(below, "word")
    lists = written(found.withColumn("own", F.log10((F.col("n") - DISCOUNT) / F.col("times"))), "hot-lists")
    spares = {int(np.int64(r.context).astype(np.uint64)): r.spare for r in _diverging(lists).collect()}
    return Tree(train, tokens, words, counts, depth, context_min, joint_min, {c: (n, m, spares.get(c)) for c, (n, m) in buckets.items()}, lists)


def _squeezed(*parts: tuple[np.ndarray, str]) -> bytes:
    """Arrays of numbers as one compressed block."""
    sizes = b"".join(len(x).to_bytes(4, "little") for x, _ in parts)
    return zstandard.ZstdCompressor(level=1).compress(sizes + b"".join(_planes(x, kind) for x, kind in parts))


def _unsqueezed(block: bytes, *kinds: str) -> list[np.ndarray]:
    raw, at, out = zstandard.ZstdDecompressor().decompress(block), 4 * len(kinds), []
    for i, kind in enumerate(kinds):
        x, at = _unplaned(raw, kind, int.from_bytes(raw[4 * i : 4 * i + 4], "little"), at)
        out.append(x)
    return out


#: Kinds of blocks: tokens and what is before them, lists of a hot word, a chunk's rows, sums for a chunk's rows.
_TOKENS, _LIST, _ROWS, _SUMS = 0, 1, 2, 3
_BLOCKS = "bucket int, chunk bigint, kind int, block binary"


def _dealt(tree: Tree, rows: DataFrame, parts: int) -> DataFrame:
    """Blocks of the tokens by bucket, and of the chunks' rows with their base scores."""
    spark, depth = rows.sparkSession, tree.depth
    turns = max(1, math.ceil(tree.words / max(1000, round(2 / HEAD_SHARE))))
    turn = F.shiftrightunsigned("key", 40) % turns
    shared = [sent(spark, _sorted(tree.counts.where(turn == i).select("key", F.col("n").alias("value")))) for i in range(turns)]
    hot, rest_of = {c: m for c, (_, m, _) in tree.hot.items()}, float(tree.tokens + tree.words + 1)
    context_min, joint_min = tree.context_min, tree.joint_min

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk, held, many = TaskContext.get().partitionId() << 24, [], 0
        for b in batches:
            for lo, hi in steps(b):
                tokens, n = token_hashes(b.column("text").slice(lo, hi - lo))
                held.append((tokens, n, *(b.column(c).slice(lo, hi - lo) for c in ("doc_id", "trains", "asks"))))
                many += len(tokens)
                if many > CHUNK:
                    yield from flushed(held, chunk)
                    many, chunk = 0, chunk + 1
        if held:
            yield from flushed(held, chunk)

    def counted(names: np.ndarray) -> np.ndarray:
        """How often training texts have words: one part of all counts after another is looked through and given back."""
        of = ((names >> np.uint64(40)) % np.uint64(turns)).astype(np.int64)
        out = np.zeros(len(names), np.int64)
        for i, parcel in enumerate(shared):
            keys, times = got(parcel)
            del parcel._value
            mine = np.flatnonzero(of == i)
            at = Index(keys).find(names[mine])
            out[mine[at >= 0]] = times[at[at >= 0]]
        return out

    def flushed(held: list[tuple], chunk: int) -> Iterator[pa.RecordBatch]:
        tokens, n = (np.concatenate([h[i] for h in held]) for i in (0, 1))
        ids, trains, asks = (pa.chunked_array([h[i] for h in held]) for i in (2, 3, 4))
        held.clear()
        names, code = np.unique(tokens, return_inverse=True)
        code = code.astype(np.int32)
        del tokens
        count = counted(names)
        row = np.repeat(np.arange(len(n), dtype=np.int32), n)
        base = np.bincount(row, np.log10((count + 1) / rest_of)[code], len(n))
        has = np.bincount(row, count[code] > 0, len(n)).astype(np.int64)
        out = [(int(chunk % parts), _ROWS, pickle.dumps((ids.to_pylist(), asks.to_pylist(), n, base, has)))]
        # codes from 1 on, the mark as the last word; 0 where a text has no word so far back, or one that is in no context
        names, count = np.append(names, START), np.append(count, 0)
        frequent = count >= context_min
        frequent[-1] = True
        frequent = np.append(False, frequent)
        back, before = code + np.int32(1), []
        firsts = np.cumsum(n) - n
        for d in range(depth):
            back = np.append(np.int32(0), back[:-1])
            back[firsts] = len(names) if d == 0 else 0
            before.append(np.where(frequent[back] & (before[-1] > 0 if d else True), back, np.int32(0)))
        word = np.where((count >= joint_min)[code], code + np.int32(1), np.int32(0))
        size = np.array([hot.get(int(x), 1) for x in names.tolist()]) if hot else np.ones(len(names), np.int64)
        home = mixed(names)
        live = np.flatnonzero(before[0] > 0).astype(np.int32)
        c = before[0][live] - 1
        bucket = (home % np.uint64(parts)).astype(np.int32)[c]
        wide = np.flatnonzero((size > 1)[c])
        further = before[1][live[wide]] if depth > 1 else np.zeros(len(wide), np.int32)
        further = np.where(further > 0, further - 1, code[live[wide]])
        bucket[wide] = (home[c[wide]] + mixed(home[further] ^ _TAG) % size[c[wide]].astype(np.uint64)) % np.uint64(parts)
        place = np.lexsort((word[live], bucket * np.int64(len(names)) + c))
        bucket, place = bucket[place], live[place]
        owners, starts = np.unique(bucket, return_index=True)
        flag = row * 2 + np.array(trains.to_numpy(zero_copy_only=False), bool)[row]
        del row, c, wide, further, code, live, back
        for owner, lo, hi in zip(owners.tolist(), starts.tolist(), [*starts[1:].tolist(), len(bucket)], strict=True):
            here = place[lo:hi]
            columns = [word[here], *(x[here] for x in before)]
            used = np.zeros(len(names) + 1, bool)
            for x in columns:
                used[x] = True
            used[0] = False
            used = np.flatnonzero(used)
            short = np.zeros(len(names) + 1, np.int64)
            short[used] = np.arange(1, len(used) + 1)
            w, c, *deeper = (short[x] for x in columns)
            times = np.zeros(len(used) + 1, np.int64)
            times[w] = np.append(0, count[used - 1])[w]
            steps_up = ((np.diff(x, prepend=0) % (len(used) + 1), "<u4") for x in (w, c))
            out.append((owner, _TOKENS, _squeezed((np.diff(names[used - 1] >> _LOW, prepend=np.uint64(0)), "<u8"), (times[1:], "<u8"), *steps_up, *((x, "<u4") for x in deeper), (flag[here], "<u4"))))
            if len(out) == 8:
                yield blocks(out, chunk)
                out = []
        yield blocks(out, chunk)

    def blocks(out: list[tuple], chunk: int) -> pa.RecordBatch:
        return batch(bucket=np.array([x[0] for x in out], np.int32), chunk=np.full(len(out), chunk, np.int64), kind=np.array([x[1] for x in out], np.int32), block=pa.array([x[2] for x in out], pa.binary()))

    return rows.select("doc_id", "text", "trains", "asks").mapInArrow(tidy(step), _BLOCKS)


def _hot_lists(tree: Tree, parts: int) -> DataFrame:
    """Blocks of what follows a hot word, for each of its buckets."""
    hot = {c: m for c, (_, m, _) in tree.hot.items()}

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            context, word = (b.column(c).to_numpy().view(np.uint64) for c in ("context", "word"))
            own, out = b.column("own").to_numpy(), []
            for c in np.unique(context):
                mine = np.flatnonzero(context == c)
                block = _squeezed((np.array([c]), "<u8"), (word[mine], "<u8"), (own[mine], "<f8"))
                home = int(mixed(np.array([c]))[0])
                out += [(((home + i) % (1 << 64)) % parts, block) for i in range(hot[int(c)])]
            yield batch(bucket=np.array([x[0] for x in out], np.int32), chunk=np.full(len(out), -1, np.int64), kind=np.full(len(out), _LIST, np.int32), block=pa.array([x[1] for x in out], pa.binary()))

    return tree.lists.select("context", "word", "own").mapInArrow(tidy(step), _BLOCKS)


def _met(tree: Tree, rows: DataFrame, made: Callable[[Iterator[Grown], list], Iterator[pa.RecordBatch]], kinds: str) -> DataFrame:
    """What ``made`` gives of each bucket's part of the tree, piece by piece, and of its chunks' rows."""
    spark = rows.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "8m")  # blocks are large; read when a query runs, as in lean()
    whole = _dealt(tree, rows, parts)
    if tree.lists is not None:
        whole = whole.unionByName(_hot_lists(tree, parts))
    rest_of, hot = float(tree.tokens + tree.words + 1), {c: (n, x) for c, (n, _, x) in tree.hot.items()}
    depth, context_min, joint_min = tree.depth, tree.context_min, tree.joint_min

    def pieces(held: list) -> Iterator[Grown]:
        many = math.ceil(sum(len(x) for _, kind, x in held if kind == _TOKENS) / PIECE)
        for i in range(many):
            yield Grown(held, depth, context_min, joint_min, rest_of, hot, i, many)

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for b in batches:
            for bucket, *block in zip(*(b.column(c).to_pylist() for c in ("bucket", "chunk", "kind")), (x.as_buffer() for x in b.column("block")), strict=True):
                if bucket != now and held:
                    yield from made(pieces(held), held)
                    held = []
                now = bucket
                held.append(block)
        if held:
            yield from made(pieces(held), held)

    return whole.repartitionById(parts, F.col("bucket")).sortWithinPartitions("bucket").mapInArrow(tidy(step), kinds)


class Grown:
    """The part of the tree whose contexts end in a bucket's words, or in those of one of several pieces of it, and the tokens scored in it.

    ``chunks``, with how many tokens each has, and ``row`` tell whose a token is, ``added`` is what the tree adds to its log10 probability. ``kept`` has for
    each depth the kept contexts and what they list, both by a token that has them.
    """

    def __init__(self, blocks: list, depth: int, context_min: int, joint_min: int, rest_of: float, hot: dict[int, tuple[int, float | None]], piece: int = 0, pieces: int = 1):
        self.chunks, hashes, counts, columns = [], [], [], [[] for _ in range(depth + 2)]
        for chunk, kind, block in blocks:
            if kind != _TOKENS:
                continue
            names, times, *x = _unsqueezed(block, "<u8", "<u8", *["<u4"] * (depth + 2))
            names = np.cumsum(names, dtype=np.uint64) << _LOW  # modulo 2^64, as the differences are
            for i in (0, 1):  # the word and the one before it go by differences
                x[i] = np.cumsum(x[i], dtype=np.int64) % (len(names) + 1)
            here = np.flatnonzero(np.append(False, (names >> np.uint64(32)) % np.uint64(pieces) == np.uint64(piece))[x[1]])
            x = [y[here] for y in x]
            used = np.zeros(len(names) + 1, bool)
            for y in x[:-1]:
                used[y] = True
            used[0] = False
            short = (np.cumsum(used) * used + used * sum(map(len, hashes))).astype(np.int32)
            hashes.append(names[used[1:]])
            counts.append(times[used[1:]].astype(np.int64))
            for y, to in zip(x[:-1], columns, strict=False):
                to.append(short[y])
            columns[-1].append(x[-1].astype(np.int32))
            self.chunks.append((chunk, len(here)))
        self.names, code = np.unique(np.concatenate(hashes), return_inverse=True) if hashes else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        count = np.zeros(len(self.names), np.int64)
        if hashes:
            np.maximum.at(count, code, np.concatenate(counts))
        code = np.append(0, code + 1).astype(np.int32)
        del hashes, counts
        columns = [[code[y] for y in x] if i <= depth else x for i, x in enumerate(columns)]
        del code
        word, *before, flag = (np.concatenate(columns.pop(0)) if self.chunks else np.zeros(0, np.int32) for _ in range(depth + 2))
        self.word, self.before = word, before
        self.row, trains = flag >> 1, (flag & 1).astype(np.float32)
        self.kept: list[tuple] = []
        self._grow(trains, np.log10((count + 1) / rest_of), context_min, joint_min, [_unsqueezed(x, "<u8", "<u8", "<f8") for _, kind, x in blocks if kind == _LIST], hot)

    def _grow(self, trains: np.ndarray, root: np.ndarray, context_min: int, joint_min: int, lists: list, hot: dict[int, tuple[int, float | None]]) -> None:
        wide = len(self.names) + 1
        live, context = np.arange(len(self.word)), np.zeros(len(self.word), np.int64)
        root = np.append(0.0, root)[self.word]
        above = root.copy()  # log10 of the chance of the word after the longest kept context that lists it, where it is in all lists so far
        log, listed_so_far = above.copy(), self.word > 0
        for d, back in enumerate(self.before):
            deep = np.flatnonzero(back[live] > 0)
            live = live[deep]
            _, first_of, context = np.unique(context[deep] * wide + back[live], return_index=True, return_inverse=True)
            del deep
            times = np.bincount(context, trains[live], len(first_of))
            known = np.full(len(first_of), -1, np.int64)  # places of the hot words among contexts
            if d == 0 and hot:
                name = self.names[back[live[first_of]] - 1]
                for c, (n, _) in hot.items():
                    known[name == np.uint64(c)] = 1
                    times[name == np.uint64(c)] = n
            enough = times >= (max(context_min, joint_min) if d else context_min)
            asked = np.flatnonzero(enough[context] & listed_so_far[live])
            pairs, first, pair = np.unique(context[asked] * wide + self.word[live[asked]], return_index=True, return_inverse=True)
            n = np.bincount(pair, trains[live[asked]], len(pairs))
            of = context[asked[first]]
            lists_it, own = n >= joint_min, np.log10(np.maximum(n - DISCOUNT, DISCOUNT) / np.maximum(times[of], 1))
            below = above[live[asked[first]]]
            theirs = known[of] > 0
            if theirs.any():
                lists_it[theirs] = False
                for c, words, logs in lists:
                    mine = np.flatnonzero(theirs & (name[of] == c[0]))
                    order = np.argsort(words)
                    words, logs = words[order], logs[order]
                    w = self.names[self.word[live[asked[first[mine]]]] - 1]
                    at = np.minimum(np.searchsorted(words, w), len(words) - 1)
                    hit = words[at] == w
                    lists_it[mine[hit]], own[mine[hit]] = True, logs[at[hit]]
            use = np.flatnonzero(lists_it)
            sums = lambda x, of=of, use=use, many=len(first_of): np.bincount(of[use], x[use], many)
            p, p_below = 10.0**own, 10.0**below
            many = np.bincount(of[use], minlength=len(first_of))
            rest, rest_below = np.maximum(1 - sums(p), 1e-9), np.maximum(1 - sums(p_below), 1e-9)
            spare = np.log10(rest / rest_below)
            saved = math.log(10) * times * (sums(p * (own - below)) + rest * spare)
            kept = (many > 0) & (saved >= (many + 1) * np.log(np.maximum(times, 1)) / 2)
            if d == 0 and hot:
                for c, (_, x) in hot.items():
                    kept[name == np.uint64(c)] = x is not None
                    spare[name == np.uint64(c)] = x or 0.0
            here = kept & (known < 0)
            mine = use[here[of[use]]]
            self.kept.append((live[first_of[here]], spare[here], times[here], live[asked[first[mine]]], own[mine] - below[mine] - spare[of[mine]], n[mine]))
            in_list = np.zeros(len(live), bool)
            in_list[asked] = lists_it[pair]
            listed_so_far[live] = in_list
            told = kept[context[asked]] & in_list[asked]
            log[live] += np.where(kept, spare, 0.0)[context]
            log[live[asked[told]]] = above[live[asked[told]]] = own[pair[told]]
            more = np.flatnonzero(enough[context])
            live, context = live[more], context[more]
        self.added = log - root

    def context_of(self, at: np.ndarray, depth: int) -> np.ndarray:
        """Hashes of the contexts of so many words before tokens."""
        out = self.names[self.before[depth - 1][at] - 1]
        for back in reversed(self.before[: depth - 1]):
            out = paired(out, self.names[back[at] - 1])
        return out


def _values(pieces: Iterator[Grown]) -> Iterator[pa.RecordBatch]:
    for grown in pieces:
        for d, (whose, spare, times, who, value, n) in enumerate(grown.kept, 1):
            yield batch(key=signed(spare_key(grown.context_of(whose, d))), value=spare, n=times.astype(np.int64))
            yield batch(key=signed(paired(grown.context_of(who, d), grown.names[grown.word[who] - 1])), value=value, n=n.astype(np.int64))


def _sums(pieces: Iterator[Grown], blocks: list) -> Iterator[pa.RecordBatch]:
    """What is added to each chunk's rows here; and the chunks' rows as they are."""
    out, sums = [(chunk, kind, x.to_pybytes()) for chunk, kind, x in blocks if kind == _ROWS], {}
    for grown in pieces:
        lo = 0
        for chunk, n in grown.chunks:
            more, held = np.bincount(grown.row[lo : lo + n], grown.added[lo : lo + n]), sums.get(chunk, np.zeros(0))
            whole = np.zeros(max(len(more), len(held)))
            whole[: len(held)] = held
            whole[: len(more)] += more
            sums[chunk], lo = whole, lo + n
    for chunk, x in sums.items():
        rows = np.flatnonzero(x)
        out.append((chunk, _SUMS, _squeezed((np.diff(rows, prepend=0), "<u4"), (x[rows], "<f8"))))
    yield batch(chunk=np.array([x[0] for x in out], np.int64), kind=np.array([x[1] for x in out], np.int32), block=pa.array([x[2] for x in out], pa.binary()))


def _diverging(found: DataFrame) -> DataFrame:
    """(context, spare, times) of contexts worth their list: what the divergence saves over all the context's tokens is more
    than half the logarithm of these for each word of the list and for the rest, the cost of a parameter."""
    own, below = F.pow(F.lit(10.0), "own"), F.pow(F.lit(10.0), "below")
    sums = found.groupBy("context").agg(F.max("times").alias("times"), F.sum(own).alias("listed"), F.sum(below).alias("listed_below"), F.sum(own * (F.col("own") - F.col("below"))).alias("gain"), F.count("*").alias("many"))
    rest = F.greatest(1 - F.col("listed"), F.lit(1e-9))
    rest_below = F.greatest(1 - F.col("listed_below"), F.lit(1e-9))
    spare = F.log10(rest / rest_below)
    saved = math.log(10) * F.col("times") * (F.col("gain") + rest * spare)
    return sums.where(saved >= (F.col("many") + 1) * F.log("times") / 2).select("context", spare.alias("spare"), "times")


def _spares(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield batch(key=signed(spare_key(b.column("context").to_numpy().view(np.uint64))), value=b.column("spare"), n=b.column("times"))


def scored(docs: DataFrame, train: DataFrame | None = None, folds: int = 7, held: int = 2, depth: int = DEPTH, context_min: int | None = None, joint_min: int | None = None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of docs.

    The tree is learned from the rows of ``train``, or from the rows of docs that ``training`` takes, which then go through
    once. A null or empty text has one token, the end. With no training rows every count is 0 and both scores are 0. Repeated
    rows are scored each. A null doc_id belongs to no fold: held_out is null. Other columns are not read.
    """
    tree = learned(training(docs, folds, held) if train is None else train, depth, context_min, joint_min)
    rows = docs.select("doc_id", "text", (_trains(folds, held) if train is None else F.lit(False)).alias("trains"), F.lit(True).alias("asks"))
    if train is not None:
        rows = rows.unionByName(train.select(F.lit(None).cast(rows.schema["doc_id"].dataType).alias("doc_id"), "text", F.lit(True).alias("trains"), F.lit(False).alias("asks")))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sums = _met(tree, rows, _sums, "chunk bigint, kind int, block binary").repartition(parts, "chunk").sortWithinPartitions("chunk")

    def whole(blocks: list) -> pa.RecordBatch:
        ids, asks, n, base, has = pickle.loads(next(x for kind, x in blocks if kind == _ROWS))
        added = np.zeros(len(n))
        for kind, x in blocks:
            if kind == _SUMS:
                at, values = _unsqueezed(x, "<u4", "<f8")
                added[np.cumsum(at, dtype=np.int64)] += values
        asks = np.array(asks, bool)
        return batch(doc_id=pa.array(ids, pa.int64()).filter(pa.array(asks)), n_tokens=n[asks].astype(np.int64), n_known=has[asks], base=base[asks], added=added[asks])

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, blocks = None, []
        for b in batches:
            for chunk, *block in zip(*(b.column(c).to_pylist() for c in ("chunk", "kind", "block")), strict=True):
                if chunk != now and blocks:
                    yield whole(blocks)
                    blocks = []
                now = chunk
                blocks.append(block)
        if blocks:
            yield whole(blocks)

    return sums.mapInArrow(tidy(step), "doc_id bigint, n_tokens bigint, n_known bigint, base double, added double").select(
        "doc_id",
        (fold("doc_id", folds) == held).alias("held_out"),
        "n_tokens",
        "n_known",
        F.lit(tree.tokens).cast("bigint").alias("train_tokens"),
        F.col("base").alias("base_score"),
        (F.col("base") + F.col("added")).alias("score"),
    )


def _sorted(df: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(keys, values) ascending, of a table of bounded size."""
    table = df.toArrow()
    keys = table.column("key").to_numpy().view(np.uint64)
    order = np.argsort(keys)
    return keys[order], table.column("value").to_numpy()[order]


def _trains(folds: int, held: int) -> Column:
    return F.col("doc_id").isNotNull() & (fold("doc_id", folds) != held)


def training(docs: DataFrame, folds: int = 7, held: int = 2) -> DataFrame:
    return docs.where(_trains(folds, held)).select("text")
