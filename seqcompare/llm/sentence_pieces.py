"""SentencePiece encoding and decoding with a given BPE model, by a relational lattice over distinct words.

A text's units are cut where no piece can reach across: before a space, around a line break, and between letters and ASCII
signs. Distinct units go through the lattice: their substrings of bounded length are exploded, joined to the table of
pieces, grouped by unit and folded by a higher-order aggregate. The models at hand are BPE, whose best split is not the
path of highest score that a Viterbi pass finds; so the fold goes through the edges by merge rank and takes an edge where
just one cut lies inside it. As every piece is made of two pieces of better rank, one pass gives the BPE split. Only units
of more than ``LONGEST_FOLD`` characters are merged by a queue instead.

Documents are then encoded from the dictionary of units: common ones (a share of ``HEAD_SHARE`` or more, at most
1 / ``HEAD_SHARE`` of them) from a broadcast, the others, none of which is hot, through a join. Units are found by a 64-bit
hash, and every row's ids are spelt out again and compared with its text: a row in which two units met in one hash is merged
by the queue.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import STEP_BYTES, Words, batch, bundled, got, sent, signed, steps, text_buffers, tidy, unbundled, written

SPACE = "▁"
HEAD_SHARE = 1.25e-7
#: A fold keeps a unit's cuts in the bits of a long.
LONGEST_FOLD = 61
#: Buckets of units for each shuffle partition: a bucket is what one step of the merge holds.
BLOCKS_A_PART = 8
#: Text bytes of rows that a task gathers before it deals them into blocks.
FLUSH_BYTES = 32 << 20
_NORMAL, _USER, _BYTE = 1, 4, 6


@dataclass
class Pieces:
    """A model's pieces by id; ``ranks`` are merge ranks, ``of_byte`` the ids of single bytes."""

    texts: list[str]
    ranks: dict[str, tuple[int, int]]
    of_byte: list[int]

    def spaces(self, k: int) -> list[int]:
        """Ids of a run of k spaces that no word takes: runs grow from the left to the longest that has a piece."""
        out = []
        while k:
            many = max(m for m in range(1, min(k, self.longest_run) + 1) if SPACE * m in self.ranks)
            out.append(self.ranks[SPACE * many][1])
            k -= many
        return out

    @property
    def longest_run(self) -> int:
        return max(len(p) for p in self.ranks if not p.strip(SPACE))


def load(path: str | None = None) -> Pieces:
    """The pieces of a model file; the default is the public BPE model of this machine."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    model = pb.ModelProto()
    with open(path, "rb") as f:
        model.ParseFromString(f.read())
    if model.trainer_spec.model_type != pb.TrainerSpec.BPE or not model.trainer_spec.byte_fallback:
        raise ValueError("a BPE model with byte fallback is wanted")
    found = [(p.piece, i, p.score) for i, p in enumerate(model.pieces) if p.type in (_NORMAL, _USER)]
    ranks = {p: (rank, i) for rank, (p, i, _) in enumerate(sorted(found, key=lambda x: (-x[2], x[1])))}
    return Pieces([p.piece for p in model.pieces], ranks, [i for i, p in enumerate(model.pieces) if p.type == _BYTE])


def cuts_are_safe(pieces: Pieces) -> bool:
    """Whether no piece joins a letter (to U+024F) and an ASCII sign, or has a space or a line break inside."""
    letter = lambda c: c.isascii() and c.isalpha() or "À" <= c <= "ɏ"
    sign = lambda c: c.isascii() and not c.isalpha()
    for p in pieces.ranks:
        body = p.lstrip(SPACE)
        if SPACE in body or "\n" in p or any(letter(a) and sign(b) or sign(a) and letter(b) for a, b in zip(body, body[1:], strict=False)):
            return False
    return True


class Units(Words):
    """Units of a run of texts. Each non-empty text gets a space in front; ``extra`` counts spaces before a unit's own."""

    def __init__(self, texts: pa.Array):
        data, offsets = text_buffers(texts)
        base = int(offsets[0])
        raw = data[base : int(offsets[-1])]
        if SPACE.encode() in raw.tobytes():
            texts = pa.array([(t or "").replace(SPACE, " ") for t in texts.to_pylist()], pa.string())
            data, offsets = text_buffers(texts)
            base, raw = 0, data[: int(offsets[-1])]
        offsets = offsets - base
        some = offsets[1:] > offsets[:-1]
        body = np.insert(raw, offsets[:-1][some], 32)
        self.offsets = offsets + np.concatenate([[0], np.cumsum(some)])
        self.rows, n = len(texts), len(body)
        self.bytes = np.zeros(n + 16, np.uint8)
        self.bytes[:n] = body
        space, line = body == 32, body == 10
        lead = (body >= 0xC3) & (body <= 0xC9)
        letter = (body >= 97) & (body <= 122) | (body >= 65) & (body <= 90) | lead
        letter[1:] |= lead[:-1]
        sign = (body < 128) & ~letter & ~space & ~line
        first = np.zeros(n + 1, bool)
        first[self.offsets] = True
        first = first[:n]
        start = first | line
        start[1:] |= line[:-1] | (letter[1:] & sign[:-1]) | (sign[1:] & letter[:-1])
        if n:
            again = np.append(space[1:] & ~first[1:], False)  # the next byte is a space of the same text
            start |= space
            start &= ~(space & again)
        self.starts = np.flatnonzero(start)
        self.row = np.searchsorted(self.offsets, self.starts, "right") - 1
        self.bounds = np.searchsorted(self.starts, self.offsets)
        self.counts = np.diff(self.bounds)
        before = np.maximum.accumulate(np.where(space, -1, np.arange(n))) if n else np.zeros(0, np.int64)
        run = np.minimum(self.starts - before[self.starts] - 1, self.starts - self.offsets[self.row]) if n else np.zeros(0, np.int64)
        self.extra = np.where(space[self.starts], run, 0) if n else run
        self.ends = np.append(self.starts[1:] - self.extra[1:], n) if len(self.starts) else self.starts

    def texts(self, which: np.ndarray) -> list[str]:
        return [SPACE + t[1:] if t.startswith(" ") else t for t in (self.word(i).decode() for i in which)]


def units_of(docs: DataFrame) -> DataFrame:
    """(unit, n, size): distinct units, how often each occurs, and its characters.

    A task hands its units on in compressed blocks, one for each bucket of hashes, and blocks are merged bucket by bucket.
    """
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = BLOCKS_A_PART * parts

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = _Held()
        for b in batches:
            for lo, hi in steps(b, most=4 * STEP_BYTES):
                held.add(Units(b.column("text").slice(lo, hi - lo)))
                if len(held.keys) > 500_000:
                    yield held.flush(buckets)
        if len(held.keys):
            yield held.flush(buckets)

    blocks = docs.select("text").mapInArrow(tidy(step), "bucket int, block binary").repartition(parts, "bucket").sortWithinPartitions("bucket")
    # what is merged has each unit once; the aggregation tells the optimizer so. Its partitions are asked for, as the lattice
    # makes many edges of each unit and small ones would be put together
    units = blocks.mapInArrow(tidy(_merge_blocks), "unit string, n bigint")
    return units.repartition(parts, "unit").groupBy("unit").agg(F.sum("n").alias("n"), F.max(F.length("unit")).alias("size"))


def _merge_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    now, held = None, []
    for b in batches:
        for bucket, block in zip(b.column("bucket").to_pylist(), b.column("block").to_pylist(), strict=True):
            if bucket != now and held:
                yield _merged_blocks(held)
                held = []
            now = bucket
            held.append(block)
    if held:
        yield _merged_blocks(held)


def _merged_blocks(blocks: list[bytes]) -> pa.RecordBatch:
    press = zstandard.ZstdDecompressor()
    counts, sizes, data = [], [], []
    for block in blocks:
        raw = press.decompress(block)
        many = int.from_bytes(raw[:4], "little")
        counts.append(np.frombuffer(raw, "<i8", many, 4))
        sizes.append(np.frombuffer(raw, "<i4", many, 4 + 8 * many))
        data.append(raw[4 + 12 * many :])
    units = Words.__new__(Words)
    size = np.concatenate(sizes).astype(np.int64)
    units.bytes = np.frombuffer(b"".join(data) + bytes(16), np.uint8)
    units.ends = np.cumsum(size)
    units.starts = units.ends - size
    keys, check = units.hashes(), units.hashes(1)
    order = np.lexsort((check, keys))
    new = np.ones(len(order), bool)
    new[1:] = (keys[order][1:] != keys[order][:-1]) | (check[order][1:] != check[order][:-1])
    first = np.flatnonzero(new)
    own = order[first]
    n = np.add.reduceat(np.concatenate(counts)[order], first)
    text = _gathered(units.bytes, units.starts[own], size[own])
    ends = np.concatenate([[0], np.cumsum(size[own])]).astype(np.int32)
    return batch(unit=pa.StringArray.from_buffers(len(own), pa.py_buffer(ends.tobytes()), pa.py_buffer(text.tobytes())), n=n)


class _Held:
    """Units seen in a task: keys ascending, their counts, and where in ``text`` each one's bytes are."""

    def __init__(self):
        self.keys, self.counts, self.first, self.sizes = (np.zeros(0, np.int64) for _ in range(4))
        self.text, self.length = [], 0

    def add(self, units: Units) -> None:
        keys, first, n = np.unique(signed(units.hashes()), return_index=True, return_counts=True)
        at = np.searchsorted(self.keys, keys)
        known = np.zeros(len(keys), bool)
        inside = at < len(self.keys)
        known[inside] = self.keys[at[inside]] == keys[inside]
        self.counts[at[known]] += n[known]
        new = ~known
        starts, sizes = units.starts[first[new]], (units.ends - units.starts)[first[new]]
        self.text.append(_gathered(units.bytes, starts, sizes))
        fresh = (keys[new], n[new], self.length + np.cumsum(sizes) - sizes, sizes)
        self.keys, self.counts, self.first, self.sizes = (np.insert(old, at[new], x) for old, x in zip((self.keys, self.counts, self.first, self.sizes), fresh, strict=True))
        self.length += len(self.text[-1])

    def flush(self, buckets: int) -> pa.RecordBatch:
        bucket = self.keys.view(np.uint64) % np.uint64(buckets)
        order = np.argsort(bucket, kind="stable")
        text = _gathered(np.concatenate(self.text), self.first[order], self.sizes[order])
        counts, sizes = self.counts[order].astype("<i8"), self.sizes[order].astype("<i4")
        ends = np.concatenate([[0], np.cumsum(self.sizes[order])])
        names, starts = np.unique(bucket[order], return_index=True)
        press, blocks = zstandard.ZstdCompressor(level=3), []
        for lo, hi in zip(starts.tolist(), [*starts[1:].tolist(), len(order)], strict=True):
            blocks.append(press.compress((hi - lo).to_bytes(4, "little") + counts[lo:hi].tobytes() + sizes[lo:hi].tobytes() + text[ends[lo] : ends[hi]].tobytes()))
        self.__init__()
        return batch(bucket=names.astype(np.int32), block=pa.array(blocks, pa.binary()))


def merged(text: str, pieces: Pieces) -> list[int]:
    """BPE of one unit by a queue of neighbouring pairs."""
    parts, nxt, prv = list(text), list(range(1, len(text) + 1)), list(range(-1, len(text) - 1))
    queue: list[tuple[int, int, str]] = []

    def offer(i: int) -> None:
        if 0 <= i and nxt[i] < len(parts) and (found := pieces.ranks.get(parts[i] + parts[nxt[i]])):
            heapq.heappush(queue, (found[0], i, parts[i] + parts[nxt[i]]))

    for i in range(len(parts)):
        offer(i)
    while queue:
        _, i, whole = heapq.heappop(queue)
        j = nxt[i] if parts[i] else len(parts)
        if not parts[i] or j >= len(parts) or parts[i] + parts[j] != whole:
            continue
        parts[i], parts[j], nxt[i] = whole, "", nxt[j]
        if nxt[j] < len(parts):
            prv[nxt[j]] = i
        offer(prv[i])
        offer(i)
    out = []
    for p in parts:
        if p:
            out += [pieces.ranks[p][1]] if p in pieces.ranks else [pieces.of_byte[b] for b in p.encode()]
    return out


def _bit(k: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), k)


def _shifted(c: Column, by: int) -> Column:
    return F.call_function("shiftleft", c.cast("bigint"), F.lit(by))


#: The id of an edge without a piece: a character to be spelt in bytes.
_NO_ID = (1 << 21) - 1


def dictionary(units: DataFrame, pieces: Pieces) -> DataFrame:
    """(key, n, ids): each unit's ids by the lattice, packed.

    A task has the edges of one unit after another, so they are grouped by a number that ascends within the task: where the
    aggregation sorts, it finds them in order. Units too long for the fold have no edges.
    """
    spark = units.sparkSession
    rows = [(p.replace(SPACE, " "), rank, i) for p, (rank, i) in pieces.ranks.items() if p.strip(SPACE) or len(p) == 1]
    table = F.broadcast(spark.createDataFrame(rows, "piece string, rank int, id int"))
    longest = max(len(p) for p, _, _ in rows)
    unit = ["at", "unit", "n"]
    size = F.length("unit")
    numbered = units.select(F.monotonically_increasing_id().alias("at"), "unit", "n", "size")
    starts = numbered.select(*unit, F.explode_outer(F.when(F.col("size") <= LONGEST_FOLD, F.sequence(F.lit(0), F.col("size") - 1))).alias("s"))
    spans = starts.select(*unit, "s", F.explode_outer(F.when(F.col("s").isNotNull(), F.sequence(F.lit(1), F.least(F.lit(longest), size - F.col("s"))))).alias("l"))
    subs = spans.select(*unit, "s", "l", F.substring("unit", F.col("s") + 1, F.col("l")).alias("piece"))
    found = subs.join(table, "piece", "left").where("l = 1 or id is not null or l is null")
    # an edge is one number, so that edges sort by rank, then by place: rank, start, length, id
    edge = _shifted(F.when(F.col("l") == 1, 0).otherwise(F.col("rank") + 1), 32) + _shifted(F.col("s"), 26) + _shifted(F.col("l"), 21) + F.coalesce("id", F.lit(_NO_ID))
    grouped = found.groupBy(*unit).agg(F.sort_array(F.collect_list(edge)).alias("edges"))

    start = lambda e: F.shiftright(e, 26).bitwiseAND(63).cast("int")
    length = lambda e: F.shiftright(e, 21).bitwiseAND(31).cast("int")
    inside = lambda e: F.call_function("shiftleft", _bit(length(e) - 1) - 1, start(e) + 1)
    ends = lambda e: _bit(start(e)) + _bit(start(e) + length(e))
    take = lambda cuts, e: (F.bit_count(cuts.bitwiseAND(inside(e))) == 1) & (cuts.bitwiseAND(ends(e)) == ends(e))
    all_cuts = _bit(F.length("unit") + 1) - 1
    many = F.filter("edges", lambda e: e >= F.lit(1 << 32))
    cuts = F.aggregate(many, all_cuts, lambda c, e: F.when(take(c, e), c.bitwiseXOR(c.bitwiseAND(inside(e)))).otherwise(c))
    folded = grouped.select(*unit, "edges", cuts.alias("cuts"))
    whole = lambda e: (F.col("cuts").bitwiseAND(inside(e)) == 0) & (F.col("cuts").bitwiseAND(ends(e)) == ends(e))
    path = F.sort_array(F.transform(F.filter("edges", whole), lambda e: _shifted(start(e), 21) + e.bitwiseAND(_NO_ID)))
    of_byte = F.array(*(F.lit(i) for i in pieces.of_byte))
    as_bytes = lambda c: F.transform(F.sequence(F.lit(1), F.octet_length(c)), lambda j: F.element_at(of_byte, F.conv(F.hex(F.substring(F.encode(c, "UTF-8"), j, F.lit(1))), 16, 10).cast("int") + 1))
    plain = F.transform("path", lambda e: e.bitwiseAND(_NO_ID).cast("int"))
    spelt = F.flatten(F.transform("path", lambda e: F.when(e.bitwiseAND(_NO_ID) != _NO_ID, F.array(e.bitwiseAND(_NO_ID).cast("int"))).otherwise(as_bytes(F.substring("unit", F.shiftright(e, 21).cast("int") + 1, F.lit(1))))))
    found_path = folded.select("unit", "n", path.alias("path"))
    ids = F.when(F.exists("path", lambda e: e.bitwiseAND(_NO_ID) == _NO_ID), spelt).otherwise(plain)
    parcel, code = sent(spark, pieces), np.dtype(_code(len(pieces.texts)))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            ids = b.column("ids")
            bounds = ids.offsets.to_numpy() - ids.offsets[0].as_py()
            flat = ids.flatten().to_numpy(zero_copy_only=False)
            none = np.flatnonzero(bounds[1:] == bounds[:-1])
            if len(none):  # too long for the fold: merged by the queue
                held = held or got(parcel)
                made = [np.array(merged(t.as_py().replace(" ", SPACE), held), flat.dtype) for t in b.column("unit").take(pa.array(none))]
                flat = np.insert(flat, np.repeat(bounds[none], [len(x) for x in made]), np.concatenate(made))
                more = np.zeros(len(bounds), np.int64)
                more[none + 1] = [len(x) for x in made]
                bounds = bounds + np.cumsum(more)
            packed_ids = pa.Array.from_buffers(pa.binary(), len(b), [None, pa.py_buffer((bounds * code.itemsize).astype(np.int32).tobytes()), pa.py_buffer(flat.astype(code).tobytes())])
            yield batch(key=signed(_hashed(b.column("unit"))), n=b.column("n"), ids=packed_ids)

    return found_path.select("unit", "n", ids.alias("ids")).mapInArrow(tidy(pack), "key bigint, n bigint, ids binary")


def _hashed(units: pa.Array) -> np.ndarray:
    """Hashes as those of the units of a text."""
    data, bounds = text_buffers(units)
    held = Words.__new__(Words)
    held.bytes = np.concatenate([data[bounds[0] : bounds[-1]], np.zeros(16, np.uint8)])
    held.starts, held.ends = bounds[:-1] - bounds[0], bounds[1:] - bounds[0]
    return held.hashes()


def _code(many: int) -> str:
    """How ids are packed: two bytes each where that is enough."""
    return "<u2" if many <= 1 << 16 else "<u4"


class _Table:
    """Ids by key: sorted keys, where each one's ids start, and the ids."""

    def __init__(self, keys: np.ndarray, ids: pa.BinaryArray, code: str):
        self.keys, first = np.unique(keys, return_index=True)
        wide = np.dtype(code).itemsize
        bounds = np.frombuffer(ids.buffers()[1], np.int32)[ids.offset : ids.offset + len(ids) + 1].astype(np.int64) // wide if len(ids) else np.zeros(1, np.int64)
        self.ids = np.frombuffer(ids.buffers()[2], code) if len(ids) and ids.buffers()[2] is not None else np.zeros(0, code)
        self.first, self.sizes = bounds[:-1][first].astype(np.int32), np.diff(bounds)[first].astype(np.int32)

    def find(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(keys), -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1)


def _gathered(flat: np.ndarray, first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The runs of ``flat`` that start at ``first``, one after another."""
    ends = np.cumsum(sizes)
    return flat[np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(first - (ends - sizes), sizes)]


def _laid(at: np.ndarray, tables: tuple[_Table, _Table], many: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids of units one after another, and how many each has. ``at`` is a place in the first table, or ``many`` on in the second."""
    sizes = np.zeros(len(at), np.int64)
    for k, t in enumerate(tables):
        mine = (at >= 0) & (at < many) if not k else at >= many
        sizes[mine] = t.sizes[at[mine] - k * many]
    ends = np.cumsum(sizes)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.int32)
    for k, t in enumerate(tables):
        mine = np.flatnonzero((at >= 0) & (at < many) if not k else at >= many)
        n = sizes[mine]
        run = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat(ends[mine] - n, n) + run] = t.ids[np.repeat(t.first[at[mine] - k * many], n) + run]
    return out, sizes


def encoded(docs: DataFrame, pieces: Pieces | None = None, *keep: str, digest: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids, and the columns of ``keep`` (of docs), for every row of docs.

    With ``digest`` also decoded_sha256, of the text that the ids decode to.
    A null or empty text has no ids. Repeated rows are encoded each. Rows that share an id may differ in text. A null
    doc_id is kept. Other columns are not read.
    """
    spark = docs.sparkSession
    pieces = pieces or load()
    if not cuts_are_safe(pieces):
        raise ValueError("the model's pieces reach across the cuts between units")
    code = _code(len(pieces.texts))
    words = written(dictionary(units_of(docs), pieces), "unit-ids")
    total = words.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    line = max(2, HEAD_SHARE * total)
    common = words.where(F.col("n") >= line).select("key", "ids").toArrow()
    ids = common.column("ids").combine_chunks()
    head = _Table(common.column("key").to_numpy(), (ids.chunk(0) if ids.num_chunks else pa.array([], pa.binary())) if isinstance(ids, pa.ChunkedArray) else ids, code)
    parcel, model = sent(spark, head), sent(spark, pieces)
    docs, names = bundled(docs, keep), keep
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema}
    keep = ("_kept",) if keep else ()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # 48 bits: where two rows share a mark, one of them doesn't spell out and is merged by the queue
    rows = docs.withColumn("mark", F.shiftrightunsigned(F.xxhash64("doc_id", "text"), 16))

    def missing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = got(parcel)
        for b in batches:
            marks = b.column("mark").to_numpy()
            for lo, hi in steps(b):
                u = Units(b.column("text").slice(lo, hi - lo))
                keys = signed(u.hashes())
                order, first, place = _rare(u, keys, table.find(keys))
                order, place = order[first], place[first]
                yield batch(mark=marks[lo:hi][u.row[order]], place=place.astype(np.int32), key=keys[order])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A bucket's blocks of rare units come first, then its blocks of rows."""
        table, held = got(parcel), got(model)
        spelt, now, units, rare = Spelling(spelling(held)), None, [], None
        for b in batches:
            for bucket, of_rows, block in zip(*(b.column(c).to_pylist() for c in ("bucket", "of_rows", "block")), strict=True):
                if bucket != now:
                    now, units, rare = bucket, [], None
                if not of_rows:
                    units.append(block)
                    continue
                rare = rare or _Rare(units, code)
                units = []
                for part in _rows_of(block):
                    for lo, hi in steps(part):
                        own = part.slice(lo, hi - lo)
                        u = Units(own.column("text"))
                        whole, n, data, bytes_of = _row_ids(u, own.column("mark").to_numpy(), table, rare, held, spelt)
                        out = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(n)]).astype(np.int32), pa.array(whole, pa.int32()))
                        more_columns = {"decoded_sha256": pa.array(_digests(data, bytes_of), pa.string())} if digest else {}
                        yield batch(doc_id=own.column("doc_id"), n_tokens=n, ids=out, **{k: own.column(k) for k in keep}, **more_columns)

    tails = rows.select("text", "mark").mapInArrow(tidy(missing), "mark bigint, place int, key bigint").join(words.where(F.col("n") < line).select("key", "ids"), "key").select("mark", "place", "ids")
    blocks = "bucket int, of_rows boolean, block binary"
    both = tails.mapInArrow(tidy(lambda batches: _rare_blocks(batches, parts)), blocks).unionByName(rows.mapInArrow(tidy(lambda batches: _row_blocks(batches, parts)), blocks))
    columns = "doc_id bigint, n_tokens bigint, ids array<int>" + "".join(f", `{k}` {kinds[k]}" for k in keep) + ", decoded_sha256 string" * digest
    return unbundled(both.repartition(parts, "bucket").sortWithinPartitions("bucket", "of_rows").mapInArrow(tidy(joined), columns), names)


def _rare(u: Units, keys: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Units that the head lacks, by row and key: which they are, which stand first of their like in the row, and the place of each among the row's kinds."""
    rare = np.flatnonzero(at < 0)
    order = rare[np.lexsort((keys[rare], u.row[rare]))]
    row, key = u.row[order], keys[order]
    new, top = np.ones(len(order), bool), np.ones(len(order), bool)
    top[1:] = row[1:] != row[:-1]
    new[1:] = top[1:] | (key[1:] != key[:-1])
    kind = np.cumsum(new) - 1
    base = np.maximum.accumulate(np.where(top, kind, 0)) if len(order) else kind
    return order, np.flatnonzero(new), kind - base


def _rare_blocks(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    """(bucket, of_rows, block): columns of (mark, place, ids), compressed, for each bucket of marks."""
    held, many = [], 0
    for b in batches:
        held.append(b)
        many += len(b)
        if many > 2_000_000:
            yield _rare_flushed(held, buckets)
            held, many = [], 0
    if many:
        yield _rare_flushed(held, buckets)


def _rare_flushed(held: list[pa.RecordBatch], buckets: int) -> pa.RecordBatch:
    table = pa.Table.from_batches(held).combine_chunks()
    mark, place = table.column("mark").to_numpy(), table.column("place").to_numpy()
    ids = table.column("ids").chunk(0)
    bounds = np.frombuffer(ids.buffers()[1], np.int32)[ids.offset : ids.offset + len(ids) + 1].astype(np.int64)
    flat = np.frombuffer(ids.buffers()[2], np.uint8)
    bucket = mark % buckets
    order = np.lexsort((place, mark, bucket))
    names, starts = np.unique(bucket[order], return_index=True)
    press, blocks = zstandard.ZstdCompressor(level=3), []
    for lo, hi in zip(starts.tolist(), [*starts[1:].tolist(), len(order)], strict=True):
        own = order[lo:hi]
        size = np.diff(bounds)[own]
        raw = [mark[own].astype("<i8").view(np.uint8).reshape(-1, 8)[:, :6].T.tobytes(), place[own].astype("<i4").tobytes(), size.astype("<i4").tobytes(), _gathered(flat, bounds[own], size).tobytes()]
        blocks.append(len(own).to_bytes(4, "little") + press.compress(b"".join(raw)))
    return batch(bucket=names.astype(np.int32), of_rows=pa.array(np.zeros(len(names), bool)), block=pa.array(blocks, pa.binary()))


class _Rare:
    """Ids of rare units by the mark of their row and their place in it."""

    def __init__(self, blocks: list[bytes], code: str):
        press, marks, places, sizes, flat = zstandard.ZstdDecompressor(), [], [], [], []
        for block in blocks:
            n = int.from_bytes(block[:4], "little")
            raw = press.decompress(block[4:])
            wide = np.zeros((n, 8), np.uint8)
            wide[:, :6] = np.frombuffer(raw, np.uint8, 6 * n).reshape(6, n).T
            marks.append(wide.view("<i8").ravel())
            places.append(np.frombuffer(raw, "<i4", n, 6 * n))
            sizes.append(np.frombuffer(raw, "<i4", n, 10 * n))
            flat.append(raw[14 * n :])
        mark = np.concatenate([*marks, np.zeros(0, np.int64)])
        ends = np.concatenate([[0], np.cumsum(np.concatenate([*sizes, np.zeros(0, np.int32)]))]).astype(np.int32)
        self.marks = np.unique(mark)
        ids = pa.Array.from_buffers(pa.binary(), len(mark), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(b"".join(flat))])
        self.table = _Table(self._key(mark, np.concatenate([*places, np.zeros(0, np.int32)])), ids, code)

    def _key(self, mark: np.ndarray, place: np.ndarray) -> np.ndarray:
        return (np.searchsorted(self.marks, mark) << 32) + place

    def find(self, mark: np.ndarray, place: np.ndarray) -> np.ndarray:
        known = np.searchsorted(self.marks, mark, "right") > np.searchsorted(self.marks, mark, "left")
        return np.where(known, self.table.find(self._key(mark, place)), -1)


def _row_blocks(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    """(bucket, of_rows, block): whole rows, compressed, for each bucket of marks."""
    held, size = [], 0
    for b in batches:
        for lo, hi in steps(b, most=FLUSH_BYTES):
            held.append(b.slice(lo, hi - lo))
            size += int(text_buffers(held[-1].column("text"))[1][[0, -1]] @ np.array([-1, 1]))
            if size > FLUSH_BYTES:
                yield from _rows_flushed(held, buckets)
                held, size = [], 0
    if held:
        yield from _rows_flushed(held, buckets)


def _rows_flushed(held: list[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    table = pa.Table.from_batches(held).combine_chunks()
    bucket = table.column("mark").to_numpy() % buckets
    press = zstandard.ZstdCompressor(level=5)
    for k in np.unique(bucket).tolist():
        out = pa.BufferOutputStream()
        part = table.take(pa.array(np.flatnonzero(bucket == k)))
        with pa.ipc.new_stream(out, part.schema) as stream:
            stream.write_table(part)
        yield batch(bucket=pa.array([k], pa.int32()), of_rows=pa.array([True]), block=pa.array([press.compress(out.getvalue())], pa.binary()))


def _rows_of(block: bytes) -> Iterator[pa.RecordBatch]:
    yield from pa.ipc.open_stream(zstandard.ZstdDecompressor().decompress(block))


def _row_ids(u: Units, marks: np.ndarray, head: _Table, rare: _Rare, pieces: Pieces, spelt: Spelling) -> tuple[np.ndarray, ...]:
    """Ids of all rows one after another and how many each has; the bytes they spell and how many of these."""
    keys = signed(u.hashes())
    at = head.find(keys)
    order, _, place = _rare(u, keys, at)
    hit = rare.find(marks[u.row[order]], place)
    at[order] = np.where(hit >= 0, hit + len(head.keys), -1)
    flat, sizes = _laid(at, (head, rare.table), len(head.keys))
    bounds = np.concatenate([[0], np.cumsum(sizes)])
    own = {}
    lone = pieces.ranks[SPACE][1]
    for i in np.unique(u.row[u.extra > 0]).tolist():
        own[i] = _with_runs(u, i, flat, bounds, pieces, lone)
    whole, n = _spliced(flat, np.diff(bounds[u.bounds]), own)
    data, bytes_of = spelt.out(whole, n)
    if len(data) != u.offsets[-1] or not np.array_equal(data, u.bytes[: len(data)]):
        own = {}
        ends, first = np.cumsum(bytes_of), np.cumsum(n) - n
        for i in range(u.rows):
            mine = u.bytes[u.offsets[i] : u.offsets[i + 1]]
            if not np.array_equal(data[ends[i] - bytes_of[i] : ends[i]], mine):
                own[i] = _by_queue(u, i, pieces, lone)
            else:
                own[i] = whole[first[i] : first[i] + n[i]]
        whole, n = _spliced(whole, n, own)
        data, bytes_of = spelt.out(whole, n)
    return whole, n, data, bytes_of


def _spliced(flat: np.ndarray, n: np.ndarray, own: dict[int, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Rows' ids with those of ``own`` in place."""
    if not own:
        return flat, n
    ends = np.cumsum(n)
    rows = [own.get(i, flat[ends[i] - n[i] : ends[i]]) for i in range(len(n))]
    return np.concatenate(rows).astype(np.int32), np.array([len(x) for x in rows], np.int64)


def _with_runs(u: Units, i: int, flat: np.ndarray, bounds: np.ndarray, pieces: Pieces, lone: int) -> np.ndarray:
    """Ids of a row with runs of spaces: a unit's own space joins the run before it unless it went into a word."""
    out, done = [], bounds[u.bounds[i]]
    for k in (u.bounds[i] + np.flatnonzero(u.extra[u.bounds[i] : u.bounds[i + 1]])).tolist():
        out.append(flat[done : bounds[k]])
        done = bounds[k]
        joins = bounds[k + 1] > done and flat[done] == lone
        out.append(np.array(pieces.spaces(int(u.extra[k]) + joins), np.int32))
        done += joins
    out.append(flat[done : bounds[u.bounds[i + 1]]])
    return np.concatenate(out).astype(np.int32)


def _by_queue(u: Units, i: int, pieces: Pieces, lone: int) -> np.ndarray:
    """Ids of a row in which two units met in one hash: every unit of it is merged on its own."""
    own = [np.array(merged(t, pieces), np.int32) for t in u.texts(np.arange(u.bounds[i], u.bounds[i + 1]))]
    bounds = np.zeros(len(u.starts) + 1, np.int64)
    bounds[u.bounds[i] + 1 : u.bounds[i + 1] + 1] = np.cumsum([len(x) for x in own])
    return _with_runs(u, i, np.concatenate(own) if own else np.zeros(0, np.int32), bounds, pieces, lone)


class Spelling:
    """Pieces' bytes in one run, to spell many ids at once, with plain spaces."""

    def __init__(self, spelt: list[bytes]):
        spelt = [x.replace(SPACE.encode(), b" ") for x in spelt]
        self.flat = np.frombuffer(b"".join(spelt), np.uint8)
        self.sizes = np.array([len(x) for x in spelt], np.int64)
        self.first = np.cumsum(self.sizes) - self.sizes

    def out(self, ids: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes that ids spell, and how many there are in each run of n ids."""
        sizes = self.sizes[ids]
        ends = np.concatenate([[0], np.cumsum(sizes)])[np.concatenate([[0], np.cumsum(n)])]
        return _gathered(self.flat, self.first[ids], sizes), np.diff(ends)


def _digests(data: np.ndarray, sizes: np.ndarray) -> list[str]:
    """SHA-256 of each row's bytes, without the space in front."""
    raw, out, at = data.tobytes(), [], 0
    for n in sizes.tolist():
        text = raw[at : at + n]
        out.append(hashlib.sha256(text[1:] if text.startswith(b" ") else text).hexdigest())
        at += n
    return out


def decode(ids: list[int] | np.ndarray, spelt: list[bytes]) -> str:
    text = b"".join([spelt[i] for i in ids]).decode("utf-8", "replace").replace(SPACE, " ")
    return text[1:] if text.startswith(" ") else text


def spelling(pieces: Pieces) -> list[bytes]:
    """The bytes that each id stands for; none for control pieces."""
    out = [p.encode() if p in pieces.ranks else b"" for p in pieces.texts]
    for value, i in enumerate(pieces.of_byte):
        out[i] = bytes([value])
    return out


def decoded(rows: DataFrame, pieces: Pieces | None = None) -> DataFrame:
    """doc_id and text for rows of doc_id and ids; null or empty ids give an empty text."""
    parcel = sent(rows.sparkSession, spelling(pieces or load()))

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spelt = got(parcel)
        for b in batches:
            yield batch(doc_id=b.column("doc_id"), text=pa.array([decode(x.values.to_numpy(zero_copy_only=False), spelt) if x.is_valid else "" for x in b.column("ids")], pa.string()))

    return rows.select("doc_id", "ids").mapInArrow(tidy(step), "doc_id bigint, text string")


def encode_and_decode(docs: DataFrame, pieces: Pieces | None = None) -> DataFrame:
    """doc_id, n_tokens, ids, decoded_sha256: the ids, and the digest of the text that they decode to."""
    return encoded(docs, pieces, digest=True)
