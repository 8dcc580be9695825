"""Sharding by minimax contiguous partition: groups in a fixed order, cut so that the fullest shard is as small as can be.

Equal texts are one group and stay together. Groups are ordered by the hash of their text. The smallest feasible capacity
over them is found by binary search, each trial a greedy pass over the prefix sums. The driver never holds all groups: it
sums ranges of hashes and looks closer only where a cut may fall, until the capacity over single groups is certain. The
cuts are then laid within what that capacity allows, as near to equal shares of what is left as they can be.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

SHARDS = 40
#: Leading bits of the hash that tell the first ranges apart.
BITS = 16
#: Ranges that a round splits the undecided ones into, at most.
MOST_ATOMS = 1 << 18
OVERHEAD = 16
#: Numbering is dealt into about so many parts.
PARTS = 4096


def _reach(prefix: np.ndarray, start: int, capacity: int) -> int:
    """Furthest cut that keeps the groups from ``start`` within capacity."""
    return int(np.searchsorted(prefix, prefix[start] + capacity, "right")) - 1


def feasible(prefix: np.ndarray, shards: int, capacity: int) -> bool:
    at = 0
    for _ in range(shards):
        at = _reach(prefix, at, capacity)
    return at == len(prefix) - 1


def smallest_capacity(sizes: np.ndarray, shards: int) -> int:
    prefix = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    low, high = max(int(sizes.max(initial=0)), -(-int(prefix[-1]) // shards)), int(prefix[-1])
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if feasible(prefix, shards, middle) else (middle + 1, high)
    return low


def cuts(sizes: np.ndarray, shards: int) -> np.ndarray:
    """Ends of the shards in the order of groups: no shard is over the smallest capacity, and shares are near equal."""
    prefix = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    capacity, n, total = smallest_capacity(sizes, shards), len(sizes), int(prefix[-1])
    least = np.zeros(shards + 1, np.int64)  # of the first k shards' end, so that the rest still fits
    least[shards] = n
    for k in range(shards - 1, 0, -1):
        least[k] = np.searchsorted(prefix, prefix[least[k + 1]] - capacity, "left")
    ends, at = np.zeros(shards, np.int64), 0
    for k in range(shards):
        share = prefix[at] + (total - prefix[at]) / (shards - k)
        best = int(np.searchsorted(prefix, share))
        if best > 0 and best <= n and abs(prefix[best - 1] - share) <= abs(prefix[min(best, n)] - share):
            best -= 1
        at = int(min(max(best, least[k + 1], at), _reach(prefix, at, capacity))) if k < shards - 1 else n
        ends[k] = at
    return ends


def _fluid(prefix: np.ndarray, single: np.ndarray, at: int, capacity: int) -> int:
    """Furthest cut from a place in bytes if all atoms but single groups could be cut anywhere."""
    target = min(at + capacity, int(prefix[-1]))
    k = int(np.searchsorted(prefix, target, "right")) - 1
    inside = k < len(single) and single[k] and target > prefix[k]
    return int(prefix[k]) if inside else target


def least_capacity(sizes: np.ndarray, single: np.ndarray, shards: int) -> int:
    """What no partition of the groups within the atoms can go below."""
    prefix = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    low, high = max(int(sizes[single].max(initial=0)), -(-int(prefix[-1]) // shards)), int(prefix[-1])
    while low < high:
        middle, at = (low + high) // 2, 0
        for _ in range(shards):
            at = _fluid(prefix, single, at, middle)
        low, high = (low, middle) if at == prefix[-1] else (middle + 1, high)
    return low


def undecided(sizes: np.ndarray, single: np.ndarray, shards: int) -> np.ndarray:
    """Atoms of several groups in which a cut of the best partition may fall; none once the capacity is known."""
    prefix = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    low, high = least_capacity(sizes, single, shards), smallest_capacity(sizes, shards)
    out, first, last = np.zeros(len(sizes), bool), 0, 0
    for _ in range(shards if low < high else 0):
        first, last = _reach(prefix, first, low), _fluid(prefix, single, last, high)
        out[first : int(np.searchsorted(prefix, last, "left"))] = True
    return np.flatnonzero(out & ~single)


def _atoms(rows: DataFrame, bits: int) -> DataFrame:
    """Ranges of hashes by their leading bits: (atom, size, n, single)."""
    atom = F.shiftright("h", 64 - bits) if bits < 64 else F.col("h")
    return rows.groupBy(atom.alias("atom")).agg(F.sum("size").alias("size"), F.count("*").alias("n"), (F.min("h") == F.max("h")).alias("single"))


def boundaries(rows: DataFrame, shards: int, bits: int = BITS) -> list[int]:
    """Hashes at which shards begin, from the second on, for rows (h, size).

    Atoms are ranges of hashes. Those in which a cut of the best partition may fall are split by more bits of the hash, again
    and again, until the smallest capacity over the groups themselves is known; all others stay whole. So the driver holds
    a bounded number of atoms, and each round is one aggregation of the rows in question.
    """
    spark = rows.sparkSession
    found = _atoms(rows, bits).toPandas()
    start = found["atom"].to_numpy(np.int64) << (64 - bits)
    width = np.full(len(found), bits)
    size, single = found["size"].to_numpy(np.int64), found["single"].to_numpy(bool)
    while True:
        order = np.argsort(start)
        start, width, size, single = start[order], width[order], size[order], single[order]
        wanted = undecided(size, single, shards) if len(size) else np.zeros(0, np.int64)
        if not len(wanted):
            break
        finer = max(1, (MOST_ATOMS // len(wanted)).bit_length() - 1)
        new = [(start, width, size, single)]
        for w in np.unique(width[wanted]).tolist():
            mine = wanted[width[wanted] == w]
            asked = spark.createDataFrame([(int(x),) for x in start[mine] >> (64 - w)], "of bigint")
            to = min(64, w + finer)
            part = _atoms(rows.join(F.broadcast(asked), F.shiftright("h", 64 - w) == F.col("of"), "left_semi"), to).toPandas()
            new.append((part["atom"].to_numpy(np.int64) << (64 - to), np.full(len(part), to), part["size"].to_numpy(np.int64), part["single"].to_numpy(bool)))
        rest = np.ones(len(size), bool)
        rest[wanted] = False
        new[0] = tuple(x[rest] for x in new[0])
        start, width, size, single = (np.concatenate(x) for x in zip(*new, strict=True))
    if not len(size):
        return []
    return [int(start[e]) if e < len(start) else None for e in cuts(size, shards)[:-1].tolist()]


def sharded(docs: DataFrame, shards: int = SHARDS, bits: int = BITS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of docs.

    A null text has the size of an empty one and goes with it. Repeated rows and null ids have slots of their own. An
    empty table gives no rows. A group larger than an equal share has its shard's capacity to itself; the rest is shared
    out evenly. Texts are taken for equal by a 64-bit hash: two that share one would only stay together.
    """
    spark = docs.sparkSession
    text = F.coalesce("text", F.lit(""))
    rows = written(
        docs.select("doc_id", (F.octet_length(text) + OVERHEAD).cast("bigint").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("h"), F.monotonically_increasing_id().alias("row")),
        "sizes",
    )
    shard = F.lit(0)
    for start in boundaries(rows.select("h", "size"), shards, bits):
        shard = shard + (F.col("h") >= F.lit(start)).cast("int") if start is not None else shard
    # slots are numbered in parts; rows without an id, and those of one text, are dealt to all parts
    part = F.pmod(F.xxhash64(F.coalesce("doc_id", "row"), "h"), F.lit(-(-PARTS // shards))).cast("int")
    placed = rows.withColumns({"shard": shard, "part": part})
    counts = placed.groupBy("shard", "part").agg(F.count("*").alias("n")).toPandas().sort_values(["shard", "part"])
    before = counts.groupby("shard")["n"].cumsum() - counts["n"] if len(counts) else counts["n"]
    starts = F.broadcast(spark.createDataFrame(list(zip(counts["shard"].tolist(), counts["part"].tolist(), before.tolist(), strict=True)), "shard int, part int, before bigint"))
    place = F.row_number().over(Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size"))
    return placed.join(starts, ["shard", "part"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("before") + place - 1).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
