"""Words of k symbols by numpy on Arrow batches: codes of all windows of many residues at once."""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Symbols that one step works on; a longer part is cut into steps that overlap by k - 1.
STEP = 1 << 21
_COMPLEMENT = np.arange(256, dtype=np.uint8)
_COMPLEMENT[list(b"ACGT")] = list(b"TGCA")
_ODD = 0x9E3779B97F4A7C15


def symbols(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column, and where its rows start and end (null: empty)."""
    if pa.types.is_large_string(texts.type):
        texts = texts.cast(pa.string())
    if texts.null_count:
        texts = texts.fill_null("")
    bounds = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    held = texts.buffers()[2]
    data = np.frombuffer(held, np.uint8)[bounds[0] : bounds[-1]] if held is not None else np.zeros(0, np.uint8)
    return data, bounds - bounds[0]


def steps(data: np.ndarray, bounds: np.ndarray, k: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(symbols, window starts, rows) of runs of rows with about ``STEP`` symbols; each window is in one run."""
    row, n = 0, len(bounds) - 1
    while row < n:
        stop = max(row + 1, int(np.searchsorted(bounds, bounds[row] + STEP, "right")) - 1)
        if stop == row + 1 and bounds[stop] - bounds[row] > STEP:
            for lo in range(int(bounds[row]), int(bounds[stop]) - k + 1, STEP):
                part = data[lo : min(lo + STEP + k - 1, int(bounds[stop]))]
                yield part, np.arange(len(part) - k + 1), np.full(len(part) - k + 1, row)
        else:
            many = np.maximum(np.diff(bounds[row : stop + 1]) - k + 1, 0)
            first = bounds[row:stop] - bounds[row]
            rows = np.repeat(np.arange(row, stop), many)
            starts = np.arange(int(many.sum())) + np.repeat(first - (np.cumsum(many) - many), many)
            yield data[bounds[row] : bounds[stop]], starts, rows
        row = stop


def _base(code: np.ndarray, many: int, k: int, backwards: bool = False) -> np.ndarray:
    """The number that each k consecutive codes make; reversed ones with ``backwards``."""
    n = max(0, len(code) - k + 1)
    out = np.zeros(n, np.int64)
    for i in reversed(range(k)) if backwards else range(k):
        out = out * many + code[i : i + n]
    return out


numbered = _base


def counted(ids: pa.Array, texts: pa.Array, k: int, canonical: bool = False, without: str | None = None) -> Iterator[pa.RecordBatch]:
    """(seq_id, feature, value) of a batch, counted step by step."""
    data, bounds = symbols(texts)
    if len(data) and data.max() > 127 or without and not without.isascii():
        yield _by_slices(ids, texts, k, canonical, without)
        return
    present = np.bincount(data, minlength=256) > 0
    if canonical:
        present |= present[_COMPLEMENT]
    kinds = np.flatnonzero(present)
    many = max(1, len(kinds))
    if many**k >= 1 << 62:
        yield _by_slices(ids, texts, k, canonical, without)
        return
    coded = np.zeros(256, np.int64)
    coded[kinds] = np.arange(len(kinds))
    names = ids.dictionary_encode()
    name_of = names.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    for part, starts, rows in steps(data, bounds, k):
        word = _base(coded[part], many, k)
        if canonical:
            word = np.minimum(word, _base(coded[_COMPLEMENT[part]], many, k, backwards=True))
        if without:
            hit = np.concatenate([[0], np.cumsum(part == ord(without))])
            good = hit[starts + k] == hit[starts]
            starts, rows = starts[good], rows[good]
        if not len(starts):
            continue
        own, who = word[starts], name_of[rows]
        span = many**k
        if (int(who.max()) + 1) * span < 1 << 22:
            n = np.bincount(who * span + own)
            key = np.flatnonzero(n)
            n = n[key]
        elif (int(who.max()) + 1) * span < 1 << 62:
            key, n = np.unique(who * span + own, return_counts=True)
        else:
            order = np.lexsort((own, who))
            own, who = own[order], who[order]
            first = np.flatnonzero(np.append(True, (own[1:] != own[:-1]) | (who[1:] != who[:-1])))
            n = np.diff(np.append(first, len(own)))
            key, who = None, who[first]
            own = own[first]
        if key is not None:
            who, own = key // span, key % span
        yield pa.RecordBatch.from_arrays([names.dictionary.take(pa.array(who)), _spelt(own, kinds, many, k), pa.array(n.astype(np.int64))], names=["seq_id", "feature", "value"])


def _spelt(word: np.ndarray, kinds: np.ndarray, many: int, k: int) -> pa.Array:
    text = np.empty((len(word), k), np.uint8)
    for i in reversed(range(k)):
        text[:, i] = kinds[word % many]
        word = word // many
    ends = (np.arange(len(word) + 1) * k).astype(np.int32)
    return pa.StringArray.from_buffers(len(word), pa.py_buffer(ends.tobytes()), pa.py_buffer(text.tobytes()))


def _by_slices(ids: pa.Array, texts: pa.Array, k: int, canonical: bool, without: str | None) -> pa.RecordBatch:
    """The same for symbols outside ASCII, or words too long for a number."""
    found: Counter = Counter()
    swap = str.maketrans("ACGT", "TGCA")
    for name, text in zip(ids.to_pylist(), texts.to_pylist(), strict=True):
        for i in range(len(text or "") - k + 1):
            word = text[i : i + k]
            if not without or without not in word:
                found[name, min(word, word.translate(swap)[::-1]) if canonical else word] += 1
    return pa.RecordBatch.from_arrays([pa.array([n for n, _ in found], pa.string()), pa.array([w for _, w in found], pa.string()), pa.array(list(found.values()), pa.int64())], names=["seq_id", "feature", "value"])


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mix."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _poly(part: np.ndarray, k: int, backwards: bool = False) -> np.ndarray:
    n, wide = max(0, len(part) - k + 1), part.astype(np.uint64) + np.uint64(1)
    out = np.zeros(n, np.uint64)
    for i in reversed(range(k)) if backwards else range(k):
        out = out * np.uint64(_ODD) + wide[i : i + n]
    return out


def word_hashes(part: np.ndarray, k: int, canonical: bool) -> np.ndarray:
    """A 63-bit hash of the word at each place; with ``canonical`` that of a word and of its reverse complement are one."""
    h = mixed(_poly(part, k))
    if canonical:
        h = np.minimum(h, mixed(_poly(_COMPLEMENT[part], k, backwards=True)))
    return (h >> np.uint64(1)).astype(np.int64)


#: Windows whose md5 is worked on at a time, so that they stay in a core's cache.
MD5_STEP = 1 << 13
#: Fewer are hashed one by one.
FEW = 500
_TURNS = np.repeat(np.array([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]]), 4, axis=0).ravel()
_SINES = (np.abs(np.sin(np.arange(1, 65))) * 2.0**32).astype(np.uint64).astype(np.uint32)
_PLACES = np.concatenate([np.arange(16), (5 * np.arange(16) + 1) % 16, (3 * np.arange(16) + 5) % 16, 7 * np.arange(16) % 16])


def word_md5(part: np.ndarray, starts: np.ndarray, k: int) -> np.ndarray:
    """The first 60 bits of the md5 of the k symbols from each start, as ``rng.draw`` takes them of a text; k is 55 at most."""
    if k > 55:
        raise ValueError("words of more than 55 symbols take more than one block")
    out = np.empty(len(starts), np.int64)
    for lo in range(0, len(starts), MD5_STEP):
        own = starts[lo : lo + MD5_STEP]
        text = np.zeros((len(own), 4 * (k // 4 + 1)), np.uint8)
        text[:, :k] = np.lib.stride_tricks.sliding_window_view(part, k)[own]
        text[:, k] = 0x80
        message = np.ascontiguousarray(text.view("<u4").T)
        a, b = _md5_rounds(message, np.uint32(8 * k))
        out[lo : lo + MD5_STEP] = (((a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap()) >> np.uint64(4)).astype(np.int64)
    return out


def numbered_md5(prefix: str, lo: int, hi: int) -> np.ndarray:
    """The first 60 bits of the md5 of ``prefix|n`` for n from lo to hi - 1, as ``rng.draw`` takes them of a text."""
    head = f"{prefix}|".encode()
    if hi - lo < FEW or len(head) + len(str(hi)) > 55:
        base = hashlib.md5(head)
        out = np.empty(hi - lo, np.int64)
        for n in range(lo, hi):
            own = base.copy()
            own.update(b"%d" % n)
            out[n - lo] = int.from_bytes(own.digest()[:8], "big") >> 4
        return out
    found = []
    while lo < hi:  # numbers of equally many digits at a time
        digits = len(str(lo))
        end = min(hi, 10**digits, lo + MD5_STEP)
        numbers, size = np.arange(lo, end), len(head) + digits
        text = np.zeros((end - lo, 4 * (size // 4 + 1)), np.uint8)
        text[:, : len(head)] = np.frombuffer(head, np.uint8)
        for place in range(digits):
            text[:, size - 1 - place] = numbers // 10**place % 10 + ord("0")
        text[:, size] = 0x80
        a, b = _md5_rounds(np.ascontiguousarray(text.view("<u4").T), np.uint32(8 * size))
        found.append((((a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap()) >> np.uint64(4)).astype(np.int64))
        lo = end
    return np.concatenate(found)


def _md5_rounds(message: np.ndarray, bits: np.uint32) -> tuple[np.ndarray, np.ndarray]:
    """The first two numbers of the digests of one block each: columns of the message's first words, the rest but its length being 0."""
    n = message.shape[1]
    first = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    a, b, c, d = (np.full(n, x, np.uint32) for x in first)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:  # f = d ^ (b & (c ^ d))
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif i < 32:  # f = c ^ (d & (b ^ c))
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        place = int(_PLACES[i])
        np.add(f, a, out=f)
        if place < len(message):
            np.add(f, message[place], out=f)
        np.add(f, np.uint32((int(_SINES[i]) + (int(bits) if place == 14 else 0)) & 0xFFFFFFFF), out=f)
        turn = int(_TURNS[i])
        np.right_shift(f, np.uint32(32 - turn), out=g), np.left_shift(f, np.uint32(turn), out=f), np.bitwise_or(f, g, out=f)
        np.add(f, b, out=f)
        a, b, c, d, f = d, f, b, c, a
    return a + first[0], b + first[1]
