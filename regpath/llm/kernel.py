"""Word and shingle hashes of many whole texts at once, straight from Arrow's bytes.

Nothing here makes a Python object for a word.  Bytes are worked through in
segments cut where a word ends.  What a caller keeps of a text, such as a hash for each
word, grows with its length; `word_segments` lets it keep less.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
#: Bytes hashed at once, and bytes of texts that are worked through together: an executor's Python stays small beside its heap.
SEGMENT, PORTION = 1 << 19, 1 << 21
_rng = np.random.Generator(np.random.PCG64(20240229))
BYTE_VALUE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) | U64(1)
PLACE_FACTOR = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) | U64(1)
ROUND_SEED = _rng.integers(1, 1 << 63, 4096, dtype=np.uint64)
BASE = U64(0x9E3779B97F4A7C15)
INVERSE = U64(pow(int(BASE), -1, 1 << 64))

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACES = np.zeros(256, dtype=bool)
SPACES[[9, 10, 11, 12, 13, 32]] = True
#: ASCII other than digits and letters, after lower-casing.
MARKS = np.zeros(256, dtype=bool)
MARKS[:48] = MARKS[58:97] = MARKS[123:128] = True

_powers = {"up": np.ones(1, dtype=np.uint64), "down": np.ones(1, dtype=np.uint64)}


def _power(which: str, n: int) -> np.ndarray:
    if len(_powers[which]) < n:
        factor = np.full(max(n, SEGMENT + 1), BASE if which == "up" else INVERSE, dtype=np.uint64)
        factor[0] = 1
        _powers[which] = np.multiply.accumulate(factor)
    return _powers[which][:n]


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijection that spreads every bit over all bits."""
    h = h ^ (h >> U64(33))
    h = h * U64(0xFF51AFD7ED558CCD)
    h ^= h >> U64(33)
    h *= U64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U64(33))


def bytes_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of the texts in a row, and the n + 1 offsets; null counts as empty.  Strings without nulls are not copied."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if not (pa.types.is_string(texts.type) or pa.types.is_large_string(texts.type)):
        texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    _, offsets, data = texts.buffers()
    kind = np.int64 if pa.types.is_large_string(texts.type) else np.int32
    off = np.frombuffer(offsets, dtype=kind)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, dtype=np.int64)
    held = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, dtype=np.uint8)
    return held, off - off[0]


def portions(texts: pa.Array, most: int | None = None) -> Iterator[tuple[int, int]]:
    """Row ranges of about `most` bytes each (PORTION without it); a longer text is a range of its own."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    off, most = np.concatenate([[0], np.cumsum(sizes)]), most or PORTION
    at = 0
    while at < len(texts):
        to = max(at + 1, int(np.searchsorted(off, off[at] + most, "right")) - 1)
        yield at, to
        at = to


def word_segments(data: np.ndarray, off: np.ndarray, breaks: np.ndarray = SPACES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(hashes, first bytes) of all words in order, segment by segment.  A-Z count as a-z."""
    at, n = 0, len(data)
    while at < n:
        to = min(n, at + SEGMENT)
        while to < n:  # a segment ends behind a break
            found = np.flatnonzero(breaks[LOWER[data[at:to]]])
            if len(found):
                to = at + int(found[-1]) + 1
                break
            to = min(n, to + SEGMENT)
        low = LOWER[data[at:to]]
        word = ~breaks[low]
        edge = np.zeros(to - at + 1, dtype=bool)
        edge[off[np.searchsorted(off, at) : np.searchsorted(off, to, "right")] - at] = True
        edge[[0, -1]] = True
        first, last = edge[:-1].copy(), edge[1:].copy()
        first[1:] |= ~word[:-1]
        last[:-1] |= ~word[1:]
        begin, end = np.flatnonzero(word & first), np.flatnonzero(word & last) + 1
        upto = np.zeros(to - at + 1, dtype=np.uint64)
        np.cumsum(BYTE_VALUE[low] * _power("up", to - at), out=upto[1:])
        yield mixed((upto[end] - upto[begin]) * _power("down", to - at)[begin] + (end - begin).astype(np.uint64)), begin + at
        at = to


def word_hashes(data: np.ndarray, off: np.ndarray, breaks: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words in order, and the n + 1 offsets of the texts' words."""
    found = list(word_segments(data, off, breaks))
    if not found:
        return np.zeros(0, dtype=np.uint64), np.zeros(len(off), dtype=np.int64)
    return np.concatenate([h for h, _ in found]), np.searchsorted(np.concatenate([b for _, b in found]), off)


def byte_counts(data: np.ndarray, off: np.ndarray, kind: np.ndarray) -> np.ndarray:
    """How many bytes of a kind, given as 256 truth values, each text has."""
    out = np.zeros(len(off) - 1, dtype=np.int64)
    for at in range(0, len(data), SEGMENT):
        there = np.flatnonzero(kind[data[at : at + SEGMENT]]) + at
        out += np.diff(np.searchsorted(there, off))
    return out


def _joined(words: np.ndarray, at: np.ndarray, k: int) -> np.ndarray:
    h = np.full(len(at), PLACE_FACTOR[63 - k], dtype=np.uint64)
    for j in range(k):
        h += words[at + j] * PLACE_FACTOR[j]
    return mixed(h)


def runs_of(words: np.ndarray, k: int) -> np.ndarray:
    """The hash of the k words from each place on, as `_joined` has it; texts' ends play no part."""
    n = max(0, len(words) - k + 1)
    h = np.full(n, PLACE_FACTOR[63 - k], dtype=np.uint64)
    for j in range(k):
        h += words[j : j + n] * PLACE_FACTOR[j]
    return mixed(h)


def power_of(exponents: np.ndarray) -> np.ndarray:
    """BASE, or for negative ones its inverse, to the power of each exponent."""
    out, left, step = np.ones(len(exponents), dtype=np.uint64), np.abs(exponents).astype(np.uint64), np.where(exponents < 0, INVERSE, BASE)
    while left.any():
        out = np.where(left & U64(1), out * step, out)
        left, step = left >> U64(1), step * step
    return out


def shingles(words: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each text's runs of k words, in order, and offsets; a text of 1 to k - 1 words has its whole sequence as one."""
    n = np.diff(off)
    many = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    to = np.concatenate([[0], np.cumsum(many)])
    at = np.arange(to[-1]) - np.repeat(to[:-1], many) + np.repeat(off[:-1], many)
    length = np.repeat(np.minimum(n, k), many)
    out = np.empty(to[-1], dtype=np.uint64)
    for size in range(1, k + 1):
        own = length == size
        if size == k and own.all():
            out = _joined(words, at, k)
        elif own.any():
            out[own] = _joined(words, at[own], size)
    return out, to


def as_sets(values: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each text, and their offsets."""
    values = values.copy()
    for a, b in zip(off[:-1], off[1:], strict=True):
        values[a:b].sort()
    new = np.ones(len(values), dtype=bool)
    new[1:] = values[1:] != values[:-1]
    new[off[:-1][off[:-1] < len(values)]] = True
    return values[new], np.concatenate([[0], np.cumsum(new)])[off]


def sums(values: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Sum of each text's values; 0 for none."""
    upto = np.concatenate([np.zeros(1, dtype=values.dtype), np.cumsum(values, dtype=values.dtype)])
    return upto[off[1:]] - upto[off[:-1]]


def sketches(values: np.ndarray, off: np.ndarray, t: int) -> np.ndarray:
    """Fast similarity sketches: n rows of t coordinates; a row without values keeps the largest number.

    In round i < t every value of a set is put in a random one of t bins, in
    round t + b in bin b.  A bin keeps the least (round, hash) it has been
    offered, and a set stops after the round in which its last bin got a value.
    Large sets need one or two rounds; every bin of every non-empty set is filled.
    """
    n, empty = len(off) - 1, ~U64(0)
    bins = np.full(n * t, empty, dtype=np.uint64)
    rows = np.repeat(np.arange(n), np.diff(off))
    for i in range(2 * t):
        if not len(rows):
            break
        h = mixed(values ^ ROUND_SEED[i])
        place = ((h >> U64(32)) * U64(t) >> U64(32)).astype(np.int64) if i < t else np.int64(i - t)
        value = (U64(i) << U64(53)) | (mixed(h + BASE) >> U64(11))
        np.minimum.at(bins, rows * t + place, value)
        live = np.unique(rows)
        open_ = np.zeros(n, dtype=bool)
        open_[live] = (bins.reshape(n, t)[live] == empty).any(axis=1)
        keep = open_[rows]
        values, rows = values[keep], rows[keep]
    return bins.reshape(n, t)


def bands(sketch: np.ndarray, rows: int) -> np.ndarray:
    """A hash for each run of `rows` coordinates; equal only if band number and coordinates are."""
    n, t = sketch.shape
    count = t // rows
    parts = sketch[:, : count * rows].reshape(n, count, rows)
    h = np.broadcast_to(np.arange(1, count + 1, dtype=np.uint64) * BASE, (n, count)).copy()
    for j in range(rows):
        h = mixed(h + parts[:, :, j] * PLACE_FACTOR[j])
    return h
