"""Whole-batch text kernels over the UTF-8 bytes of an Arrow column (NumPy, no row loop).

Word hashes are polynomial over a random byte table modulo 2**64; a hit of a hash is never the
answer by itself where exactness matters, the callers compare the texts afterwards.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_RNG = np.random.default_rng(20240229)
#: One random 64-bit number for each byte value, and another where two independent hashes are taken.
BYTE_CODE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
SECOND_CODE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
FOLDED = np.arange(256, dtype=np.uint8)
FOLDED[65:91] += 32
_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers = np.ones(1, np.uint64), np.ones(1, np.uint64)

#: ASCII white space of the word rule ``[^\x20\x09-\x0D]+``.
NOT_SPACE = np.ones(256, bool)
NOT_SPACE[[32, 9, 10, 11, 12, 13]] = False
#: The word rule ``[^\x00-\x2F\x3A-\x60\x7B-\x7F]+`` after lower-casing: 0-9, letters, all above ASCII.
ALNUM = np.zeros(256, bool)
ALNUM[48:58] = ALNUM[65:91] = ALNUM[97:123] = True
ALNUM[128:] = True


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, at least n of each."""
    global _powers
    if len(_powers[0]) < n:
        size = 1 << (n - 1).bit_length()
        grown = []
        for root in (_BASE, _INVERSE):
            a = np.full(size, root, np.uint64)
            a[0] = 1
            grown.append(np.multiply.accumulate(a))
        _powers = grown[0], grown[1]
    return _powers


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def raw(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null is an empty text. offsets[0] is 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()) if pa.types.is_string(column.type) else column
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    body = column.buffers()[2]
    data = np.frombuffer(body, np.uint8) if body is not None and body.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def words(data: np.ndarray, offsets: np.ndarray, kinds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words in ``data``, and for each text the index of its first word."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = kinds[data]
    edge = np.empty(len(data), bool)
    edge[0] = True
    np.not_equal(inside[1:], inside[:-1], out=edge[1:])
    cuts = offsets[1:-1]
    edge[cuts[cuts < len(data)]] = True
    at = np.flatnonzero(edge)
    ends = np.append(at[1:], len(data))
    use = inside[at]
    starts, ends = at[use], ends[use]
    return starts, ends, np.searchsorted(starts, offsets)


def prefix_sums(data: np.ndarray, codes: np.ndarray = BYTE_CODE) -> np.ndarray:
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(codes[data] * powers(len(data) + 1)[0][: len(data)], out=out[1:])
    return out


def span_hash(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of data[start:end] for each pair, equal wherever the bytes are equal."""
    return mix((sums[ends] - sums[starts]) * powers(len(sums))[1][starts] + (ends - starts).astype(np.uint64))


def window_hash(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` word hashes (len - width + 1 of them)."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for k in range(width):
        out *= _BASE
        out += hashes[k : k + n]
    return mix(out)


def window_starts(first: np.ndarray, width: int) -> np.ndarray:
    """Indices of words at which a window of ``width`` words lies inside one text."""
    total = int(first[-1])
    if total < width:
        return np.zeros(0, np.int64)
    good = np.ones(total - width + 1, bool)
    for back in range(1, width):
        at = first[1:-1] - back
        good[at[(at >= 0) & (at < len(good))]] = False
    return np.flatnonzero(good)


def owner(first: np.ndarray, index: np.ndarray) -> np.ndarray:
    """The text that each word index belongs to."""
    return np.searchsorted(first, index, side="right") - 1


def covered(n: int, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Which of n places lie in one of the runs."""
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + lengths, -1)
    return np.cumsum(edge[:-1]) > 0
