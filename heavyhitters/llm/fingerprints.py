"""Vectorised polynomial fingerprints over UTF-8 bytes (uint64 arithmetic, mod 2**64).

A prefix sum of byte * BASE**position gives the hash of any span by one
subtraction and one multiplication with the inverse power, so spans of a whole
batch are hashed without a Python loop.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
INVERSE = np.uint64(pow(int(BASE), -1, 1 << 64))
MASK = (1 << 64) - 1


def mix(x: np.ndarray) -> np.ndarray:
    """Avalanche a uint64 array (two multiply-xorshift rounds)."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def mix_int(x: int) -> int:
    """`mix` for one Python int."""
    return int(mix(np.array([x & MASK], np.uint64))[0])


@lru_cache(maxsize=4)
def _powers(base: int, size: int) -> np.ndarray:
    out = np.full(size, np.uint64(base), np.uint64)
    if size:
        out[0] = 1
    return np.multiply.accumulate(out)


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """BASE**0 .. BASE**(n-1), or the inverse powers; cached by rounded size."""
    size = 1 << max(10, int(n - 1).bit_length())
    return _powers(int(INVERSE if inverse else BASE), size)[:n]


def prefix(data: np.ndarray) -> np.ndarray:
    """Prefix sums S with S[j] - S[i] = hash of data[i:j] times BASE**i."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(len(data)), out=out[1:])
    return out


def spans(sums: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """Mixed hashes of data[start:stop]; equal spans have equal hashes wherever they stand."""
    raw = (sums[stop] - sums[start]) * powers(len(sums), inverse=True)[start]
    return mix(raw + (stop - start).astype(np.uint64))


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[32, *range(9, 14)]] = True


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and stop of every run of non-space bytes, and the document each is in.

    Runs never cross a document border.
    """
    n = len(data)
    solid = ~_IS_SPACE[data]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.zeros(n, bool)
    before[1:] = solid[:-1]
    starts = np.flatnonzero(solid & (~before | edge[:-1]))
    after = np.zeros(n, bool)
    after[:-1] = solid[1:]
    stops = np.flatnonzero(solid & (~after | edge[1:])) + 1
    owner = np.searchsorted(offsets, starts, side="right") - 1
    return starts, stops, owner


def shingles(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed word shingles of each document: (document, hash), sorted by both.

    A document with fewer words than `width` has its whole word sequence as one
    shingle; without words it has none. Words are lower-cased in ASCII only.
    """
    starts, stops, owner = word_spans(data, offsets)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    words = spans(prefix(lower_ascii(data)), starts, stops)
    docs = len(offsets) - 1
    count = np.bincount(owner, minlength=docs)
    first = np.zeros(docs + 1, np.int64)
    np.cumsum(count, out=first[1:])
    sums = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * powers(len(words)), out=sums[1:])
    long = np.maximum(count - width + 1, (count > 0).astype(np.int64))
    total = int(long.sum())
    doc = np.repeat(np.arange(docs), long)
    base = np.zeros(docs, np.int64)
    base[1:] = np.cumsum(long)[:-1]
    begin = first[doc] + np.arange(total) - base[doc]
    end = np.minimum(begin + width, first[doc + 1])
    value = spans(sums, begin, end)
    order = np.lexsort((value, doc))
    doc, value = doc[order], value[order]
    keep = np.ones(total, bool)
    keep[1:] = (doc[1:] != doc[:-1]) | (value[1:] != value[:-1])
    return doc[keep], value[keep]
