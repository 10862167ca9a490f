"""Polynomial hashes of byte ranges, worked out for whole Arrow batches at once.

Prefix sums are taken modulo 2**64 with a random word for each byte value: the sum over a range,
multiplied by the inverse power of its start, depends on its bytes alone.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np

BASE = 0x9E3779B97F4A7C15 | 5  # odd, so it has an inverse modulo 2**64
_M = (1 << 64) - 1


@lru_cache(maxsize=8)
def byte_words(seed: int) -> np.ndarray:
    """A random 64-bit word for each byte value."""
    return np.array([int.from_bytes(hashlib.blake2b(bytes([seed, b]), digest_size=8).digest(), "little") for b in range(256)], np.uint64)


_tables: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and BASE**-i for i from 0 to n at least."""
    have = _tables.get("up")
    if have is None or len(have) <= n:
        size = max(1 << 16, 1 << int(n + 1).bit_length())
        up = np.full(size, BASE & _M, np.uint64)
        down = np.full(size, pow(BASE, -1, 1 << 64), np.uint64)
        up[0] = down[0] = 1
        _tables["up"], _tables["down"] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _tables["up"], _tables["down"]


def prefix(data: np.ndarray, seed: int = 1) -> np.ndarray:
    """Prefix hash: entry i covers the first i bytes."""
    up, _ = powers(len(data))
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(byte_words(seed)[data] * up[: len(data)], out=out[1:])
    return out


def ranges(pre: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each byte range [start, end)."""
    return (pre[end] - pre[start]) * _tables["down"][start]


def mix(h: np.ndarray) -> np.ndarray:
    """A one-to-one scrambling of 64-bit words, so that every bit depends on all."""
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0x7FB5D329728EA185)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: The white space that ends a word, 0x20 and 0x09 to 0x0D.
WORD = np.ones(256, bool)
WORD[[0x20, 9, 10, 11, 12, 13]] = False
#: A token of at least so many bytes is hashed alone, to keep the power tables short.
GIANT = 1 << 17


def spans(data: np.ndarray, offsets: np.ndarray, classes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of every token: a longest run of bytes of one class but class 0, within a row."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    kind = classes[data]
    cut = np.empty(len(data) + 1, bool)
    cut[0] = cut[-1] = True
    np.not_equal(kind[1:], kind[:-1], out=cut[1:-1])
    cut[offsets] = True
    at = np.flatnonzero(cut)
    start, end = at[:-1], at[1:]
    keep = kind[start] != 0
    start, end = start[keep], end[keep]
    return start, end, np.searchsorted(offsets, start, "right") - 1


def token_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, block: int = 1 << 16) -> np.ndarray:
    """A scrambled hash of each token, worked out block by block."""
    out = np.empty(len(start), np.uint64)
    giant = np.flatnonzero(end - start >= GIANT)
    for i in giant:
        out[i] = int.from_bytes(hashlib.blake2b(data[start[i] : end[i]].tobytes(), digest_size=8).digest(), "little")
    a = 0
    while a < len(start):
        if end[a] - start[a] >= GIANT:
            a += 1
            continue
        b = int(np.searchsorted(start, start[a] + block, "left"))
        later = giant[(giant > a) & (giant < b)]
        b = int(later[0]) if len(later) else b
        low = start[a]
        pre = prefix(data[low : end[b - 1]])
        out[a:b] = mix(ranges(pre, start[a:b] - low, end[a:b] - low))
        a = b
    return out


def shingles(words: np.ndarray, n: int = 5) -> np.ndarray:
    """Hash of each run of n words; of the whole sequence if it is shorter; nothing if there are none."""
    k = min(n, len(words))
    if not k:
        return words
    m = np.uint64(0xD6E8FEB86659FD93)
    out = words[: len(words) - k + 1].copy()
    for i in range(1, k):
        out *= m
        out += words[i : len(words) - k + 1 + i]
    return mix(out + np.uint64(k))
