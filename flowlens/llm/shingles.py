"""Word-shingle sets as sorted 64-bit hashes, computed for a whole text in vector operations."""

from __future__ import annotations

import numpy as np

WORDS = 5
#: An odd multiplier and its inverse modulo 2^64: prefix sums of byte * inverse^i give the hash of any byte range.
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)
MASK = (1 << 64) - 1


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Powers:
    """Powers of BASE and INVERSE, grown as longer texts come."""

    def __init__(self):
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << max(16, n.bit_length())
            self.up, self.down = (np.full(size, x, np.uint64) for x in (BASE, INVERSE))
            for powers in (self.up, self.down):
                powers[0] = 1
                np.cumprod(powers, out=powers)
        return self.up, self.down


#: Space, tab to carriage return.
BLANK = np.zeros(256, bool)
BLANK[[0x20, 9, 10, 11, 12, 13]] = True


def shingle_set(text: str | None, powers: Powers, words: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a text: A-Z lower-cased, words without blanks, `words` words each. A shorter text is
    one shingle of all its words; null or blank texts have none."""
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    if not len(raw):
        return np.zeros(0, np.uint64)
    low = raw + ((raw >= 65) & (raw <= 90)) * np.uint8(32)
    gap = BLANK[raw]
    edge = np.diff(np.concatenate([[True], gap, [True]]).astype(np.int8))
    start, end = np.flatnonzero(edge < 0), np.flatnonzero(edge > 0)
    if not len(start):
        return np.zeros(0, np.uint64)
    up, down = powers.upto(len(raw) + 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum((low.astype(np.uint64) + np.uint64(1)) * down[: len(raw)], dtype=np.uint64)])
    word = mixed((total[end] - total[start]) * up[start] + (end - start).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    k = min(words, len(word))
    acc = np.zeros(len(word) - k + 1, np.uint64)
    for i in range(k):
        acc = acc * np.uint64(BASE) + word[i : len(word) - k + 1 + i]
    return np.unique(mixed(acc + np.uint64(k)))


def coefficients(n: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 1 << 32, n, dtype=np.uint32) | np.uint32(1), rng.integers(0, 1 << 32, n, dtype=np.uint32)


def minhash(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least value of every multiply-shift hash over the set."""
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    low = (shingles >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(low), 2048):
        part = low[i : i + 2048]
        h = part[None, :] * a[:, None]
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA6B)
        h += b[:, None]
        h ^= h >> np.uint32(13)
        np.minimum(out, h.min(axis=1), out=out)
    return out
