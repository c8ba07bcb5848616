"""Vectorised byte kernels: words, word hashes, shingles, min-hash signatures over many texts at once.

A span's hash takes eight bytes at a time, all spans side by side; a span of over BLOCK bytes is cut into blocks and the
blocks' hashes are hashed again. Every step multiplies and shifts, so no text structure cancels out, and two seeds give
hashes that do not collide together.
"""

from __future__ import annotations

import numpy as np

FIRST, SECOND = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
BLOCK = 256
MISSING = np.uint64(0xD6E8FEB86659FD93)
SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Separators where words are runs of ASCII letters, digits and non-ASCII bytes.
NOT_ALNUM = np.ones(256, bool)
NOT_ALNUM[48:58] = NOT_ALNUM[65:91] = NOT_ALNUM[97:123] = False
NOT_ALNUM[128:] = False

def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0x9FB21C651E98DF25)
    h ^= h >> np.uint64(32)
    return h


def _words_at(cells: np.ndarray, at: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Eight bytes from every position of an aligned buffer, those behind the first left ones zero."""
    cell, shift = at >> 3, ((at & 7) << 3).astype(np.uint64)
    word = cells[cell] >> shift | cells[cell + 1] << (np.uint64(64) - shift)
    return word & np.uint64(2**64 - 1) >> (np.uint64(64) - (np.minimum(left, 8) << 3).astype(np.uint64))


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: np.uint64 = FIRST) -> np.ndarray:
    """64-bit hash of data[start:end] for every span."""
    size = (ends - starts).astype(np.int64)
    out = np.full(len(size), seed, np.uint64)
    left = np.where(size > BLOCK, 0, size)
    cells = np.zeros(len(data) // 8 + 2, np.uint64)
    cells.view(np.uint8)[: len(data)] = data
    live = np.flatnonzero(left)
    for step in range(0, int(left.max()) if len(left) else 0, 8):
        live = live[left[live] > step]
        h = (out[live] ^ _words_at(cells, starts[live] + step, left[live] - step)) * (seed | np.uint64(1))
        out[live] = h ^ h >> np.uint64(32)
    wide = np.flatnonzero(size > BLOCK)
    if len(wide):
        count = -(-size[wide] // BLOCK)
        first = np.concatenate(([0], np.cumsum(count)))
        begin = np.repeat(starts[wide], count) + BLOCK * ranges(np.zeros(len(wide), np.int64), count)
        parts = span_hashes(data, begin, np.minimum(begin + BLOCK, np.repeat(ends[wide], count)), seed)
        out[wide] = span_hashes(parts.view(np.uint8), 8 * first[:-1], 8 * first[1:], mix(seed + np.zeros(1, np.uint64))[0])
    return mix(out + size.astype(np.uint64) * MISSING)


def word_spans(data: np.ndarray, offs: np.ndarray, space: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words, and each row's first word: row i has words first[i]:first[i+1]."""
    n = len(data)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offs), np.int64)
    word = ~space[data]
    begins, stops = word.copy(), word.copy()
    begins[1:] &= ~word[:-1]
    stops[:-1] &= ~word[1:]
    edge = offs[:-1][offs[:-1] < offs[1:]]
    begins[edge] = word[edge]
    last = offs[1:][offs[:-1] < offs[1:]] - 1
    stops[last] = word[last]
    starts = np.flatnonzero(begins)
    return starts, np.flatnonzero(stops) + 1, np.searchsorted(starts, offs)


def ranges(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Concatenation of first[i] .. first[i]+count[i]-1."""
    total = int(count.sum())
    if total == 0:
        return np.zeros(0, np.int64)
    at = np.repeat(first - np.concatenate(([0], np.cumsum(count)[:-1])), count)
    return at + np.arange(total)


def shingle_hashes(words: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word shingles of all rows, and each row's first shingle; a row of 1 to k-1 words has one."""
    n_words = np.diff(first)
    count = np.where(n_words > 0, np.maximum(n_words - k + 1, 1), 0)
    at = np.concatenate(([0], np.cumsum(count)))
    if at[-1] == 0:
        return np.zeros(0, np.uint64), at
    start, stop = ranges(first[:-1], count), np.repeat(first[1:], count)
    h = np.zeros(len(start), np.uint64)
    padded = np.concatenate((words, np.full(k, MISSING)))
    for j in range(k):
        w = padded[start + j]
        w[start + j >= stop] = MISSING
        h = h * np.uint64(0xA24BAED4963EE407) + w
        h ^= h >> np.uint64(31)
    return mix(h), at


def text_shingles(data: np.ndarray, offs: np.ndarray, k: int, space: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of lower-cased rows (with repeats), and row boundaries."""
    low = LOWER[data]
    starts, ends, first = word_spans(low, offs, space)
    words = span_hashes(low, starts, ends) if len(starts) else np.zeros(0, np.uint64)
    return shingle_hashes(words, first, k)


class MinHasher:
    """n min-hashes of every row; rows without shingles get none (the caller leaves them out)."""

    def __init__(self, n: int, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.xor = rng.integers(0, 2**64, n, dtype=np.uint64)
        self.mul = rng.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def __call__(self, shingles: np.ndarray, at: np.ndarray) -> np.ndarray:
        """(rows, n) signature; at has the row boundaries, all rows non-empty."""
        out = np.empty((len(at) - 1, len(self.xor)), np.uint64)
        for i, (x, m) in enumerate(zip(self.xor, self.mul, strict=True)):
            out[:, i] = np.minimum.reduceat((shingles ^ x) * m, at[:-1])
        return out
