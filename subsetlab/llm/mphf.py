"""Minimal perfect hash over keys of two 64-bit hashes, built level by level with numpy.

Every level hashes its keys into a bit array of gamma bits a key; keys that are alone at a position are settled there,
the others go on to the next level. A key's number is the rank of its bit, so n keys get 0 .. n-1 in about gamma + 1
bits a key. Foreign keys get some number or -1; callers compare a stored fingerprint.
"""

from __future__ import annotations

import numpy as np

from .kernels import mix

_STEP = 0x9E3779B97F4A7C15


def _place(keys: np.ndarray, prints: np.ndarray, level: int, size: int) -> np.ndarray:
    """Both hashes count, so keys that agree in one of them part at some level."""
    h = mix(mix(keys + np.uint64(_STEP * (level + 1) % 2**64)) ^ prints) >> np.uint64(32)
    return ((h * np.uint64(size)) >> np.uint64(32)).astype(np.int64)


class MinimalPerfectHash:
    def __init__(self, keys: np.ndarray, prints: np.ndarray, gamma: float = 2.0):
        """(key, print) pairs of uint64, distinct as pairs."""
        self.n, self.levels, base = len(keys), [], 0
        rest, more, level = keys, prints, 0
        while len(rest):
            size = max(64, int(len(rest) * gamma) + 63 & ~63)
            at = _place(rest, more, level, size)
            alone = np.bincount(at, minlength=size) == 1
            bits = np.packbits(alone, bitorder="little").view(np.uint64)
            ranks = np.concatenate(([0], np.cumsum(np.bitwise_count(bits))[:-1])).astype(np.int64) + base
            self.levels.append((size, bits, ranks))
            base += int(np.count_nonzero(alone))
            rest, more, level = rest[~alone[at]], more[~alone[at]], level + 1
            if level > 200:
                raise ValueError("pairs are not distinct")

    def __call__(self, keys: np.ndarray, prints: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), -1, np.int64)
        left = np.arange(len(keys))
        for level, (size, bits, ranks) in enumerate(self.levels):
            if not len(left):
                break
            at = _place(keys[left], prints[left], level, size)
            word, bit = at >> 6, (at & 63).astype(np.uint64)
            hit = (bits[word] >> bit) & np.uint64(1) == 1
            below = bits[word[hit]] & ((np.uint64(1) << bit[hit]) - np.uint64(1))
            out[left[hit]] = ranks[word[hit]] + np.bitwise_count(below)
            left = left[~hit]
        return out


class LineIndex:
    """Compact arrays of one shard: fingerprint, document count (saturating at 65535) and smallest document of each key."""

    def __init__(self, keys: np.ndarray, prints: np.ndarray, counts: np.ndarray, owners: np.ndarray):
        self.hash = MinimalPerfectHash(keys, prints)
        at = self.hash(keys, prints)
        self.prints, self.counts, self.owners = np.empty(len(keys), np.uint64), np.empty(len(keys), np.uint16), np.empty(len(keys), np.int64)
        self.prints[at], self.counts[at], self.owners[at] = prints, np.minimum(counts, 65535), owners

    def probe(self, keys: np.ndarray, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(count, smallest document) of each key; count 0 where the shard does not hold it."""
        if not self.hash.n:
            return np.zeros(len(keys), np.uint16), np.full(len(keys), -1, np.int64)
        at = self.hash(keys, prints)
        known = at >= 0
        at[~known] = 0
        known &= self.prints[at] == prints
        return np.where(known, self.counts[at], 0), np.where(known, self.owners[at], -1)
