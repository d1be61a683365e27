"""A sharded minimal perfect hash in numpy, built level by level from bit arrays."""

from __future__ import annotations

import numpy as np

#: Bits per key that is still to place, on every level; levels before the rest is kept as it is.
SPREAD, LEVELS = 2, 40
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))  # fixed values: a 64-bit finaliser


def scramble(keys: np.ndarray, level: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = keys + np.uint64((level + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> np.uint64(30))) * _MIX[0]
        x = (x ^ (x >> np.uint64(27))) * _MIX[1]
        return x ^ (x >> np.uint64(31))


class PerfectHash:
    """Distinct 64-bit keys to 0 .. n-1, without the keys themselves: about 3 bits a key and a running count.

    ``levels``: per level (size in bits, packed bits, keys placed before each 64-bit word).
    """

    def __init__(self, keys: np.ndarray):
        keys = np.asarray(keys, np.uint64)
        self.size, self.levels, placed = len(keys), [], 0
        for level in range(LEVELS):
            if not len(keys):
                break
            bits = max(64, -(-SPREAD * len(keys) // 64) * 64)
            at = (scramble(keys, level) % np.uint64(bits)).astype(np.int64)
            alone = np.bincount(at, minlength=bits) == 1
            words = np.packbits(alone, bitorder="little").view(np.uint64)
            before = placed + np.concatenate(([0], np.cumsum(np.bitwise_count(words), dtype=np.int64)[:-1]))
            self.levels.append((bits, words, before))
            placed += int(alone.sum())
            keys = keys[~alone[at]]
        self.rest = np.sort(keys)  # empty but in freak cases
        self.placed = placed

    def index(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key; for a key that was not built in, some place or -1."""
        keys = np.asarray(keys, np.uint64)
        out = np.full(len(keys), -1, np.int64)
        open_ = np.arange(len(keys))
        for level, (bits, words, before) in enumerate(self.levels):
            if not len(open_):
                break
            at = (scramble(keys[open_], level) % np.uint64(bits)).astype(np.int64)
            word, bit = words[at >> 6], (at & 63).astype(np.uint64)
            hit = (word >> bit) & np.uint64(1) == 1
            below = np.bitwise_count(word & ((np.uint64(1) << bit) - np.uint64(1)))
            out[open_[hit]] = (before[at >> 6] + below)[hit]
            open_ = open_[~hit]
        if len(open_) and len(self.rest):
            at = np.minimum(np.searchsorted(self.rest, keys[open_]), len(self.rest) - 1)
            same = self.rest[at] == keys[open_]
            out[open_[same]] = self.placed + at[same]
        return out


class CountShard:
    """A perfect hash over one half of 128-bit line hashes, with the other half as fingerprint and a count each."""

    def __init__(self, key: np.ndarray, check: np.ndarray, count: np.ndarray):
        # the hash places the first halves; keys that share one get a slot under the first and the others stand aside
        first, at = np.unique(key, return_index=True)
        others = np.setdiff1d(np.arange(len(key)), at)
        self.hash = PerfectHash(first)
        slot = self.hash.index(first)
        self.check, self.count = np.zeros(len(first), np.uint64), np.zeros(len(first), np.int64)
        self.check[slot], self.count[slot] = check[at], count[at]
        self.aside = {(int(key[i]), int(check[i])): int(count[i]) for i in others}

    def counts(self, key: np.ndarray, check: np.ndarray) -> np.ndarray:
        """The count of each 128-bit hash, 0 where it is not in the shard."""
        out = np.zeros(len(key), np.int64)
        if len(self.check):
            slot = self.hash.index(key)
            known = slot >= 0
            known[known] = self.check[slot[known]] == check[known]
            out[known] = self.count[slot[known]]
        if self.aside:
            for i in np.flatnonzero(out == 0):
                out[i] = self.aside.get((int(key[i]), int(check[i])), 0)
        return out
