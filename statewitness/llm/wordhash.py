"""Vectorised hashing of words and word n-grams over whole batches of texts.

Words are maximal runs of bytes other than ASCII white space. A word's hash is a polynomial in an odd
multiplier over random values of its bytes, taken from one running sum over the batch; an n-gram's
hash is the same over its words' hashes. Both are mixed and are 64 bits wide; two families with
independent seeds give 128 bits.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


#: Most powers that are kept between texts (8 MB); longer texts have theirs made anew.
KEPT_POWERS = 1 << 20


class Powers:
    """Powers of an odd number and of its inverse modulo 2**64; a bounded number of them is kept."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(0, np.uint64)

    @staticmethod
    def made(b: int, n: int) -> np.ndarray:
        out = np.full(n, b, np.uint64)
        out[0] = 1
        return np.multiply.accumulate(out)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > KEPT_POWERS:
            return self.made(self.base, n), self.made(self.inverse, n)
        if len(self.up) < n:
            size = max(n, 1 << 16)
            self.up, self.down = self.made(self.base, size), self.made(self.inverse, size)
        return self.up[:n], self.down[:n]


class Family:
    """One seeded hash family; ``fold_case`` makes A-Z count as a-z."""

    def __init__(self, seed: int, fold_case: bool = False):
        rng = np.random.Generator(np.random.PCG64(seed))
        self.table = rng.integers(0, 1 << 64, 256, np.uint64)
        if fold_case:
            self.table[0x41:0x5B] = self.table[0x61:0x7B]
        self.bytes, self.words = (Powers(int(x) | 1) for x in rng.integers(0, 1 << 64, 2, np.uint64))

    def word_hashes(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        up, down = self.bytes.get(len(raw))
        run = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(self.table[raw] * up, out=run[1:])
        return mix((run[ends] - run[starts]) * down[starts] + (ends - starts).astype(np.uint64))

    def spans(self, hashes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hashes of the word sequences [start, end)."""
        up, down = self.words.get(len(hashes) + 1)
        run = np.zeros(len(hashes) + 1, np.uint64)
        np.cumsum(hashes * up[:-1], out=run[1:])
        return mix((run[ends] - run[starts]) * down[starts] + (ends - starts).astype(np.uint64))

    def grams(self, hashes: np.ndarray, n: int) -> np.ndarray:
        """Hashes of every n consecutive words, also across documents (the caller masks those)."""
        count = len(hashes) - n + 1
        if count <= 0:
            return np.zeros(0, np.uint64)
        at = np.arange(count)
        return self.spans(hashes, at, at + n)


@lru_cache(8)
def family(seed: int, fold_case: bool = False) -> Family:
    """The family of a seed, made once in a worker."""
    return Family(seed, fold_case)


@dataclass
class Words:
    """Words of a batch: byte bounds, and for each text the range of its words."""

    raw: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    docs: np.ndarray

    @property
    def doc_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.docs) - 1), np.diff(self.docs))


def find_words(raw: np.ndarray, offsets: np.ndarray) -> Words:
    """Words of each text in one buffer; no word crosses a text's bounds."""
    n = len(raw)
    if not n:
        none = np.zeros(0, np.int64)
        return Words(raw, none, none, np.zeros(len(offsets), np.int64))
    space = SPACE[raw]
    before, after = np.empty(n, bool), np.empty(n, bool)
    before[0] = after[-1] = True
    before[1:], after[:-1] = space[:-1], space[1:]
    before[offsets[:-1][offsets[:-1] < n]] = True
    after[offsets[1:][offsets[1:] > 0] - 1] = True
    starts = np.flatnonzero(~space & before)
    ends = np.flatnonzero(~space & after) + 1
    return Words(raw, starts, ends, np.searchsorted(starts, offsets))


def inside(words: Words, n: int) -> np.ndarray:
    """Whether the n words from each position on lie in one text (positions with n words left)."""
    count = len(words.starts) - n + 1
    if count <= 0:
        return np.zeros(0, bool)
    last = np.repeat(words.docs[1:], np.diff(words.docs))[:count]
    return np.arange(count) + n <= last
