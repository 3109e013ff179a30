"""Hashed word and character n-gram features of many words at once.

Words lie end to end in one byte buffer, each between a begin and an end mark. A position-free
polynomial hash modulo 2**64 of any slice is a difference of two running sums times a power of
the inverse base, so all n-grams of all words come from a few array operations.
"""

from __future__ import annotations

import numpy as np

BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
INVERSE = np.uint64(pow(int(BASE), -1, 2**64))
_MIX = np.uint64(0xD6E8FEB86659FD93)
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power(which: int, n: int) -> np.ndarray:
    if len(_powers[which]) < n:
        base = (BASE, INVERSE)[which]
        all_but_first = np.full(n * 2, base, np.uint64)
        all_but_first[0] = 1
        _powers[which] = np.cumprod(all_but_first)
    return _powers[which][:n]


class Buffer:
    """Words as b'<word>' slices of one buffer, with slice hashes."""

    def __init__(self, words: list[bytes]):
        joined = b"<" + b"><".join(words) + b">"
        flat = np.frombuffer(joined, np.uint8).astype(np.uint64) + np.uint64(1)
        self.sizes = np.fromiter(map(len, words), np.int64, len(words)) + 2
        self.ends = np.cumsum(self.sizes)
        self.starts = self.ends - self.sizes
        self.n = len(flat)
        self.sums = np.zeros(self.n + 1, np.uint64)
        np.cumsum(flat * _power(0, self.n), out=self.sums[1:])
        self.undo = _power(1, self.n + 1)
        self.word_of = np.repeat(np.arange(len(words)), self.sizes)

    def slices(self, at: np.ndarray, size, kind: int, bits: int) -> np.ndarray:
        """Bucket of each slice; kind keeps feature families apart."""
        h = (self.sums[at + size] - self.sums[at]) * self.undo[at]
        h = (h ^ (h >> np.uint64(31)) ^ np.uint64(kind * 0x51ED27)) * _MIX
        return ((h ^ (h >> np.uint64(29))) * BASE >> np.uint64(64 - bits)).astype(np.int64)

    def grams(self, n: int, kind: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
        """(word, bucket) of every n-gram, marks included."""
        at = np.arange(max(0, self.n - n + 1))
        at = at[at + n <= self.ends[self.word_of[at]]]
        return self.word_of[at], self.slices(at, n, kind, bits)

    def whole(self, kind: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
        return np.arange(len(self.sizes)), self.slices(self.starts, self.sizes, kind, bits)

    def affixes(self, n: int, kind: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
        """Prefix and suffix of n bytes of every word that is long enough."""
        w = np.flatnonzero(self.sizes >= n + 2)
        head = self.slices(self.starts[w], n + 1, kind, bits)
        tail = self.slices(self.ends[w] - n - 1, n + 1, kind + 1, bits)
        return np.concatenate([w, w]), np.concatenate([head, tail])


def by_word(parts: list[tuple[np.ndarray, np.ndarray]], n_words: int) -> tuple[np.ndarray, np.ndarray]:
    """(bucket sorted by word, first place of each word's features); every word needs a feature."""
    word = np.concatenate([p[0] for p in parts])
    bucket = np.concatenate([p[1] for p in parts])
    order = np.argsort(word, kind="stable")
    return bucket[order], np.searchsorted(word[order], np.arange(n_words))


def in_parts(features, words: list[bytes], most: int = 20_000) -> tuple[np.ndarray, np.ndarray]:
    """features(words) of many words with bounded working memory; buckets as 32-bit numbers."""
    buckets, firsts, base = [], [], 0
    for s in range(0, len(words), most):
        bucket, first = features(words[s : s + most])
        buckets.append(bucket.astype(np.int32))
        firsts.append(first + base)
        base += len(bucket)
    return np.concatenate(buckets), np.concatenate(firsts)
