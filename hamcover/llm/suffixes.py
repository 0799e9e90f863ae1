"""Suffix arrays over arrays of word codes, in numpy."""

from __future__ import annotations

import numpy as np


def dense(values: np.ndarray) -> np.ndarray:
    """Ranks from 1 of the values."""
    return np.unique(values, return_inverse=True)[1].astype(np.int64) + 1


def suffix_array(codes: np.ndarray, depth: int) -> np.ndarray:
    """Positions sorted by their next `depth` codes at least. Codes are from 0; what lies behind the end is least.

    Prefix doubling: ranks by 2k codes are ranks of pairs of ranks by k codes. It stops when all ranks differ.
    """
    n = len(codes)
    if n == 0:
        return np.empty(0, np.int64)
    rank, k = codes.astype(np.int64) + 1, 1
    if depth <= 1:
        return np.argsort(rank, kind="stable")
    while True:
        key = rank * (int(rank.max()) + 1)
        key[: n - k] += rank[k:]
        order = np.argsort(key)
        ordered = key[order]
        fresh = np.empty(n, np.int64)
        fresh[0] = 1
        np.cumsum(ordered[1:] != ordered[:-1], out=fresh[1:])
        fresh[1:] += 1
        rank = np.empty(n, np.int64)
        rank[order] = fresh
        k *= 2
        if k >= depth or fresh[-1] == n:
            return order


class Shard:
    """A suffix array over text, searched for many patterns at once. Patterns are suffixes of `pattern`,
    which ends each of its texts with -1; no code of the text is below 0."""

    def __init__(self, text: np.ndarray, depth: int):
        self.n = len(text)
        self.order = suffix_array(text, depth)
        self.text = np.concatenate([text, np.full(1, -2, np.int64)])

    def common(self, at: np.ndarray, pattern: np.ndarray, starts: np.ndarray, most: np.ndarray | None = None) -> np.ndarray:
        """Codes that the text from `at` on has in common with the pattern from `starts` on, up to `most`."""
        length = np.zeros(len(at), np.int64)
        live = np.arange(len(at))
        while len(live):
            off = length[live]
            same = self.text[np.minimum(at[live] + off, self.n)] == pattern[starts[live] + off]
            if most is not None:
                same &= off < most[live]
            live = live[same]
            length[live] += 1
        return length

    def bound(self, pattern: np.ndarray, starts: np.ndarray, most: np.ndarray | None = None, upper: bool = False) -> np.ndarray:
        """Binary search of all patterns in step: the first place in the order that isn't below the pattern (upper: above it).
        With `most`, only so many codes of a pattern count."""
        lo, hi = np.zeros(len(starts), np.int64), np.full(len(starts), self.n, np.int64)
        live = np.flatnonzero(lo < hi)
        while len(live):
            mid = (lo[live] + hi[live]) >> 1
            at = self.order[mid]
            limit = None if most is None else most[live]
            n = self.common(at, pattern, starts[live], limit)
            a, b = self.text[np.minimum(at + n, self.n)], pattern[starts[live] + n]
            right = a < b
            if most is not None:
                right = np.where(n == limit, upper, right)
            lo[live] = np.where(right, mid + 1, lo[live])
            hi[live] = np.where(right, hi[live], mid)
            live = live[lo[live] < hi[live]]
        return lo

    def longest(self, pattern: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Length of the longest match of each pattern's beginning anywhere in the text: it is at a neighbour of the pattern's place."""
        if not self.n:
            return np.zeros(len(starts), np.int64)
        place = self.bound(pattern, starts)
        left = self.common(self.order[np.maximum(place - 1, 0)], pattern, starts)
        right = self.common(self.order[np.minimum(place, self.n - 1)], pattern, starts)
        return np.maximum(left, right)
