"""A compressed full-text index over word codes: the Burrows-Wheeler transform in a wavelet matrix, searched for many patterns in step."""

from __future__ import annotations

import numpy as np

from hamcover.llm.suffixes import suffix_array


class Bits:
    """A bit vector with ranks: 64-bit words and the count of ones before each."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        packed = np.zeros((n >> 6) + 1, np.uint64)
        data = np.packbits(bits, bitorder="little")
        packed.view(np.uint8)[: len(data)] = data
        self.words = packed
        ones = np.bitwise_count(packed).astype(np.int32)
        self.before = np.zeros(len(packed), np.int32)
        np.cumsum(ones[:-1], out=self.before[1:])
        self.zeros = n - int(ones.sum())

    def get(self, at: np.ndarray) -> np.ndarray:
        return ((self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)

    def rank(self, at: np.ndarray) -> np.ndarray:
        """Ones before each place."""
        word = at >> 6
        mask = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[word] + np.bitwise_count(self.words[word] & mask)


class WaveletMatrix:
    def __init__(self, symbols: np.ndarray, sigma: int):
        self.levels: list[Bits] = []
        self.height = max(1, int(sigma - 1).bit_length())
        now = symbols
        for level in range(self.height - 1, -1, -1):
            ones = ((now >> level) & 1).astype(bool)
            self.levels.append(Bits(ones))
            now = np.concatenate([now[~ones], now[ones]])
        every = np.arange(sigma, dtype=np.int64)
        self.first = self._down(every, np.zeros(sigma, np.int64))

    def _down(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        for bits, level in zip(self.levels, range(self.height - 1, -1, -1), strict=True):
            ones = bits.rank(at)
            at = np.where((symbols >> level) & 1, bits.zeros + ones, at - ones)
        return at

    def rank(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol stands before each place."""
        return self._down(symbols, at) - self.first[symbols]

    def before(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each place, and how often it stands before."""
        symbols = np.zeros(len(at), np.int64)
        for bits, level in zip(self.levels, range(self.height - 1, -1, -1), strict=True):
            one, ones = bits.get(at), bits.rank(at)
            symbols |= one.astype(np.int64) << level
            at = np.where(one, bits.zeros + ones, at - ones)
        return symbols, at - self.first[symbols]


class FmIndex:
    """Index of segments of codes, one behind the other, with a separator (0) behind each. Codes are 1 to sigma - 1.

    What stays is the wavelet matrix, and the segment's number for every `sample`-th place of a segment. Which segment a row of the order
    lies in is told by going back from place to place until a sampled one is met; no segment's first place is passed. Separators sort by
    their segment, so no order goes beyond a segment's end.
    """

    def __init__(self, codes: np.ndarray, sizes: np.ndarray, sigma: int, sample: int = 4):
        count = len(sizes)
        owner = np.repeat(np.arange(count, dtype=np.int32), sizes + 1)
        self.n, self.begins = len(owner), np.cumsum(sizes + 1) - sizes - 1
        offset = np.arange(self.n) - np.repeat(self.begins, sizes + 1)
        self.text = np.zeros(self.n, np.int32)
        inside = offset < np.repeat(sizes, sizes + 1)
        self.text[inside] = codes
        order = suffix_array(np.where(inside, self.text.astype(np.int64) + count, owner), self.n)
        self.bwt = WaveletMatrix(self.text[order - 1], sigma)
        self.less = np.concatenate([[0], np.cumsum(np.bincount(self.text, minlength=sigma))])
        marked = (offset % sample == 0)[order]
        self.marks, self.samples = Bits(marked), owner[order[marked]]

    def extend(self, symbols: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One step of backward search: ranges of symbol + pattern from those of pattern."""
        both = self.bwt.rank(np.concatenate([symbols, symbols]), np.concatenate([lo, hi]))
        base = self.less[symbols]
        return base + both[: len(lo)], base + both[len(lo) :]

    def owners(self, rows: np.ndarray) -> np.ndarray:
        """The segment of each row of the order; not for rows of separators."""
        out, live, at = np.empty(len(rows), np.int32), np.arange(len(rows)), rows
        while len(live):
            known = self.marks.get(at)
            out[live[known]] = self.samples[self.marks.rank(at[known])]
            live, at = live[~known], at[~known]
            symbols, ranks = self.bwt.before(at)
            at = self.less[symbols] + ranks
        return out

    def matching_statistics(self, stream: np.ndarray, ends: np.ndarray, most: int, least: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each end place in the stream (exclusive): length, up to `most`, of the longest suffix of the stream
        there that occurs at `least` places of the text, and its range in the order. Codes of the stream that the text lacks are 0."""
        length, low, high = np.zeros(len(ends), np.int64), np.zeros(len(ends), np.int64), np.full(len(ends), self.n, np.int64)
        live = np.arange(len(ends))
        for step in range(1, most + 1):
            at = ends[live] - step
            symbols = np.where(at >= 0, stream[np.maximum(at, 0)], 0)
            some = symbols > 0
            live, symbols = live[some], symbols[some]
            if not len(live):
                break
            if step == 1:
                lo, hi = self.less[symbols], self.less[symbols + 1]
            else:
                lo, hi = self.extend(symbols, low[live], high[live])
            some = hi - lo >= least
            live = live[some]
            low[live], high[live], length[live] = lo[some], hi[some], step
        return length, low, high
