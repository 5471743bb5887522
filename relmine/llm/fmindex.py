"""A compressed FM-index over short word sequences, with matching statistics.

The index holds many sequences in one text, each ended by its own mark. The
Burrows-Wheeler transform is kept as a wavelet tree of packed bit vectors with a
count per 64 bits. Backward search extends a match to the left; where it fails
the match gives up words on the right by moving to the parent interval of the
longest-common-prefix array. All queries advance in step, so each step is a few
array operations over all of them.
"""

from __future__ import annotations

import numpy as np


class WaveletTree:
    """rank(symbol, i) over an integer array, level by level on packed bits."""

    def __init__(self, symbols: np.ndarray, sigma: int):
        self.levels = max(1, int(sigma - 1).bit_length())
        self.bits, self.ones, self.zeros = [], [], []
        rest = symbols.astype(np.int64)
        for level in range(self.levels - 1, -1, -1):
            bit = (rest >> level) & 1
            padded = np.zeros(-(-(len(bit) + 1) // 64) * 64, np.uint8)
            padded[:len(bit)] = bit
            words = np.packbits(padded, bitorder="little").view(np.uint64)
            self.bits.append(words)
            self.ones.append(np.concatenate([[0], np.cumsum(np.bitwise_count(words).astype(np.int64))[:-1]]).astype(np.int32))
            self.zeros.append(int(len(bit) - bit.sum()))
            rest = np.concatenate([rest[bit == 0], rest[bit == 1]])

    def _ones(self, level: int, i: np.ndarray) -> np.ndarray:
        word, off = i >> 6, (i & 63).astype(np.uint64)
        mask = (np.uint64(1) << off) - np.uint64(1)
        return self.ones[level][word] + np.bitwise_count(self.bits[level][word] & mask).astype(np.int64)

    def count_before(self, symbol: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Occurrences of ``symbol`` before i and before j."""
        start = np.zeros_like(i)
        for n in range(self.levels):
            bit = (symbol >> (self.levels - 1 - n)) & 1
            a, b, c = self._ones(n, i), self._ones(n, j), self._ones(n, start)
            one = bit == 1
            i = np.where(one, self.zeros[n] + a, i - a)
            j = np.where(one, self.zeros[n] + b, j - b)
            start = np.where(one, self.zeros[n] + c, start - c)
        return i - start, j - start


class FmIndex:
    """Over sequences of word codes (uint64), each with an owner; a match counts in smaller owners only."""

    def __init__(self, sequences: list[np.ndarray], owners: np.ndarray):
        m = len(sequences)
        sizes = np.fromiter(map(len, sequences), np.int64, m)
        words, codes = np.unique(np.concatenate(sequences), return_inverse=True)
        ends = np.cumsum(sizes + 1) - 1
        text = np.empty(int(sizes.sum()) + m, np.int64)
        is_end = np.zeros(len(text), bool)
        is_end[ends] = True
        text[is_end] = np.arange(m)  # its own mark ends each sequence, so suffixes never tie
        text[~is_end] = codes + m
        self.sizes, self.ends, self.codes = sizes, ends, text
        order, ranks = self._sorted(text, int(sizes.max(initial=1)) + 1)
        self.n = len(text)
        owner_of = np.repeat(owners, sizes + 1)
        self.lcp = self._common(order, ranks)
        self.before, self.after = self._walls(self.lcp)
        # word w has symbol w + 1; all marks share symbol 0, which no query asks for
        last = text[order - 1]
        self.tree = WaveletTree(np.where(last < m, 0, last - m + 1), len(words) + 1)
        self.first = np.concatenate([[0, m], m + np.cumsum(np.bincount(codes, minlength=len(words)))])
        self.m, self.owners = m, owners
        self.least = [owner_of[order]]
        while 2 << (len(self.least) - 1) <= self.n:
            half = 1 << (len(self.least) - 1)
            self.least.append(np.minimum(self.least[-1][:-half], self.least[-1][half:]))

    @staticmethod
    def _sorted(text: np.ndarray, longest: int) -> tuple[np.ndarray, list[np.ndarray]]:
        """Suffix order by doubling, and the ranks by the first 1, 2, 4, ... symbols."""
        n = len(text)
        rank = np.unique(text, return_inverse=True)[1].astype(np.int64)
        ranks, width = [rank.astype(np.int32)], 1
        while width < longest:
            other = np.full(n, -1, np.int64)
            other[:n - width] = rank[width:]
            key = rank * (n + 1) + other + 1
            order = np.argsort(key, kind="stable")
            sorted_key = key[order]
            rank = np.empty(n, np.int64)
            rank[order] = np.concatenate([[0], np.cumsum(sorted_key[1:] != sorted_key[:-1])])
            ranks.append(rank.astype(np.int32))
            width *= 2
            if rank.max(initial=0) == n - 1:
                break
        return np.argsort(rank, kind="stable"), ranks

    @staticmethod
    def _common(order: np.ndarray, ranks: list[np.ndarray]) -> np.ndarray:
        n = len(order)
        a, b, out = order[:-1].copy(), order[1:].copy(), np.zeros(n - 1, np.int64)
        for level in range(len(ranks) - 1, -1, -1):
            inside = (a < n) & (b < n)
            same = inside & (ranks[level][np.minimum(a, n - 1)] == ranks[level][np.minimum(b, n - 1)])
            step = same.astype(np.int64) << level
            out, a, b = out + step, a + step, b + step
        return np.concatenate([[-1], out, [-1]]).astype(np.int64)  # walls at both ends

    @staticmethod
    def _walls(lcp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each place the nearest one before and after it with a smaller value, by pointer jumping."""
        def nearest(v: np.ndarray) -> np.ndarray:
            t = np.arange(len(v)) - 1
            t[0] = 0
            while True:
                wrong = np.flatnonzero((v[t] >= v) & (t > 0))
                if not len(wrong):
                    return t
                t[wrong] = t[t[wrong]]

        back = nearest(lcp)
        return back, len(lcp) - 1 - nearest(lcp[::-1])[::-1]

    def _least(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Smallest owner in [lo, hi), which holds at least one row."""
        level = np.frexp((hi - lo).astype(np.float64))[1] - 1
        out = np.empty(len(lo), self.owners.dtype)
        for k in np.unique(level):
            at = np.flatnonzero(level == k)
            row = self.least[k]
            out[at] = np.minimum(row[lo[at]], row[hi[at] - (1 << int(k))])
        return out

    def matching_statistics(self) -> np.ndarray:
        """For each place of the text, the longest match that starts there and also stands in a sequence
        of a smaller owner; marks have 0."""
        out = np.zeros(self.n, np.int64)
        who = np.arange(self.m)
        at = self.ends - 1
        first_of = self.ends - self.sizes
        lo, hi, size = np.zeros(self.m, np.int64), np.full(self.m, self.n), np.zeros(self.m, np.int64)
        while True:
            live = at >= first_of
            if not live.all():
                who, at, first_of, lo, hi, size = (x[live] for x in (who, at, first_of, lo, hi, size))
            if not len(who):
                return out
            symbol = self.codes[at] - self.m + 1
            a, b = self.tree.count_before(symbol, lo, hi)
            a, b = self.first[symbol] + a, self.first[symbol] + b
            good = a < b
            good[good] = self._least(a[good], b[good]) < self.owners[who[good]]
            size = np.where(good, size + 1, size)
            lo, hi = np.where(good, a, lo), np.where(good, b, hi)
            out[at[good]] = size[good]
            bad = ~good
            at = at - (good | (bad & (size == 0)))
            shrink = np.flatnonzero(bad & (size > 0))
            if len(shrink):
                x, y = lo[shrink], hi[shrink]
                depth = np.maximum(self.lcp[x], self.lcp[y])
                size[shrink] = np.maximum(depth, 0)
                lo[shrink] = np.where(self.lcp[x] == depth, self.before[x], x)
                hi[shrink] = np.where(self.lcp[y] == depth, self.after[y], y)
                root = shrink[size[shrink] == 0]
                lo[root], hi[root] = 0, self.n
