"""A compressed full-text index over words: Burrows-Wheeler transform in a wavelet matrix.

Suffixes are ordered by their first ``depth`` words only, which is all that patterns up to that
length need.  Rank is answered from packed bits with one count per 64 bits.  Many streamed texts are
searched backwards in step, one numpy operation for all of them.
"""
from __future__ import annotations

import numpy as np

I64 = np.int64


class BitVector:
    def __init__(self, bits: np.ndarray):
        self.n = len(bits)
        packed = np.packbits(bits, bitorder="little")
        self.words = np.zeros(self.n // 64 + 1, np.uint64)
        self.words.view(np.uint8)[: len(packed)] = packed
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words))]).astype(np.int32)

    def rank1(self, i: np.ndarray) -> np.ndarray:
        """Ones in bits[:i]."""
        w = i >> 6
        return self.before[w] + np.bitwise_count(self.words[w] & ((np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)))


class WaveletMatrix:
    def __init__(self, values: np.ndarray, size: int):
        self.levels, self.zeros = [], []
        for bit in reversed(range(max(1, int(size - 1).bit_length()))):
            b = (values >> bit) & 1
            self.levels.append((bit, BitVector(b.astype(np.uint8))))
            self.zeros.append(int(len(b) - b.sum()))
            values = np.concatenate([values[b == 0], values[b == 1]])

    def rank(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How often c is in values[:i], plus the start of c's run in the last level."""
        for (bit, v), z in zip(self.levels, self.zeros):
            one = v.rank1(i)
            i = np.where((c >> bit) & 1, z + one, i - one)
        return i


class FMIndex:
    """Index over texts of word numbers >= 1.  ``owner``: a number per text."""

    def __init__(self, texts: list[np.ndarray], owner: np.ndarray, depth: int):
        self.depth = depth
        sizes = np.array([len(t) + 1 for t in texts], I64)
        text = np.zeros(int(sizes.sum()), I64)
        stop = np.cumsum(sizes) - 1
        for t, e in zip(texts, stop):
            text[e - len(t) : e] = t
        self.size = int(text.max(initial=0)) + 1
        # Each text's end is a symbol of its own, so that no match runs into the next text.
        rank = text + len(texts)
        rank[stop] = np.arange(len(texts))
        n, step, kept = len(text), 1, []
        _, rank = np.unique(rank, return_inverse=True)
        kept.append(rank)
        while step < depth and len(text):
            ahead = np.zeros(n, I64)
            ahead[: n - step] = rank[step:] + 1
            _, rank = np.unique(rank * I64(n + 1) + ahead, return_inverse=True)
            kept.append(rank)
            step *= 2
        self.sa = np.argsort(rank, kind="stable")
        before = text[self.sa - 1]
        self.matrix = WaveletMatrix(before, self.size)
        count = np.bincount(text, minlength=self.size)
        self.start = np.concatenate([[0], np.cumsum(count)])[: self.size]
        self.base = self.matrix.rank(np.arange(self.size), np.zeros(self.size, I64))
        self.lcp = self._lcp(kept, n)
        del kept, rank
        # Owners as ranks and common lengths as bytes keep the tables small.
        self.owners, place = np.unique(owner, return_inverse=True)
        self.least_owner = self._table(np.repeat(place, sizes)[self.sa].astype(np.int32), np.minimum)
        self.least_lcp = self._table(self.lcp.astype(np.int8 if 2 * depth < 127 else np.int32), np.minimum)

    def _lcp(self, kept: list[np.ndarray], n: int) -> np.ndarray:
        """lcp[i]: common words of rows i - 1 and i, up to the sorted depth; the ends are -1."""
        a, b, out = self.sa[:-1].copy(), self.sa[1:].copy(), np.zeros(max(0, n - 1), I64)
        for k in reversed(range(len(kept))):
            inside = (a < n) & (b < n)
            same = np.zeros(len(out), bool)
            same[inside] = kept[k][a[inside]] == kept[k][b[inside]]
            for x in (a, b, out):
                x[same] += 1 << k
        return np.concatenate([[-1], out, [-1]])

    @staticmethod
    def _table(values: np.ndarray, least) -> list[np.ndarray]:
        rows, k = [values], 1
        while 2 * k <= len(values):
            rows.append(least(rows[-1][:-k], rows[-1][k:]))
            k *= 2
        return rows

    def widen(self, lo: np.ndarray, hi: np.ndarray, depth: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows that share their first ``depth`` words with rows lo:hi."""
        lo, hi = lo.copy(), hi.copy()
        for k in reversed(range(len(self.least_lcp))):
            row = self.least_lcp[k]
            at = lo - (1 << k) + 1
            ok = at >= 0
            ok[ok] = row[at[ok]] >= depth[ok]
            lo[ok] -= 1 << k
            ok = hi + (1 << k) <= len(self.lcp)
            ok[ok] = row[hi[ok]] >= depth[ok]
            hi[ok] += 1 << k
        return lo, hi

    def extend(self, lo: np.ndarray, hi: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One step of backward search; a word the index lacks (0 or beyond) gives an empty range."""
        known = (c > 0) & (c < self.size)
        c = np.where(known, c, 0)
        off = self.start[c] - self.base[c]
        a, b = self.matrix.rank(c, lo) + off, self.matrix.rank(c, hi) + off
        return np.where(known, a, 0), np.where(known, b, 0)

    def owner_of(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """The least owner in non-empty rows lo:hi."""
        k = np.log2(hi - lo).astype(I64)
        out = np.empty(len(lo), self.least_owner[0].dtype)
        for x in np.unique(k):
            m = k == x
            out[m] = np.minimum(self.least_owner[x][lo[m]], self.least_owner[x][hi[m] - (1 << int(x))])
        return self.owners[out]

    def matching_statistics(self, texts: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Per streamed text and start: the longest match's length, up to ``depth``, and the least owner of such a match (-1: no match)."""
        order = sorted(range(len(texts)), key=lambda i: -len(texts[i]))
        size = np.array([len(texts[i]) for i in order], I64)
        width, n = int(size.max(initial=0)), len(self.sa)
        grid = np.zeros((width, len(order)), I64)
        for j, i in enumerate(order):
            grid[: size[j], j] = texts[i][::-1]
        length, owner = np.zeros((width, len(order)), I64), np.full((width, len(order)), -1, I64)
        lo, hi, deep = np.zeros(len(order), I64), np.full(len(order), n, I64), np.zeros(len(order), I64)
        for t in range(width):
            live = int(np.searchsorted(-size, -t, "left"))
            lo, hi, deep = lo[:live], hi[:live], deep[:live]
            c = grid[t, :live]
            a, b = self.extend(lo, hi, c)
            stuck = np.flatnonzero((a >= b) & (deep > 0))
            while len(stuck):  # shorten at the far end until the word fits
                up = np.maximum(self.lcp[lo[stuck]], self.lcp[hi[stuck]])
                up = np.minimum(np.maximum(up, 0), deep[stuck] - 1)
                lo[stuck], hi[stuck] = self.widen(lo[stuck], hi[stuck], up)
                lo[stuck[up == 0]], hi[stuck[up == 0]] = 0, n
                deep[stuck] = up
                a[stuck], b[stuck] = self.extend(lo[stuck], hi[stuck], c[stuck])
                stuck = stuck[(a[stuck] >= b[stuck]) & (deep[stuck] > 0)]
            fits = a < b
            lo, hi, deep = np.where(fits, a, 0), np.where(fits, b, n), np.where(fits, deep + 1, 0)
            over = np.flatnonzero(deep > self.depth)
            if len(over):
                lo[over], hi[over] = self.widen(lo[over], hi[over], np.full(len(over), self.depth))
                deep[over] = self.depth
            length[t, :live] = deep
            if fits.any():
                owner[t, :live][fits] = self.owner_of(lo[fits], hi[fits])
        out: list = [None] * len(texts)
        for j, i in enumerate(order):
            out[i] = length[: size[j], j][::-1], owner[: size[j], j][::-1]
        return out
