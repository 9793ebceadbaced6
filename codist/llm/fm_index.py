"""Compressed FM-index over word codes: backward search on a wavelet matrix, many patterns at a time.

Suffixes are sorted by their first ``depth`` symbols only, by prefix doubling. Backward search
counts right for patterns up to that length, which is all that windows of fewer words need. What is kept
of the index are bit vectors with a rank directory of a quarter of their size, and where each run of rows
begins with the least mark in it. The suffix array is not kept, whole or sampled: what is asked of a run is
its least mark, and in an order of limited depth a walk from row to row would not reach the samples.
"""

from __future__ import annotations

import numpy as np

U = np.uint64


class Bits:
    """A bit vector with rank: words of 64 bits, the ones before each 1024th word and, from there, before each word."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        padded = np.zeros((n // 64 + 1) * 64, dtype=bool)
        padded[:n] = bits
        self.words = np.packbits(padded, bitorder="little").view(U)
        before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)[:-1]])
        self.far = before[::1024].copy()
        self.near = (before - np.repeat(self.far, 1024)[: len(before)]).astype(np.uint16)

    def rank(self, at: np.ndarray) -> np.ndarray:
        """Ones before each place."""
        w = at >> 6
        return self.far[w >> 10] + self.near[w] + np.bitwise_count(self.words[w] & ((U(1) << (at & 63).astype(U)) - U(1)))


class WaveletMatrix:
    """Ranks of any symbol in a sequence, one bit vector for each bit of the symbols."""

    def __init__(self, symbols: np.ndarray):
        self.bits = max(1, int(symbols.max(initial=0)).bit_length())
        self.levels, self.zeros = [], []
        for b in range(self.bits - 1, -1, -1):
            one = (symbols >> b) & 1 == 1
            self.levels.append(Bits(one))
            self.zeros.append(len(symbols) - int(one.sum()))
            symbols = np.concatenate([symbols[~one], symbols[one]])
        self.size = len(symbols)
        every = np.arange(int(symbols.max(initial=0)) + 1)
        self.base = self._down(every, np.zeros(len(every), dtype=np.int64)).astype(np.uint32 if len(symbols) < 1 << 32 else np.int64)

    def _down(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        for b, (level, zeros) in enumerate(zip(self.levels, self.zeros)):
            one = (symbol >> (self.bits - 1 - b)) & 1 == 1
            rank = level.rank(at)
            at = np.where(one, zeros + rank, at - rank)
        return at

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol occurs before each place."""
        return self._down(symbol, at) - self.base[symbol]


def _dense(x: np.ndarray) -> np.ndarray:
    return np.unique(x, return_inverse=True)[1].astype(np.int64)


class FMIndex:
    """Index of a text of symbols from 1 on, with 0 between its parts; windows of ``k`` symbols group its rows into runs.

    ``marks`` has a number for each symbol of the text; ``least`` is then the least number of each run.
    """

    def __init__(self, text: np.ndarray, k: int, marks: np.ndarray | None = None):
        text = np.append(text, 0).astype(np.int64)
        n = len(text)
        ranks, size = {1: text}, 1
        while size < k + 1:
            now = ranks[size]
            after = np.zeros(n, dtype=np.int64)
            after[: n - size] = now[size:] + 1 if n > size else 0
            ranks[2 * size] = _dense(now * (int(now.max()) + 3) + after)
            size *= 2
        self.k = k
        sa = np.argsort(ranks[size], kind="stable")
        bwt = text[sa - 1]
        self.count = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=int(text.max()) + 1))])
        self.wavelet = WaveletMatrix(bwt)
        new, at = np.zeros(n, dtype=bool), 0
        new[0] = True
        for b in sorted(ranks, reverse=True):
            if k - at >= b:
                place = np.minimum(sa + at, n - 1)
                held = ranks[b][place]
                new[1:] |= held[1:] != held[:-1]
                at += b
        self.n, begin = n, np.flatnonzero(new)
        if marks is not None:
            self.least = np.minimum.reduceat(np.append(marks, np.iinfo(marks.dtype).max)[sa], begin)
        self.runs = Bits(new)
        self.run_begin = np.append(begin, n).astype(np.uint32 if n < 1 << 32 else np.int64)

    def run(self, row: np.ndarray) -> np.ndarray:
        """The run of each row."""
        return self.runs.rank(row + 1) - 1

    def step(self, symbol: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows that begin with the symbol and then what the rows lo..hi begin with."""
        known = (symbol > 0) & (symbol < len(self.count) - 1)
        s = np.where(known, symbol, 0)
        both = self.wavelet.rank(np.concatenate([s, s]), np.concatenate([lo, hi]))
        begin = self.count[s]
        n = len(s)
        return np.where(known, begin + both[:n], 0), np.where(known, begin + both[n:], 0)

    def windows(self, queries: np.ndarray, first: np.ndarray) -> np.ndarray:
        """For each symbol of the queries the run of rows that begin with the window from it on, or -1.

        Query q is queries[first[q]:first[q+1]]. Each goes from its end to its beginning: a match grows
        to the left by backward search; at k symbols it is reported and cut on the right by taking all
        rows of its run; where it cannot grow it begins anew one symbol further left.
        """
        out = np.full(len(queries), -1, dtype=np.int64)
        q = np.flatnonzero(np.diff(first) >= self.k)
        begin, right = first[q].copy(), first[q + 1].copy()
        at, total = right.copy(), self.n
        lo, hi = np.zeros(len(q), dtype=np.int64), np.full(len(q), total, dtype=np.int64)
        while len(at):
            new_lo, new_hi = self.step(queries[at - 1], lo, hi)
            grown = new_hi > new_lo
            at = np.where(grown, at - 1, right - 1)
            right = np.where(grown, right, right - 1)
            lo, hi = np.where(grown, new_lo, 0), np.where(grown, new_hi, total)
            full = grown & (right - at >= self.k)
            if full.any():
                run = self.run(lo[full])
                out[at[full]] = run
                lo[full], hi[full] = self.run_begin[run], self.run_begin[run + 1]
                right[full] = at[full] + self.k
            go = (at > begin) & (right - begin >= self.k)
            if not go.all():
                begin, at, right, lo, hi = begin[go], at[go], right[go], lo[go], hi[go]
        return out

    def matches(self, query: np.ndarray) -> list[tuple[int, int]]:
        """Ranges of the query that are covered by windows of k symbols that the text holds."""
        found = np.flatnonzero(self.windows(query, np.array([0, len(query)])) >= 0)
        out: list[tuple[int, int]] = []
        for i in found.tolist():
            if out and i <= out[-1][1]:
                out[-1] = out[-1][0], i + self.k
            else:
                out.append((i, i + self.k))
        return out
