"""Words and hashes of whole batches of texts as numpy arrays over their UTF-8 bytes.

Word separators of every operator here are ASCII, so that words can be cut byte by byte:
bytes of multi-byte characters are never separators.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Anything but space, tab, line feed, vertical tab, form feed, carriage return.
NON_SPACE = np.ones(256, dtype=bool)
NON_SPACE[[32, *range(9, 14)]] = False
#: ASCII letters and digits, and whatever is not ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[65:91] = ALNUM[97:123] = ALNUM[128:] = True

_seeded = np.random.Generator(np.random.PCG64(20240229))
_BYTE_CODES = _seeded.integers(1, 2**63, 256, dtype=np.uint64) | U(1)
_BASE, _WORD_BASE = U(0x9E3779B97F4A7C15), U(0xD6E8FEB86659FD93)
_SLICE = 1 << 19


def _inverse(x: np.uint64) -> np.uint64:
    return U(pow(int(x), -1, 1 << 64))


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n."""
    have = _powers.get(int(base))
    if have is None or len(have[0]) < n:
        size = max(n, _SLICE + 64)
        up, down = np.full(size, base, dtype=U), np.full(size, _inverse(base), dtype=U)
        up[0] = down[0] = U(1)
        have = _powers[int(base)] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return have[0][:n], have[1][:n]


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit over all."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


def texts_of(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts of a column, one after the other, and where each begins; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    held = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return held[at[0] : at[-1]] if len(at) else held, at - at[0]


def chunks(at: np.ndarray, most: int = 1 << 21) -> Iterator[tuple[int, int]]:
    """Ranges of texts of at most so many bytes together, or one text that is longer."""
    i, n = 0, len(at) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + most, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


class Words:
    """The words of some texts: byte ranges [start, end) and, for text i, words first[i]..first[i+1]."""

    def __init__(self, data: np.ndarray, at: np.ndarray, kind: np.ndarray, lower: bool = False):
        self.data = _LOWER[data] if lower else data
        inside = kind[data]
        n = len(data)
        if n:
            before, after = np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
            before[1:], after[:-1] = inside[:-1], inside[1:]
            filled = at[1:] > at[:-1]
            before[at[:-1][filled]] = False
            after[at[1:][filled] - 1] = False
            np.logical_not(before, out=before)
            np.logical_not(after, out=after)
            before &= inside
            after &= inside
            self.start, self.end = np.flatnonzero(before), np.flatnonzero(after) + 1
        else:
            self.start = self.end = np.zeros(0, dtype=np.int64)
        self.first = np.searchsorted(self.start, at)

    def __len__(self) -> int:
        return len(self.start)

    def hashes(self) -> np.ndarray:
        """64-bit hash of each word."""
        out = np.empty(len(self.start), dtype=U)
        i = 0
        while i < len(out):
            a = self.start[i]
            j = max(i + 1, int(np.searchsorted(self.end, a + _SLICE, side="right")))
            b = self.end[j - 1]
            up, down = powers(_BASE, b - a + 1)
            total = np.zeros(b - a + 1, dtype=U)
            np.cumsum(_BYTE_CODES[self.data[a:b]] * up[:-1], out=total[1:])
            s, e = self.start[i:j] - a, self.end[i:j] - a
            out[i:j] = (total[e] - total[s]) * down[s] + (e - s).astype(U)
            i = j
        return mixed(out)

    def owners(self) -> np.ndarray:
        """The text that each word is of."""
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))

    def word(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()

    def joined(self, i: int, j: int) -> bytes:
        """Words i..j with one blank between."""
        if j <= i:
            return b""
        held = self.data[self.start[i] : self.end[j - 1]].tobytes()
        gap = self.start[i + 1 : j] - self.end[i : j - 1]
        if (gap == 1).all():
            return held.translate(_TO_BLANK) if any(c in held for c in b"\t\n\v\f\r") else held
        base = self.start[i]
        return b" ".join(held[s - base : e - base] for s, e in zip(self.start[i:j].tolist(), self.end[i:j].tolist()))


_TO_BLANK = bytes.maketrans(b"\t\n\v\f\r", b"     ")


def window_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k words from each word on; windows may span texts, see ``whole``."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=U)
    if k <= 8:
        out = np.zeros(n, dtype=U)
        for i in range(k):
            out *= _WORD_BASE
            out += words[i : i + n]
        return mixed(out + U(k))
    up, down = powers(_WORD_BASE, len(words) + 1)
    total = np.zeros(len(words) + 1, dtype=U)
    np.cumsum(words * up[:-1], out=total[1:])
    return mixed((total[k:] - total[:-k]) * down[:n] + U(k))


def whole(first: np.ndarray, n_windows: int, k: int) -> np.ndarray:
    """Which of the windows of k words lie in one text; first: the first word of each text, and the number of words."""
    ok = np.zeros(n_windows + 1, dtype=np.int32)
    size = np.diff(first)
    has = size >= k
    np.add.at(ok, first[:-1][has], 1)
    np.add.at(ok, first[1:][has] - k + 1, -1)
    return np.cumsum(ok[:-1]) > 0
