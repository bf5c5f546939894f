"""A compressed FM-index over integer symbols, in NumPy, for patterns of bounded length.

The text is sorted by its first ``depth`` symbols only, which is all that patterns of up to
``depth`` symbols need. The Burrows-Wheeler transform is held in a wavelet matrix of packed
bits with block counts, and the intervals of shorter patterns as one bit a row and length
with a directory of filled words: about log2(symbols) + 2 * depth bits a symbol in all, and
neither the text nor a suffix array is kept. Backward search runs for many patterns at once.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64


class Bits:
    """Packed bits with rank."""

    def __init__(self, bits: np.ndarray) -> None:
        words = np.zeros(len(bits) // 64 + 1, np.uint64)
        packed = np.packbits(bits, bitorder="little")
        words.view(np.uint8)[: len(packed)] = packed
        self.words = words
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(words))]).astype(np.int32)
        self.zeros = len(bits) - int(self.before[-1])

    def ones_before(self, i: np.ndarray) -> np.ndarray:
        w = i >> 6
        mask = (_U(1) << (i & 63).astype(np.uint64)) - _U(1)
        return self.before[w] + np.bitwise_count(self.words[w] & mask)


class Runs:
    """Rows in runs, for each of several lengths: where the run of a row begins and ends.

    ``new[d]`` marks rows that begin a run of length d; row 0 begins one of every length."""

    def __init__(self, new: np.ndarray) -> None:
        self.n = new.shape[1]
        size = self.n // 64 + 1
        packed = np.packbits(new, axis=1, bitorder="little")
        raw = np.zeros((len(new), size * 8), np.uint8)
        raw[:, : packed.shape[1]] = packed
        self.words = raw.view(np.uint64)
        some, at = self.words != 0, np.arange(size, dtype=np.int32)
        #: nearest word with a mark, at or before and at or after each word
        self.back = np.maximum.accumulate(np.where(some, at, 0), 1)
        self.ahead = np.minimum.accumulate(np.where(some, at, size)[:, ::-1], 1)[:, ::-1]

    def begin(self, d: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Last mark of length d at or before the row."""
        w = row >> 6
        here = self.words[d, w] & (~_U(0) >> (63 - (row & 63)).astype(np.uint64))
        w = np.where(here != 0, w, self.back[d, np.maximum(w - 1, 0)])
        here = np.where(here != 0, here, self.words[d, w])
        for shift in (1, 2, 4, 8, 16, 32):
            here = here | (here >> _U(shift))
        return (w << 6) + np.bitwise_count(here).astype(np.int64) - 1

    def end(self, d: np.ndarray, row: np.ndarray) -> np.ndarray:
        """First mark of length d after the row, or the number of rows."""
        w, last = row >> 6, self.words.shape[1]
        here = self.words[d, w] & ~(~_U(0) >> (63 - (row & 63)).astype(np.uint64))
        after = np.where(w + 1 < last, self.ahead[d, np.minimum(w + 1, last - 1)], last)
        w = np.where(here != 0, w, after)
        here = np.where(here != 0, here, self.words[d, np.minimum(w, last - 1)])
        low = np.bitwise_count((here & (~here + _U(1))) - _U(1)).astype(np.int64)
        return np.where(w >= last, self.n, (w << 6) + low)


class WaveletMatrix:
    def __init__(self, x: np.ndarray, n_symbols: int) -> None:
        self.levels = []
        for level in range(max(1, (n_symbols - 1).bit_length()) - 1, -1, -1):
            bit = (x >> level) & 1
            self.levels.append((level, Bits(bit.astype(np.uint8))))
            x = np.concatenate([x[bit == 0], x[bit == 1]])
        self.base = np.zeros(n_symbols, np.int64)
        self.base = self._down(np.arange(n_symbols), np.zeros(n_symbols, np.int64))

    def _down(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        for level, bits in self.levels:
            ones = bits.ones_before(i)
            i = np.where((symbol >> level) & 1 == 1, bits.zeros + ones, i - ones)
        return i

    def rank(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How often the symbol stands before place i."""
        return self._down(symbol, i) - self.base[symbol]


class FMIndex:
    """Index of ``text`` (integers from 0; 0 separates) for patterns up to ``depth``."""

    def __init__(self, text: np.ndarray, n_symbols: int, depth: int) -> None:
        n = len(text)
        self.n, self.depth = n, depth
        order = self._sort(text, depth)
        self.wavelet = WaveletMatrix(text[order - 1], n_symbols)
        self.first = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=n_symbols))])
        padded = np.concatenate([text, np.zeros(depth, text.dtype)])
        self.lcp = np.zeros(n + 1, np.int8)
        alive = np.ones(max(n - 1, 0), bool)
        new = np.zeros((depth + 1, n), bool)
        new[:, :1] = True
        for k in range(depth):
            x = padded[order + k]
            alive &= x[1:] == x[:-1]
            self.lcp[1:n] += alive
            new[k + 1, 1:] = ~alive
        self.runs = Runs(new)
        #: by row, once: where in the text it starts; callers take what they need and drop it
        self.order = order.astype(np.int32 if n < 2**31 else np.int64)

    @staticmethod
    def _sort(text: np.ndarray, depth: int) -> np.ndarray:
        """Rows by their first ``depth`` symbols: ranks of twice the length each round."""
        n = len(text)
        rank, have = text.astype(np.int64), 1
        while have < depth:
            step = min(have, depth - have)
            ahead = np.zeros(n, np.int64)
            ahead[: n - step] = rank[step:] + 1
            _, rank = np.unique((rank << 32) | ahead, return_inverse=True)
            have += step
        return np.argsort(rank, kind="stable")

    def extend(self, symbol: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows of the patterns with one more symbol in front."""
        both = self.wavelet.rank(np.concatenate([symbol, symbol]), np.concatenate([lo, hi]))
        return self.first[symbol] + both[: len(lo)], self.first[symbol] + both[len(lo) :]

    def matching(self, queries: np.ndarray, least_rows: int):
        """Backward matching statistics of queries (rows of symbols, 0: none), from the last
        column to the first: yields (column, length, lo, hi), the longest pattern of at most
        ``depth`` symbols that starts at the column and has ``least_rows`` rows."""
        m = len(queries)
        lo, hi, size = np.zeros(m, np.int64), np.full(m, self.n, np.int64), np.zeros(m, np.int64)

        def shorten(which: np.ndarray, to: np.ndarray) -> None:
            row = lo[which]
            lo[which], hi[which], size[which] = self.runs.begin(to, row), self.runs.end(to, row), to

        for c in range(queries.shape[1] - 1, -1, -1):
            symbol = queries[:, c]
            none = np.flatnonzero(symbol == 0)
            lo[none], hi[none], size[none] = 0, self.n, 0
            full = np.flatnonzero(size == self.depth)
            shorten(full, np.full(len(full), self.depth - 1))
            todo = np.flatnonzero(symbol > 0)
            while len(todo):
                a, b = self.extend(symbol[todo], lo[todo], hi[todo])
                good = b - a >= least_rows
                ok = todo[good]
                lo[ok], hi[ok] = a[good], b[good]
                size[ok] += 1
                todo = todo[~good]
                done = todo[size[todo] == 0]
                lo[done], hi[done] = 0, self.n
                todo = todo[size[todo] > 0]
                # the longest shorter pattern with more rows
                to = np.maximum(self.lcp[lo[todo]], self.lcp[hi[todo]]).astype(np.int64)
                shorten(todo, np.minimum(to, size[todo] - 1))
            yield c, size, lo, hi
