"""A compressed full-text index over integer sequences: Burrows-Wheeler transform, wavelet matrix, backward search."""

from __future__ import annotations

import numpy as np

#: Suffixes are sorted by so many symbols at least; patterns of up to this length are found exactly.
DEPTH = 64


class BitRank:
    """Packed bits with a count per 64-bit word: ones before a position."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        packed = np.packbits(bits, bitorder="little")
        self.words = np.frombuffer(packed.tobytes() + bytes(8 * (n // 64 + 1) - len(packed)), "<u8")
        self.before = np.concatenate(([0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64))).astype(np.int32)

    def ones(self, at: np.ndarray) -> np.ndarray:
        word, low = at >> 6, (at & 63).astype(np.uint64)
        return self.before[word] + np.bitwise_count(self.words[word] & ((np.uint64(1) << low) - np.uint64(1)))


class Wavelet:
    """A wavelet matrix: occurrences of a symbol before a position, in one step per bit of the alphabet."""

    def __init__(self, symbols: np.ndarray, bits: int):
        self.levels: list[tuple[int, BitRank, int]] = []
        rest = symbols
        for shift in range(bits - 1, -1, -1):
            one = (rest >> shift) & 1 == 1
            zeros = int(len(rest) - one.sum())
            self.levels.append((shift, BitRank(one), zeros))
            rest = np.concatenate((rest[~one], rest[one]))
        starts = np.flatnonzero(np.concatenate(([True], rest[1:] != rest[:-1]))) if len(rest) else np.zeros(0, np.int64)
        self.begin = np.zeros(1 << bits, np.int64)
        self.begin[rest[starts]] = starts

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        for shift, ones, zeros in self.levels:
            up = ones.ones(at)
            at = np.where((symbol >> shift) & 1 == 1, zeros + up, at - up)
        return at - self.begin[symbol]


class Index:
    """The index of ``text`` (symbols from 1 on; 0 ends it), for patterns of up to ``depth`` symbols."""

    def __init__(self, text: np.ndarray, depth: int = DEPTH):
        self.depth = 1 << max(0, depth - 1).bit_length()
        text = np.concatenate((np.asarray(text, np.int64), [0]))
        n = len(text)
        _, first = np.unique(text, return_inverse=True)
        ranks, width = {1: first.astype(np.int64)}, 1
        while width < self.depth:
            r = ranks[width]
            later = np.zeros(n, np.int64)
            later[: max(0, n - width)] = r[width:] + 1
            key = r * (n + 1) + later
            order = np.argsort(key, kind="stable")
            step = np.concatenate(([0], np.cumsum(key[order][1:] != key[order][:-1])))
            ranks[2 * width] = np.empty(n, np.int64)
            ranks[2 * width][order] = step
            width *= 2
        self.suffixes = np.argsort(ranks[self.depth], kind="stable")
        self.n, self.ranks = n, ranks
        bits = max(1, int(text.max()).bit_length())
        self.counts = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=1 << bits))))
        self.wavelet = Wavelet(text[self.suffixes - 1], bits)
        self._table: list[np.ndarray] | None = None

    def common(self) -> np.ndarray:
        """Symbols that each row shares with the row before, up to ``depth`` (row 0: none)."""
        a, b = self.suffixes[1:].copy(), self.suffixes[:-1].copy()
        found = np.zeros(len(a), np.int64)
        width = self.depth
        while width:
            inside = (a + found < self.n) & (b + found < self.n)
            x, y = np.minimum(a + found, self.n - 1), np.minimum(b + found, self.n - 1)
            found += width * (inside & (found + width <= self.depth) & (self.ranks[width][x] == self.ranks[width][y]))
            width //= 2
        return np.concatenate(([0], found))

    def extend(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows that start with ``symbol`` and go on as the rows ``low`` to ``high`` do."""
        base = self.counts[symbol]
        return base + self.wavelet.rank(symbol, low), base + self.wavelet.rank(symbol, high)

    def shorten(self, row: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All rows that share the first ``length`` symbols with ``row``: nearest lesser common lengths, by doubling."""
        if self._table is None:
            level, self._table = self.common().astype(np.int8 if self.depth < 128 else np.int32), []
            while True:
                self._table.append(level)
                reach = 1 << (len(self._table) - 1)
                if 2 * reach > self.n:
                    break
                level = np.minimum(level[: self.n - 2 * reach + 1], level[reach : self.n - reach + 1])
        low, high = row.copy(), row + 1
        for k in range(len(self._table) - 1, -1, -1):
            reach, level = 1 << k, self._table[k]
            fits = low >= reach
            down = fits & (level[np.where(fits, low - reach + 1, 0)] >= length)
            low = np.where(down, low - reach, low)
            fits = high + reach <= self.n
            up = fits & (level[np.where(fits, high, 0)] >= length)
            high = np.where(up, high + reach, high)
        return low, high

    def step(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray, length: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """One symbol to the left for many patterns at once: the longest prefix of symbol + pattern that occurs, of ``most`` symbols at most."""
        known = symbol > 0
        safe = np.where(known, symbol, 1)
        a, b = self.extend(safe, low, high)
        length = length + 1
        lost = np.flatnonzero(~known | (a >= b))
        if len(lost):
            # the longest shortened pattern that the symbol precedes somewhere: bisect its length
            good, bad = np.zeros(len(lost), np.int64), length[lost] - 1
            while (bad - good > 1).any():
                mid = (good + bad + 1) // 2
                mid = np.where(bad - good > 1, mid, good)
                x, y = self.extend(safe[lost], *self.shorten(low[lost], mid))
                found = x < y
                good, bad = np.where(found, mid, good), np.where(found | (bad - good <= 1), bad, mid)
            x, y = self.extend(safe[lost], *self.shorten(low[lost], good))
            none = ~known[lost] | (x >= y)
            a[lost], b[lost] = np.where(none, 0, x), np.where(none, self.n, y)
            length[lost] = np.where(none, 0, good + 1)
        over = np.flatnonzero(length > most)
        if len(over):
            a[over], b[over] = self.shorten(a[over], np.full(len(over), most))
            length[over] = most
        return a, b, length


def matching_statistics(index: Index, patterns: list[np.ndarray], most: int):
    """Yield ``(which, start, low, high, length)`` from right to left: at each start the longest prefix of the rest, up to ``most``, that the index holds.

    ``which`` are the patterns that reach the position; a symbol of 0 is one the index doesn't know.
    """
    if not patterns:
        return
    sizes = np.array([len(p) for p in patterns])
    flat, begin = np.concatenate(patterns), np.cumsum(sizes) - sizes
    low, high = np.zeros(len(sizes), np.int64), np.full(len(sizes), index.n, np.int64)
    length = np.zeros(len(sizes), np.int64)
    for back in range(1, int(sizes.max()) + 1):
        which = np.flatnonzero(sizes >= back)
        start = sizes[which] - back
        low[which], high[which], length[which] = index.step(flat[begin[which] + start], low[which], high[which], length[which], most)
        yield which, start, low[which], high[which], length[which]
