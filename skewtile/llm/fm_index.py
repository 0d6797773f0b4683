"""A compressed FM-index over integer text: wavelet matrix of the Burrows-Wheeler transform, sampled suffix array, batched backward search.

What is kept is packed bits: one bit a symbol and level, with 16-bit counts a word and one wide count in 65,536 bits; two marks a
row for the intervals that agree in the pattern's length and in one symbol less; and a place for each sampled suffix. The text
and the whole suffix array go when the index is built. All methods take arrays and answer for all entries at once.
"""

from __future__ import annotations

import numpy as np

SAMPLE = 32
"""Places of the text whose suffixes are sampled, besides the first after every stop symbol (0)."""


class Bits:
    """A bit vector with rank and select."""

    def __init__(self, bit: np.ndarray):
        self.words = np.packbits(np.append(bit, np.zeros(-len(bit) % 64 + 64, bool)), bitorder="little").view(np.uint64)
        before = np.append(0, np.cumsum(np.bitwise_count(self.words), dtype=np.int64))[:-1]
        self.wide = before[::1024].copy()
        self.near = (before - np.repeat(self.wide, 1024)[: len(before)]).astype(np.uint16)
        self.n_ones = int(bit.sum())

    def rank(self, at: np.ndarray) -> np.ndarray:
        """Ones before each place."""
        word = at >> 6
        below = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.wide[word >> 10] + self.near[word] + np.bitwise_count(self.words[word] & below)

    def get(self, at: np.ndarray) -> np.ndarray:
        return (self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1

    def select(self, k: np.ndarray, end: int) -> np.ndarray:
        """The place of one number k, from 0; `end` for those past the last."""
        known = k < self.n_ones
        k = np.where(known, k, 0)
        block = np.searchsorted(self.wide, k, "right") - 1
        low, high = block << 10, np.minimum((block + 1) << 10, len(self.near))
        left = k - self.wide[block]
        while (open_ := high - low > 1).any():  # ten halvings within a block
            middle = (low + high) >> 1
            up = open_ & (self.near[np.minimum(middle, len(self.near) - 1)] <= left)
            low, high = np.where(up, middle, low), np.where(open_ & ~up, middle, high)
        bits = np.unpackbits(self.words[low].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        inside = (np.cumsum(bits, axis=1, dtype=np.uint8) > (left - self.near[low])[:, None]).argmax(1)
        return np.where(known, (low << 6) + inside, end)

    def n_bytes(self) -> int:
        return self.words.nbytes + self.wide.nbytes + self.near.nbytes


class WaveletMatrix:
    """Rank over symbols below 2 ** levels in packed bits."""

    def __init__(self, symbols: np.ndarray, levels: int):
        self.n, self.levels, self.bits, self.zeros = len(symbols), levels, [], []
        cur = symbols
        for level in reversed(range(levels)):
            bit = ((cur >> level) & 1).astype(bool)
            self.bits.append(Bits(bit))
            self.zeros.append(int(len(bit) - bit.sum()))
            cur = np.concatenate([cur[~bit], cur[bit]])

    def rank(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How often each symbol stands before low, and before high."""
        base = np.zeros(len(symbol), np.int64)
        for k in range(self.levels):
            one = ((symbol >> (self.levels - 1 - k)) & 1).astype(bool)
            b, lo, hi = np.split(self.bits[k].rank(np.concatenate([base, low, high])), 3)
            z = self.zeros[k]
            base, low, high = np.where(one, z + b, base - b), np.where(one, z + lo, low - lo), np.where(one, z + hi, high - hi)
        return low - base, high - base

    def read(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each place, and how often it stands before it."""
        symbol, base = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        for k in range(self.levels):
            one = self.bits[k].get(at)
            b, r = np.split(self.bits[k].rank(np.concatenate([base, at])), 2)
            symbol = symbol * 2 + one
            base, at = np.where(one, self.zeros[k] + b, base - b), np.where(one, self.zeros[k] + r, at - r)
        return symbol, at - base


def suffix_order(text: np.ndarray, lengths: tuple[int, ...]) -> tuple[np.ndarray, list[np.ndarray]]:
    """The suffix array, past the end being below every symbol, and for each of the lengths, which rows differ in so many first symbols from
    the row before. By doubling: ranks by the first 1, 2, 4, ... symbols until no two are equal."""
    n = len(text)
    ranks = {1: np.unique(text, return_inverse=True)[1].astype(np.int64)}
    d = 1
    while ranks[d].max() + 1 < n:
        nxt = np.zeros(n, np.int64)
        nxt[: max(0, n - d)] = ranks[d][d:] + 1
        ranks[2 * d] = np.unique(ranks[d] * (n + 1) + nxt, return_inverse=True)[1]
        if d > max(lengths):
            del ranks[d]
        d *= 2
    rows = np.argsort(ranks[d], kind="stable")
    starts = []
    for length in lengths:
        same, at = np.ones(max(0, n - 1), bool), 0
        for step in sorted((k for k in ranks if k <= length), reverse=True):
            if at + step <= length:
                r = np.append(ranks[step][at:], np.full(min(at, n), -1))[rows]
                same &= r[1:] == r[:-1]
                at += step
        starts.append(np.append(True, ~same))
    return rows, starts


class FMIndex:
    def __init__(self, text: np.ndarray, pattern: int, label: np.ndarray | None = None):
        """text: symbols from 0, the stop symbol 0 at its end. pattern: the length that match() reports intervals of. label: a number for each
        place of the text, of which each interval of that length knows the least."""
        self.pattern, self.n = pattern, len(text)
        rows, (shorter, whole) = suffix_order(text, (pattern - 1, pattern))
        self.count = np.append(0, np.cumsum(np.bincount(text)))
        self.wavelet = WaveletMatrix(text[rows - 1], max(1, int(len(self.count) - 2).bit_length()))
        self.shorter, self.whole = Bits(shorter), Bits(whole)
        self.least = None if label is None else np.minimum.reduceat(label[rows], np.flatnonzero(whole))
        sampled = (rows % SAMPLE == 0) | (text[rows - 1] == 0)
        self.sampled, self.places = Bits(sampled), rows[sampled].astype(np.int32 if len(text) < 2**31 else np.int64)

    def _interval(self, marks: Bits, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows that agree with each row, as the marks have it."""
        k = marks.rank(row + 1) - 1
        low, high = np.split(marks.select(np.concatenate([k, k + 1]), self.n), 2)
        return low, high

    def least_label(self, low: np.ndarray) -> np.ndarray:
        """The least label of the intervals that match() reported, told by their first rows."""
        return self.least[self.whole.rank(low + 1) - 1]

    def locate(self, row: np.ndarray) -> np.ndarray:
        """Places in the text of the suffixes in these rows, by steps to the left until one is sampled."""
        out, steps = np.empty(len(row), np.int64), np.zeros(len(row), np.int64)
        todo = np.arange(len(row))
        row = row.copy()
        while len(todo):
            known = self.sampled.get(row[todo])
            at = todo[known]
            out[at] = self.places[self.sampled.rank(row[at])] + steps[at]
            todo = todo[~known]
            symbol, before = self.wavelet.read(row[todo])
            row[todo] = self.count[symbol] + before
            steps[todo] += 1
        return out

    def extend(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Backward search: the intervals of symbol + pattern from those of the patterns; empty for symbols that the text lacks."""
        known = symbol < len(self.count) - 1
        symbol = np.where(known, symbol, 0)
        a, b = self.wavelet.rank(symbol, low, high)
        return np.where(known, self.count[symbol] + a, 0), np.where(known, self.count[symbol] + b, 0)

    def match(self, stream: np.ndarray, starts: np.ndarray, lengths: np.ndarray, lane: int = 128) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Streams pieces of `stream` right to left, all at once. Returns the start of every window of `pattern` symbols inside a piece and the
        interval of its occurrences. Matching statistics are held at `pattern`: after each window its interval is widened to the
        first pattern - 1 symbols and extended by the symbol on the left. Pieces are cut into lanes of so many windows."""
        windows = np.maximum(0, lengths - self.pattern + 1)
        cuts = -(-windows // lane)
        piece = np.repeat(np.arange(len(starts)), cuts)
        turn = np.arange(len(piece)) - np.repeat(np.cumsum(cuts) - cuts, cuts)
        first = starts[piece] + turn * lane
        left = np.minimum(lane, windows[piece] - turn * lane)
        at = first + left - 1

        def anew(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            low, high = np.zeros(len(at), np.int64), np.full(len(at), self.n, np.int64)
            for k in reversed(range(self.pattern)):
                low, high = self.extend(stream[at + k], low, high)
            return low, high

        low, high = anew(at)
        out = [(at.copy(), low, high)]
        while True:
            go = at > first
            if not go.any():
                break
            at, first, low, high = at[go] - 1, first[go], low[go], high[go]
            found = high > low
            a, b = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
            wide = self._interval(self.shorter, low[found])
            a[found], b[found] = self.extend(stream[at[found]], *wide)
            if not found.all():  # search anew where the window before does not occur
                a[~found], b[~found] = anew(at[~found])
            low, high = a, b
            out.append((at.copy(), low, high))
        return tuple(np.concatenate(x) for x in zip(*out))

    def n_bytes(self) -> int:
        """All that the index keeps, but for labels."""
        return sum(b.n_bytes() for b in (*self.wavelet.bits, self.shorter, self.whole, self.sampled)) + self.places.nbytes + self.count.nbytes
