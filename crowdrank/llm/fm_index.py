"""A compressed FM-index over integer symbols, searched for many patterns at once.

The Burrows-Wheeler transform is kept as a wavelet matrix: one bit vector a level, packed into
64-bit words with one running count a word. Symbol 0 separates texts. Suffixes are ordered by their
first ``depth`` symbols or more, which is all that patterns of that length need.
"""

from __future__ import annotations

import numpy as np

_ONE, _SIX, _LOW = np.uint64(1), np.int64(6), np.int64(63)


class BitVector:
    """Packed bits with O(1) rank, vectorised."""

    def __init__(self, bits: np.ndarray) -> None:
        n = len(bits)
        padded = np.zeros((n // 64 + 1) * 64, np.uint8)
        padded[:n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        counts = np.bitwise_count(self.words).astype(np.int32)
        self.before = np.concatenate(([0], np.cumsum(counts)[:-1])).astype(np.int32)

    def rank1(self, i: np.ndarray) -> np.ndarray:
        w = i >> _SIX
        low = (_ONE << (i & _LOW).astype(np.uint64)) - _ONE
        return self.before[w] + np.bitwise_count(self.words[w] & low)


class WaveletMatrix:
    def __init__(self, symbols: np.ndarray, sigma: int) -> None:
        self.levels = max(1, int(sigma - 1).bit_length())
        self.bits, self.zeros = [], []
        now = symbols
        for level in range(self.levels - 1, -1, -1):
            b = (now >> level) & 1
            self.bits.append(BitVector(b.astype(np.uint8)))
            self.zeros.append(int(len(b) - b.sum()))
            now = np.concatenate((now[b == 0], now[b == 1]))
        self.start = self.descend(np.zeros(sigma, np.int64), np.arange(sigma))

    def descend(self, i: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        for depth, (bits, zeros) in enumerate(zip(self.bits, self.zeros, strict=True)):
            one = ((symbol >> (self.levels - 1 - depth)) & 1).astype(bool)
            r = bits.rank1(i).astype(np.int64)
            i = np.where(one, zeros + r, i - r)
        return i

    def rank(self, i: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """How often ``symbol`` stands before place ``i``."""
        return self.descend(i, symbol) - self.start[symbol]


def _pairs(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return np.unique(first * np.int64(len(first) + 1) + second, return_inverse=True)[1].astype(np.int64)


def _behind(rank: np.ndarray, by: int) -> np.ndarray:
    out = np.zeros(len(rank), np.int64)
    out[: len(rank) - by] = rank[by:] + 1
    return out


class FMIndex:
    """``texts``: arrays of 64-bit symbols; ``weights``: how many copies each text stands for."""

    def __init__(self, texts: list[np.ndarray], weights: np.ndarray, depth: int) -> None:
        self.depth = depth
        sizes = np.array([len(t) for t in texts])
        flat = np.concatenate(texts)
        self.alphabet, ids = np.unique(flat, return_inverse=True)
        ends = np.cumsum(sizes + 1)
        text = np.zeros(int(ends[-1]), np.int64)
        inside = np.ones(len(text), bool)
        inside[ends - 1] = False
        text[inside] = ids + 1
        self.text, self.starts = text, ends - sizes - 1
        powers, span = {1: text}, 1
        while span < depth + 1:
            powers[2 * span] = _pairs(powers[span], _behind(powers[span], span)) if span < len(text) else powers[span]
            span *= 2
        order = np.argsort(powers[span], kind="stable")
        shallow, done = None, 0  # classes of equal first depth - 1 symbols
        for p in sorted(powers, reverse=True):
            if (depth - 1) & p:
                shallow = powers[p] if shallow is None else _pairs(shallow, _behind(powers[p], done) if done < len(text) else powers[p] * 0)
                done += p
        sigma = len(self.alphabet) + 1
        self.wavelet = WaveletMatrix(text[order - 1], sigma)
        self.counts = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=sigma))))
        self.weight_before = np.concatenate(([0], np.cumsum(np.repeat(weights, sizes + 1)[order])))
        classes = shallow[order] if shallow is not None else np.zeros(len(text), np.int64)
        cuts = np.flatnonzero(np.concatenate(([True], classes[1:] != classes[:-1])))
        of = np.cumsum(np.concatenate(([True], classes[1:] != classes[:-1]))) - 1
        self.class_lo, self.class_hi = cuts[of], np.append(cuts[1:], len(text))[of]

    def encode(self, symbols: np.ndarray) -> np.ndarray:
        """Ids of symbols; those that no text holds get -1."""
        at = np.searchsorted(self.alphabet, symbols)
        at[at == len(self.alphabet)] = 0
        return np.where(self.alphabet[at] == symbols, at + 1, -1) if len(self.alphabet) else np.full(len(symbols), -1)

    def step(self, lo: np.ndarray, hi: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Put ``symbol`` before the pattern of each interval."""
        known = symbol > 0
        c = np.where(known, symbol, 0)
        a, b = self.counts[c] + self.wavelet.rank(lo, c), self.counts[c] + self.wavelet.rank(hi, c)
        return np.where(known, a, 0), np.where(known, b, 0)

    def occurrences(self, pattern: np.ndarray) -> int:
        """Weighted occurrences of one pattern of at most ``depth`` symbols."""
        lo, hi = np.zeros(1, np.int64), np.full(1, len(self.text))
        for c in self.encode(pattern)[::-1]:
            lo, hi = self.step(lo, hi, np.array([c]))
        return int(self.weight_before[hi[0]] - self.weight_before[lo[0]]) if hi[0] > lo[0] else 0

    def statistics(self, texts: list[np.ndarray]) -> list[np.ndarray]:
        """Weighted occurrences of every run of ``depth`` symbols of the streamed texts.

        All texts advance together from their right ends. A run's interval is cut back to the class
        of its first ``depth - 1`` symbols before the next symbol comes, so each costs one step;
        where the interval is empty, the shorter run is searched anew.
        """
        d, sizes = self.depth, np.array([len(t) for t in texts])
        by = np.argsort(-sizes, kind="stable")
        base = np.concatenate(([0], np.cumsum(sizes)[:-1])) if len(sizes) else sizes
        ids = self.encode(np.concatenate(texts)) if len(texts) else np.zeros(0, np.int64)
        out = np.zeros(len(ids), np.int64)
        live = by[: int((sizes >= d).sum())]
        lo, hi = np.zeros(len(live), np.int64), np.full(len(live), len(self.text))
        for k in range(d - 1):
            lo, hi = self.step(lo, hi, ids[base[live] + sizes[live] - 1 - k])
        for k in range(d - 1, int(sizes[live[0]]) if len(live) else 0):
            m = int((sizes[live] > k).sum())
            live, lo, hi = live[:m], lo[:m], hi[:m]
            at = base[live] + sizes[live] - 1 - k
            a, b = self.step(lo, hi, ids[at])
            found = b > a
            out[at] = np.where(found, self.weight_before[b] - self.weight_before[a], 0)
            some = np.where(found, a, 0)
            lo, hi = self.class_lo[some].copy(), self.class_hi[some].copy()
            if len(lost := np.flatnonzero(~found)):
                x, y = np.zeros(len(lost), np.int64), np.full(len(lost), len(self.text))
                for j in range(d - 2, -1, -1):
                    x, y = self.step(x, y, ids[at[lost] + j])
                    y = np.maximum(x, y)
                lo[lost], hi[lost] = x, y
        return [out[b : b + max(0, s - d + 1)] for b, s in zip(base, sizes, strict=True)]
