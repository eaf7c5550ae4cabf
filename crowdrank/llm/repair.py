"""Re-Pair grammars over id sequences, and the shard format that holds them.

A round counts all adjacent pairs of a shard and replaces the most frequent ones by new symbols,
many at once: a symbol is either a left or a right member in a round, so replacements never overlap
(runs of one symbol are paired from their left). Pairs inside chunks are counted on the distinct
chunks with their frequencies; rounds over the whole sequence follow for pairs that cross chunks. Both
go on until no pair is frequent enough or a round saves less than a stated share of the symbols. No
pair crosses the end of a document, so every document starts at a symbol.

Shard: magic ``RPSHARD2``; five unsigned 64-bit numbers: documents, rules, symbols, ids, first
nonterminal; document ids (signed 64 bits) and a byte each, 1 where there is no id; first symbol of
each document, plus the end (64 bits); ids of each document (64 bits); rules (two 24-bit symbols
each); expansion length of each rule (32 bits); the sequence (24-bit symbols). All little-endian.
"""

from __future__ import annotations

import struct

import numpy as np

MAGIC = b"RPSHARD2"


_SLOTS = 1 << 20


def _slot(keys: np.ndarray) -> np.ndarray:
    return ((keys * np.int64(0x9E3779B97F4A7C15 - 2**64)) >> np.int64(42)) & np.int64(_SLOTS - 1)


def pick_pairs(keys: np.ndarray, weights: np.ndarray | None, least: int, most: int) -> np.ndarray:
    """The most frequent pairs (``left << 32 | right``), each symbol on one side only."""
    slot = _slot(keys)
    often = (np.bincount(slot, weights, minlength=_SLOTS) >= least)[slot]
    if not often.any():
        return keys[:0]
    pairs, at = np.unique(keys[often], return_inverse=True)
    counts = np.bincount(at, None if weights is None else weights[often])
    order = np.argsort(-counts, kind="stable")[: 2 * most]
    side: dict[int, int] = {}
    out = []
    for pair in pairs[order[counts[order] >= least]].tolist():
        a, b = pair >> 32, pair & 0xFFFFFFFF
        if a == b and a in side or side.get(a, 1) != 1 or side.get(b, 2) != 2:
            continue
        side[a], side[b] = (3, 3) if a == b else (1, 2)
        out.append(pair)
        if len(out) == most:
            break
    return np.array(out, np.int64)


def replace(seq: np.ndarray, joined: np.ndarray, pairs: np.ndarray, first: int) -> np.ndarray:
    """``seq`` with the i-th pair replaced by ``first + i``, marked: deleted places become -1.

    ``joined[i]``: places i and i + 1 may form a pair.
    """
    keys = (seq[:-1] << np.int64(32)) | seq[1:]
    order = np.argsort(pairs)
    near = np.zeros(_SLOTS, bool)
    near[_slot(pairs)] = True
    hit = np.flatnonzero(near[_slot(keys)] & joined)
    at = np.searchsorted(pairs[order], keys[hit])
    at[at == len(pairs)] = 0
    real = pairs[order][at] == keys[hit]
    hit, at = hit[real], at[real]
    if not len(hit):
        return seq
    same = seq[hit] == seq[hit + 1]
    if same.any():
        new = np.concatenate(([True], (np.diff(hit) > 1) | ~same[1:] | ~same[:-1] | (seq[hit[1:]] != seq[hit[:-1]])))
        start = np.maximum.accumulate(np.where(new, np.arange(len(hit)), 0))
        keep = ~same | ((np.arange(len(hit)) - start) % 2 == 0)
        hit, at = hit[keep], at[keep]
    out = seq.copy()
    out[hit] = first + order[at]
    out[hit + 1] = -1
    return out


def compress(chunks: list[np.ndarray] | tuple[np.ndarray, np.ndarray], sequence: np.ndarray, end_chunk: int, first: int, least: int = 8, most: int = 16_384, share: float = 0.05) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rules ``(n, 2)``, symbols and places of document ends for a sequence of chunk numbers.

    ``chunks``: flat ids and sizes. A pair must occur ``least`` times; a round replaces at most
    ``most`` pairs and the next one takes the others; rounds end when one saves less than ``share``.
    """
    flat, sizes = chunks
    rules: list[np.ndarray] = []
    weight = np.bincount(sequence, minlength=len(sizes)).astype(np.float64)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    flat = flat.astype(np.int64)
    symbol = first
    while True:
        joined = owner[1:] == owner[:-1]
        inner = np.flatnonzero(joined)
        pairs = pick_pairs((flat[inner] << np.int64(32)) | flat[inner + 1], weight[owner[inner]], least, most) if len(inner) else flat[:0]
        if not len(pairs):
            break
        flat = replace(flat, joined, pairs, symbol)
        kept = flat >= 0
        saved, size = weight[owner[~kept]].sum(), weight[owner].sum()
        owner, flat = owner[kept], flat[kept]
        rules.append(np.stack((pairs >> 32, pairs & 0xFFFFFFFF), 1))
        symbol += len(pairs)
        if saved < share * size:
            break
    sizes = np.bincount(owner, minlength=len(sizes))
    starts = np.cumsum(sizes) - sizes
    n = sizes[sequence]
    where = np.repeat(starts[sequence] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
    seq = flat[where]
    last = np.zeros(len(seq), bool)
    last[np.cumsum(n)[sequence == end_chunk] - 1] = True
    while True:
        joined = ~last[:-1]
        inner = np.flatnonzero(joined)
        pairs = pick_pairs((seq[inner] << np.int64(32)) | seq[inner + 1], None, least, most) if len(inner) else seq[:0]
        if not len(pairs):
            break
        new = replace(seq, joined, pairs, symbol)
        gone = new < 0
        last[:-1] |= gone[1:] & last[1:]
        size = len(seq)
        last, seq = last[~gone], new[~gone]
        rules.append(np.stack((pairs >> 32, pairs & 0xFFFFFFFF), 1))
        symbol += len(pairs)
        if size - len(seq) < share * size:
            break
    return (np.concatenate(rules) if rules else np.zeros((0, 2), np.int64)), seq, np.flatnonzero(last)


def _pack24(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]).tobytes()


def _unpack24(b: bytes) -> np.ndarray:
    out = np.zeros((len(b) // 3, 4), np.uint8)
    out[:, :3] = np.frombuffer(b, np.uint8).reshape(-1, 3)
    return out.view("<u4").ravel()


def lengths_of(rules: np.ndarray, first: int) -> np.ndarray:
    out = np.ones(len(rules), np.int64)
    for i, (a, b) in enumerate(rules.tolist()):
        out[i] = (out[a - first] if a >= first else 1) + (out[b - first] if b >= first else 1)
    return out


def write_shard(docs: list[int | None], counts: np.ndarray, rules: np.ndarray, seq: np.ndarray, ends: np.ndarray, first: int) -> bytes:
    starts = np.concatenate(([0], ends + 1)).astype("<i8")
    head = struct.pack("<5Q", len(docs), len(rules), len(seq), int(counts.sum()), first)
    ids = np.array([0 if d is None else d for d in docs], "<i8").tobytes()
    return b"".join((MAGIC, head, ids, bytes(d is None for d in docs), starts.tobytes(), counts.astype("<i8").tobytes(), _pack24(rules.ravel()), lengths_of(rules, first).astype("<u4").tobytes(), _pack24(seq)))


class Shard:
    """Random access to the documents of a shard; a rule is expanded when first needed."""

    _terminals: list[bytes] = []

    def __init__(self, blob: bytes) -> None:
        if blob[:8] != MAGIC:
            raise ValueError("not a shard of this format")
        d, r, s, self.n_ids, self.first = struct.unpack("<5Q", blob[8:48])
        at = 48

        def take(n: int) -> bytes:
            nonlocal at
            at += n
            return blob[at - n : at]

        numbers = np.frombuffer(take(8 * d), "<i8").tolist()
        self.docs = [None if none else x for x, none in zip(numbers, take(d), strict=True)]
        self.starts = np.frombuffer(take(8 * (d + 1)), "<i8")
        self.counts = np.frombuffer(take(8 * d), "<i8")
        self.rules = _unpack24(take(6 * r)).reshape(-1, 2)
        self.lengths = np.frombuffer(take(4 * r), "<u4")
        self.symbols = _unpack24(take(3 * s))
        self._known: dict[int, bytes] = {}
        self._all: list[bytes] | None = None

    def expand_all(self) -> None:
        """Expand every rule at once, for readers of the whole shard."""
        if len(Shard._terminals) < self.first:
            Shard._terminals = [i.to_bytes(4, "little") for i in range(self.first)]
        known = Shard._terminals[: self.first]
        for a, b in self.rules.tolist():
            known.append(known[a] + known[b])
        self._all = known

    def expand(self, symbol: int) -> bytes:
        """Ids of a symbol, as little-endian 32-bit integers."""
        known, first, todo = self._known, self.first, [] if symbol in self._known else [symbol]
        while todo:
            x = todo[-1]
            if x in known:
                todo.pop()
            elif x < first:
                known[x] = x.to_bytes(4, "little")
                todo.pop()
            else:
                a, b = self.rules[x - first].tolist()
                if a in known and b in known:
                    known[x] = known[a] + known[b]
                    todo.pop()
                else:
                    todo += [y for y in (b, a) if y not in known]
        return known[symbol]

    def ids(self, i: int, start: int = 0, stop: int | None = None) -> bytes:
        """Ids ``start`` to ``stop`` of the i-th document (with its end id), as little-endian 32-bit integers.

        Expansion lengths say which symbols hold them; no others are expanded.
        """
        own = self.symbols[self.starts[i] : self.starts[i + 1]]
        n = int(self.counts[i])
        stop = n if stop is None else min(stop, n)
        if start >= stop:
            return b""
        cut = 0
        if start > 0 or stop < n:
            sizes = np.ones(len(own), np.int64)
            rule = own >= self.first
            sizes[rule] = self.lengths[own[rule] - self.first]
            ends = np.cumsum(sizes)
            lo, hi = int(np.searchsorted(ends, start, side="right")), int(np.searchsorted(ends, stop)) + 1
            own, cut = own[lo:hi], start - (int(ends[lo - 1]) if lo else 0)
        if self._all is not None:
            parts = map(self._all.__getitem__, own.tolist())
        else:
            parts = map(self.expand, own.tolist())
        return b"".join(parts)[4 * cut : 4 * (cut + stop - start)]
