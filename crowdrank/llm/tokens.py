"""Whole-text encoding with the tokenizers library, one call for each distinct piece.

Texts are cut where no pre-token of the two supported vocabularies can cross: at single spaces and
line ends between other characters, and behind a Latin letter that a mark or digit follows. The ids
of the pieces, joined, are the ids of the text; tests hold them against whole-text calls. Pieces are
found, hashed and looked up as arrays; only new ones reach the library.
"""

from __future__ import annotations

import numpy as np

from crowdrank.llm.common import byte_sums, run_hash

#: White space of one byte, and the UTF-8 forms of longer white space.
_WHITE = np.zeros(256, bool)
_WHITE[[*range(9, 14), *range(28, 33)]] = True
_WIDE = ("\x85", "\xa0", "\u1680", *map(chr, range(0x2000, 0x200B)), "\u2028", "\u2029", "\u202f", "\u205f", "\u3000")
_WIDE_LEADS = np.zeros(256, bool)
_WIDE_LEADS[[c.encode()[0] for c in _WIDE]] = True
_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[[*range(65, 91), *range(97, 123)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class PieceEncoder:
    """Numbers of pieces and their ids.

    ``spaced``: a piece carries the space before it and line ends are pieces (byte-level vocabulary);
    otherwise white space is dropped and case ignored, as the vocabulary itself does. At most about
    ``keep`` pieces are remembered; ``forget`` starts anew and is called by the user of the numbers.
    """

    def __init__(self, path: str, spaced: bool, keep: int = 1_500_000) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.spaced, self.keep = spaced, keep
        self.forget()

    def forget(self) -> None:
        self.known, self.number = np.zeros(0, np.uint64), np.zeros(0, np.int32)
        self.recent, self.recent_number = self.known, self.number
        self.count, self.used = 0, 0
        self.start, self.size, self.flat = np.zeros(1024, np.int64), np.zeros(1024, np.int32), np.zeros(8192, np.uint32)

    def full(self) -> bool:
        return self.count > self.keep or self.used > 16 * self.keep

    def add(self, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """New numbers for pieces whose ids stand in a row."""
        n = len(sizes)
        while self.count + n > len(self.start):
            self.start, self.size = np.concatenate((self.start, np.zeros_like(self.start))), np.concatenate((self.size, np.zeros_like(self.size)))
        while self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate((self.flat, np.zeros_like(self.flat)))
        at = slice(self.count, self.count + n)
        self.start[at], self.size[at] = self.used + np.cumsum(sizes) - sizes, sizes
        self.flat[self.used : self.used + len(ids)] = ids
        self.count, self.used = self.count + n, self.used + len(ids)
        return np.arange(at.start, at.stop, dtype=np.int32)

    def ids_of(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32)

    def learn(self, pieces: list[str], spaced: list[bool]) -> np.ndarray:
        """Numbers of new pieces. Those of letters alone, one pre-token each, share calls: words
        are joined by spaces, or by line ends where they stand without a space."""
        out = np.zeros(len(pieces), np.int32)
        plain, bare, other = [], [], []
        for i, (w, space) in enumerate(zip(pieces, spaced, strict=True)):
            (other if not w.isalpha() else plain if space else bare).append(i)
        for own, joint in ((plain, " "), (bare, "\n")):
            for lo in range(0, len(own), 256):
                part = own[lo : lo + 256]
                text = joint.join([pieces[i] for i in part])
                e = self.tokenizer.encode(f" {text}" if self.spaced and joint == " " else text, add_special_tokens=False)
                of, ids = np.array(e.word_ids), np.array(e.ids, np.uint32)
                cuts = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1], [True])))
                sizes = np.diff(cuts)
                if joint == "\n" and len(sizes) == 2 * len(part) - 1:
                    ids, sizes = ids[np.repeat(np.arange(len(sizes)) % 2 == 0, sizes)], sizes[::2]
                if len(sizes) == len(part):
                    out[part] = self.add(ids, sizes)
                else:
                    other += part
        for lo in range(0, len(other), 256):
            part = other[lo : lo + 256]
            rows = [self.ids_of(f" {pieces[i]}" if self.spaced and spaced[i] else pieces[i]) for i in part]
            out[part] = self.add(np.concatenate(rows), np.array([len(r) for r in rows]))
        return out

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Numbers of sorted keys, -1 where new."""
        out = np.full(len(keys), -1, np.int32)
        for table, number in ((self.known, self.number), (self.recent, self.recent_number)):
            if len(table):
                at = np.searchsorted(table, keys)
                at[at == len(table)] = 0
                out = np.where(table[at] == keys, number[at], out)
        return out

    def remember(self, keys: np.ndarray, numbers: np.ndarray) -> None:
        self.recent, self.recent_number = _merge(self.recent, self.recent_number, keys, numbers)
        if len(self.recent) > 65_536:
            self.known, self.number = _merge(self.known, self.number, self.recent, self.recent_number)
            self.recent, self.recent_number = np.zeros(0, np.uint64), np.zeros(0, np.int32)

    def pieces(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Piece numbers of all texts in a row, and where each text begins (with the end)."""
        coded = [t.encode() if t else b"" for t in texts]
        a, offsets = _joined(coded)
        odd = _odd(a, offsets, texts) if self.spaced else set()
        if odd:
            a, offsets = _joined([b"" if i in odd else c for i, c in enumerate(coded)])
        if not self.spaced:
            a = _LOWER[a]
        line = a == 10
        divider = np.zeros(len(a), bool)
        divider[offsets[1:] - 1] = True
        space = (a == 32) | (divider if self.spaced else line)
        letter = _ASCII_LETTER[a]
        latin = np.zeros(len(a), bool)
        latin[1:] = (a[:-1] == 0xC3) & (a[1:] != 0x97) & (a[1:] != 0xB7)
        begin = ~space
        fresh = np.ones(len(a), bool)
        fresh[1:] = space[:-1] | ((letter | latin)[:-1] & ~letter[1:] & (a[1:] < 0x80))
        if self.spaced:
            fresh |= line
            fresh[1:] |= line[:-1]
        begin &= fresh
        starts = np.flatnonzero(begin)
        last = ~space
        last[:-1] &= space[1:] | begin[1:]
        ends = np.flatnonzero(last) + 1
        before = np.zeros(len(starts), bool)
        if len(starts):
            before = (a[starts - 1] == 32) & (starts > 0) if self.spaced else np.ones(len(starts), bool)
        keys = run_hash(byte_sums(a), starts, ends)
        if self.spaced:
            keys = keys ^ (before * np.uint64(0xA5A5A5A55A5A5A5B))
        unique, first, inverse = np.unique(keys, return_index=True, return_inverse=True)
        numbers = self.find(unique)
        if len(new := np.flatnonzero(numbers < 0)):
            data, at = a.tobytes(), first[new]
            numbers[new] = self.learn([data[s:e].decode() for s, e in zip(starts[at].tolist(), ends[at].tolist(), strict=True)], before[at].tolist())
            self.remember(unique[new], numbers[new])
        found = numbers[inverse]
        edges = np.searchsorted(starts, offsets)
        if odd:
            parts = np.split(found, edges[1:-1])
            for i in odd:
                ids = self.ids_of(texts[i])
                parts[i] = self.add(ids, np.array([len(ids)]))
            found, edges = np.concatenate(parts), np.cumsum([0, *map(len, parts)])
        return found, edges

    def expand(self, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces in a row, and the number of ids before each piece (with the total)."""
        sizes = self.size[numbers].astype(np.int64)
        before = np.concatenate(([0], np.cumsum(sizes)))
        return self.flat[np.repeat(self.start[numbers] - before[:-1], sizes) + np.arange(before[-1])], before

    def encode_all(self, texts: list[str | None], group: int = 128):
        """Ids of each text as little-endian unsigned 32-bit integers."""
        for i in range(0, len(texts), group):
            numbers, edges = self.pieces(texts[i : i + group])
            ids, before = self.expand(numbers)
            data, cuts = ids.astype("<u4").tobytes(), (4 * before[edges]).tolist()
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                yield data[lo:hi]
            if self.full():
                self.forget()


def _joined(coded: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All texts with a line end behind each, and where they begin (with the end)."""
    return np.frombuffer(b"\n".join(coded) + b"\n", np.uint8), np.cumsum([0, *(len(c) + 1 for c in coded)])


def _odd(a: np.ndarray, offsets: np.ndarray, texts: list[str | None]) -> set[int]:
    """Texts with white space at an end, next to other white space, or of more than one byte."""
    white = _WHITE[a]
    at = np.flatnonzero(white[1:] & white[:-1])
    found = set(np.searchsorted(offsets, at + 1, side="right") - 1) | set(np.searchsorted(offsets, at, side="right") - 1)
    if white[0]:
        found.add(0)
    lead = np.flatnonzero(_WIDE_LEADS[a])
    if len(lead):
        found |= {i for i in set(np.searchsorted(offsets, lead, side="right") - 1) - found if any(c in texts[i] for c in _WIDE)}
    return {int(i) for i in found if texts[i] and (texts[i][0].isspace() or texts[i][-1].isspace() or _crowded(texts[i]))}


def _crowded(text: str) -> bool:
    space = np.array([c.isspace() for c in text])
    return bool((space[1:] & space[:-1]).any()) or any(c in text for c in _WIDE)


def _merge(keys: np.ndarray, values: np.ndarray, more: np.ndarray, more_values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.searchsorted(keys, more)
    return np.insert(keys, at, more), np.insert(values, at, more_values)


_LOADED: dict[tuple[str, bool], PieceEncoder] = {}


def encoder(path: str, spaced: bool, keep: int = 1_500_000) -> PieceEncoder:
    """One encoder a worker process."""
    if (path, spaced) not in _LOADED:
        _LOADED[path, spaced] = PieceEncoder(path, spaced, keep)
    return _LOADED[path, spaced]
