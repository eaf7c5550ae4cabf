"""How many items stand above a score: counts by boxes of items, each box settled as a whole where it can be.

Items are cut at medians into nested boxes. A box whose least product with a vector is above the score
counts whole, one whose largest is below counts nothing, and only boxes that the score cuts are opened.
"""

from __future__ import annotations

import numpy as np

#: Scores closer than this are ties, which go by id.
TIE = 1e-12
LEAF = 32
#: Numbers that one step looks at together.
CHUNK = 1 << 21
#: Share of the items that a few vectors may look at singly; beyond it plain products are faster.
WORTH = 0.05


class Boxes:
    """Nested boxes over items: ``start``, ``end`` in ``order``, centre, half width, left child (or -1)."""

    def __init__(self, ids: np.ndarray, v: np.ndarray) -> None:
        order = np.argsort(ids, kind="stable")
        start, end, child, low, high = [0], [len(ids)], [], [], []
        i = 0
        while i < len(start):
            a, b = start[i], end[i]
            rows = v[order[a:b]]
            low.append(rows.min(0))
            high.append(rows.max(0))
            wide = high[-1] - low[-1]
            if b - a > LEAF and wide.max() > 0:
                mid = (b - a) // 2
                # parts stay in order of ids, so boxes of equal vectors are sorted by id
                part = np.argpartition(rows[:, wide.argmax()], mid)
                order[a:b] = order[a:b][np.concatenate([np.sort(part[:mid]), np.sort(part[mid:])])]
                child.append(len(start))
                start += [a, a + mid]
                end += [a + mid, b]
            else:
                child.append(-1)
            i += 1
        self.start, self.end, self.child = np.array(start), np.array(end), np.array(child)
        low, high = np.array(low), np.array(high)
        self.centre, self.half = (low + high) / 2, (high - low) / 2
        self.ids, self.v = ids[order], v[order]

    def above(self, g: np.ndarray, own: np.ndarray, t: np.ndarray, most: int | None = None) -> np.ndarray | None:
        """Items above ``own`` for each vector; nothing if over ``most`` products of single items are due."""
        out, looked = np.zeros(len(g), np.int64), 0
        size, far = np.abs(g), np.abs(g).sum(1) * (np.abs(self.v).max() if len(self.v) else 0)
        slack = TIE + 1e-13 * (far + np.abs(own))
        todo = [(np.arange(len(g)), np.zeros(len(g), np.int64))] if len(self.v) else []
        while todo:
            q, n = todo.pop()
            if len(q) * g.shape[1] > CHUNK and len(q) > 1:
                h = len(q) // 2
                todo += [(q[:h], n[:h]), (q[h:], n[h:])]
                continue
            c = np.einsum("ij,ij->i", g[q], self.centre[n]) - own[q]
            r = np.einsum("ij,ij->i", size[q], self.half[n])
            np.add.at(out, q[whole := c - r > slack[q]], (self.end - self.start)[n[whole]])
            cut = ~whole & (c + r >= -slack[q])
            q, n, c = q[cut], n[cut], c[cut]
            inner = self.child[n] >= 0
            if inner.any():
                k = self.child[n[inner]]
                todo.append((np.repeat(q[inner], 2), np.stack([k, k + 1], 1).ravel()))
            same = ~inner & (self.half[n].max(1) == 0)
            if same.any():
                np.add.at(out, q[same], np.where(np.abs(c[same]) <= TIE, self._before(n[same], t[q[same]]), (c[same] > 0) * (self.end - self.start)[n[same]]))
            q, n = q[~inner & ~same], n[~inner & ~same]
            looked += len(q) * LEAF
            if most is not None and looked > most:
                return None
            for i in range(0, len(q), step := max(1, CHUNK // (LEAF * g.shape[1]))):
                p, m = q[i : i + step], n[i : i + step]
                at = self.start[m][:, None] + np.arange(LEAF)
                real = at < self.end[m][:, None]
                at = at.clip(0, len(self.v) - 1)
                d = np.einsum("ijk,ik->ij", self.v[at], g[p]) - own[p][:, None]
                np.add.at(out, p, (real & ((d > TIE) | (np.abs(d) <= TIE) & (self.ids[at] < t[p][:, None]))).sum(1))
        return out

    def _before(self, n: np.ndarray, t: np.ndarray) -> np.ndarray:
        """Items of a box of equal vectors with an id below ``t``, by bisection."""
        a, b = self.start[n].copy(), self.end[n].copy()
        while (open_ := a < b).any():
            mid = (a + b) // 2
            less = open_ & (self.ids[mid.clip(0, len(self.ids) - 1)] < t)
            a, b = np.where(less, mid + 1, a), np.where(open_ & ~less, mid, b)
        return a - self.start[n]


def _products(g: np.ndarray, own: np.ndarray, t: np.ndarray, ids: np.ndarray, v: np.ndarray) -> np.ndarray:
    out = np.zeros(len(g), np.int64)
    for i in range(0, len(g), step := max(1, CHUNK // max(1, len(ids)))):
        d = g[i : i + step] @ v.T - own[i : i + step, None]
        row, at = np.nonzero(np.abs(d) <= TIE)
        out[i : i + step] = np.count_nonzero(d > TIE, axis=1) + np.bincount(row[ids[at] < t[i + row]], minlength=len(d))
    return out


def count_above(g: np.ndarray, own: np.ndarray, t: np.ndarray, ids: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For each vector of ``g`` the items above ``own``; ties go to ids below ``t``."""
    few = np.linspace(0, len(g) - 1, min(len(g), 64)).astype(np.int64)
    boxes = Boxes(ids, v) if len(ids) > 64 * LEAF and len(g) > 64 else None
    if boxes is None or boxes.above(g[few], own[few], t[few], int(WORTH * len(few) * len(ids))) is None:
        return _products(g, own, t, ids, v)
    return boxes.above(g, own, t)
