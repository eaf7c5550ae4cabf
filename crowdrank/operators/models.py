"""Group recommenders as forward functions over a unit's tables; the tape differentiates them.

A unit of work holds its examples and the vectors they touch. ``Unit.users(index)`` gives member
vectors, with or without the social convolution; a model turns padded members into group vectors and
scores them against items.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from crowdrank.functions import kernels as kn
from crowdrank.functions.tape import Table, Var, concat, exp, log_sigmoid, relu, softmax, stack


#: Squared gradients that every number starts with; they bound its first steps.
ACC = 1e-2


@dataclass
class Config:
    """One estimator; the ablations and baselines are settings of it.

    ``aggregate``: attention, mean, influence, voting, metric, ncf or virtual. ``views``: names of the
    neighbour lists that are convolved (empty: none); ``skip`` adds the base vector to a convolved one.
    ``over``: pools the tanh layer (``hidden``) or its ``input``. ``layers``: stacked blocks of voting.
    ``dense``: learning rate of shared parameters as a share of ``lr``. ``mode``: simple, two_stage,
    joint or pooled. ``negatives``: degree (each graph by its own noise), group or uniform. ``loss``: ns,
    pair or hinge. ``pool``: draws from the noise that a unit gets a graph; ``touched``: draws from the
    items that a group's members touched.
    """

    aggregate: str = "attention"
    views: tuple[str, ...] = ()
    mode: str = "joint"
    negatives: str = "degree"
    loss: str = "ns"
    d: int = 16
    heads: int = 2
    m: int = 4
    eta: float = 1.0
    gamma: float = 1.0
    lr: float = 0.3
    dense: float = 0.02
    over: str = "hidden"
    skip: bool = False
    layers: int = 2
    rounds: int = 3
    local: int = 24
    batch: int = 64
    unit_rows: int = 4000
    pool: int = 2048
    touched: int = 16
    neighbours: int = 4
    margin: float = 0.5
    seed: int = 7


def parameters(c: Config, features: int = 0) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(c.seed)
    d = c.d
    near_one = lambda: np.eye(d) + rng.normal(0, 0.05, (d, d))
    small = lambda *s: rng.normal(0, 0.1, s)
    p: dict[str, np.ndarray] = {}
    if c.aggregate in ("attention", "metric", "ncf"):
        p |= {n: near_one() for n in ("Wq", "Wk", "Wv", "Hq", "Hk", "Hv", "Wo")}
    if c.aggregate in ("attention", "voting", "metric", "ncf"):
        p |= {"Ws": near_one(), "bs": np.zeros(d), "ctx": small(d)}
    if c.aggregate == "influence":
        p |= {"F1": small(8, max(1, features)), "f1": np.zeros(8), "F2": small(1, 8)}
    if c.aggregate == "voting":
        p |= {"A": small(d, 2 * d)}
        for i in range(c.layers):
            p |= {f"{n}{i}": near_one() for n in ("Wq", "Wk", "Wv", "Hq", "Hk", "Hv", "Wo")} | {f"N1{i}": small(d, d), f"n1{i}": np.zeros(d), f"N2{i}": small(d, d)}
    if c.aggregate == "ncf":
        p |= {"M1": small(d, 3 * d), "m1": np.zeros(d), "M2": small(1, d), "m2": np.ones((1, d))}
    for v in c.views:
        p |= {f"P{v}": near_one(), f"p{v}": np.zeros(d), f"W{v}": np.concatenate([np.eye(d), 0.2 * np.eye(d)], 1) + small(d, 2 * d) * 0.5, f"w{v}": np.full(d, 0.01)}
    if len(c.views) > 1:
        p["Z"] = small(len(c.views), len(c.views) * d)
    return p


class Unit:
    """Vectors and lists that a unit of work pulled, by dense local numbers.

    ``near``: neighbours by view and user; ``features``: hand-made numbers of users; ``around``: mean
    vectors of the items and of the friends of users, side by side.
    """

    def __init__(self, users: dict[int, np.ndarray], items: dict[int, np.ndarray], near: dict[str, dict[int, list[int]]], features: dict[int, np.ndarray] | None = None, around: dict[int, np.ndarray] | None = None) -> None:
        self.user_at, self.item_at = {u: i for i, u in enumerate(users)}, {v: i for i, v in enumerate(items)}
        self.U = np.array(list(users.values())) if users else np.zeros((0, 1))
        self.V = np.array(list(items.values())) if items else np.zeros((0, 1))
        self.near, self.features, self.around = near, features or {}, around or {}
        self._padded: dict[str, tuple[np.ndarray, np.ndarray]] = {}

    def lists(self, own: np.ndarray, view: str) -> tuple[np.ndarray, np.ndarray]:
        """Padded neighbours of users ``own``; the lists of all users are padded once."""
        if view not in self._padded:
            near = self.near.get(view, {})
            rows = [[self.user_at[n] for n in near.get(u, ()) if n in self.user_at] for u in self.user_at]
            at, mask = np.zeros((len(rows), max([1, *map(len, rows)])), np.int64), np.zeros((len(rows), max([1, *map(len, rows)])), bool)
            for i, r in enumerate(rows):
                at[i, : len(r)], mask[i, : len(r)] = r, True
            self._padded[view] = at, mask
        at, mask = (x[own] for x in self._padded[view])
        n = max(1, int(mask.any(0).sum()))
        return at[:, :n], mask[:, :n]

    def users(self, own: np.ndarray, U: Var, P: dict[str, Var], c: Config) -> Var:
        """Vectors of the users with local numbers ``at``."""
        at, own = own, U.rows(own)
        if c.aggregate == "voting":
            own = own + Var(self.numbers(at, self.around, 2 * c.d)) @ P["A"].T
        if not c.views:
            return own
        views = []
        for v in c.views:
            near, mask = self.lists(at, v)
            y = kn.convolve(own, U.rows(near), mask, P, v)
            views.append(own + y if c.skip else y)
        return views[0] if len(views) == 1 else kn.mix_views(views, P["Z"])

    def groups(self, groups: list[list[int]], U: Var, P: dict[str, Var], c: Config, ties: list[list[int]] | None = None) -> tuple[Var, Var | None]:
        """Vectors of member lists, and the weights of their members.

        ``ties``: for each group its tied members, pair after pair (voting listens along ties only).
        """
        groups = [[u for u in g if u in self.user_at] for g in groups]
        at, mask = padded([len(g) for g in groups], np.array([self.user_at[u] for g in groups for u in g], np.int64))
        return self.pooled(at, mask, U, P, c, self.tied(groups, ties, at.shape[1]) if c.aggregate == "voting" else None)

    def numbers(self, at: np.ndarray, table: dict[int, np.ndarray], width: int) -> np.ndarray:
        """Rows of ``table`` for users by local number; zeros where there are none."""
        ids, none = list(self.user_at), np.zeros(width)
        return np.array([table.get(ids[i], none) for i in at.tolist()]).reshape(len(at), width)

    def tied(self, groups: list[list[int]], ties: list[list[int]] | None, n: int) -> np.ndarray:
        """Which of ``n`` places of each group listen to which: their own and tied ones."""
        out = np.zeros((len(groups), n, n), bool)
        for i, (g, flat) in enumerate(zip(groups, ties or [[]] * len(groups), strict=True)):
            place = {u: k for k, u in enumerate(g)}
            out[i, range(len(g)), range(len(g))] = True
            for p, q in zip(flat[::2], flat[1::2], strict=True):
                if p in place and q in place:
                    out[i, place[p], place[q]] = True
        return out

    def pooled(self, at: np.ndarray, mask: np.ndarray, U: Var, P: dict[str, Var], c: Config, tied: np.ndarray | None = None) -> tuple[Var, Var | None]:
        """As ``groups``, from padded local numbers of members; ``tied``: pairs of places that listen (voting)."""
        ids, local = np.unique(at[mask], return_inverse=True)
        at = np.zeros(mask.shape, np.int64)
        at[mask] = local
        n = mask.shape[1]
        x = self.users(ids, U, P, c).rows(at)
        b, _, d = x.shape
        if c.aggregate in ("mean", "virtual"):
            w = Var(mask / np.maximum(mask.sum(1, keepdims=True), 1))
        elif c.aggregate == "influence":
            f = self.numbers(ids, self.features, P["F1"].shape[1])
            score = relu(relu(Var(f) @ P["F1"].T + P["f1"]) @ P["F2"].T).reshape(len(ids), 1)
            w = softmax(score.rows(at).reshape(b, n), mask)
        else:
            if c.aggregate == "voting":
                o = x
                for layer in range(c.layers):
                    o = o + kn.masked_heads(o, tied, {k: P[f"{k}{layer}"] for k in ("Wq", "Wk", "Wv", "Hq", "Hk", "Hv", "Wo")}, c.heads)
                    o = o + relu(o @ P[f"N1{layer}"].T + P[f"n1{layer}"]) @ P[f"N2{layer}"].T
            else:
                o = kn.masked_heads(x, mask[:, None, :] & mask[:, :, None], P, c.heads)
            g, w = kn.attentive_pool(o, mask, P, over=c.over if c.aggregate == "attention" else "input")
            if c.aggregate == "metric":
                return (w.reshape(b, 1, n) @ x).reshape(b, d), w
            return g, w
        return (w.reshape(b, 1, n) @ x).reshape(b, d), w


def pair_scores(g: Var, v: Var, P: dict[str, Var], c: Config) -> Var:
    """``g`` (b, d) against ``v`` (b, m, d): (b, m)."""
    b, m, d = v.shape
    wide = g.reshape(b, 1, d)
    if c.aggregate == "metric":
        diff = v - wide
        return (diff * diff).sum(2) * -1.0
    if c.aggregate == "ncf":
        rep = wide * np.ones((b, m, 1))
        h = relu(concat([rep, v, rep * v]) @ P["M1"].T + P["m1"])
        return (h @ P["M2"].T + (rep * v) @ P["m2"].T).reshape(b, m)
    return (v @ g.reshape(b, d, 1)).reshape(b, m)


def product_loss(g: Var, v: Var) -> Var:
    """``loss_of`` of products of ``g`` (b, d) and ``v`` (b, m, d), the positive first, by negative sampling."""
    z = (v.data @ g.data[:, :, None])[:, :, 0]
    z[:, 0] *= -1
    cost = np.logaddexp(0, z)

    def back(up):
        ds = np.exp(z - cost) * up
        ds[:, 0] *= -1
        return (ds[:, None] @ v.data)[:, 0], ds[:, :, None] * g.data[:, None]

    return Var(cost.sum(), (g, v), back)


def loss_of(pos: Var, neg: Var, c: Config) -> Var:
    if c.loss == "pair":
        return -(log_sigmoid(pos - neg).sum() * (1 / neg.shape[1]))
    if c.loss == "hinge":
        return relu(neg - pos + c.margin).sum() * (1 / neg.shape[1])
    return -(log_sigmoid(pos).sum() + log_sigmoid(-neg).sum())


@dataclass
class Example:
    """A positive: members (one for a user edge), item, weight, and what was drawn for a group.

    ``touched``: items that the members touched, drawn by popularity; ``share``: the part of the noise
    that touched items hold; ``ties``: tied members, pair after pair.
    """

    members: list[int]
    item: int
    w: float = 1.0
    touched: list[int] | None = None
    share: float = 0.0
    ties: list[int] | None = None


def padded(sizes, flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lists that follow each other in ``flat``, as rows filled up by 0, and which places are real."""
    sizes = np.asarray(sizes, np.int64)
    mask = np.arange(max(1, int(sizes.max(initial=0)))) < sizes[:, None]
    at = np.zeros(mask.shape, np.int64)
    at[mask] = flat
    return at, mask


class Rows:
    """Examples of one kind as arrays of local numbers, made once a unit; lists lie one after another."""

    def __init__(self, rows: list[Example], unit: Unit) -> None:
        self.rows = rows
        self.members, self.size, self.start = self._flat([[unit.user_at[u] for u in e.members if u in unit.user_at] for e in rows])
        self.touched, self.count, self.first = self._flat([[unit.item_at[i] for i in e.touched or ()] for e in rows])
        self.item = np.array([unit.item_at[e.item] for e in rows], np.int64)
        self.share = np.array([e.share for e in rows])
        self.run = np.cumsum([e.w for e in rows])

    @staticmethod
    def _flat(lists: list[list[int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        size = np.array([len(x) for x in lists], np.int64)
        return np.array([i for x in lists for i in x], np.int64), size, np.cumsum(size) - size

    def groups(self, part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Padded members of the examples ``part``."""
        n = self.size[part]
        return padded(n, self.members[np.repeat(self.start[part] - (np.cumsum(n) - n), n) + np.arange(n.sum())])


def draw(kind: str, part: list[Example], pools: dict[str, np.ndarray], unit: Unit, c: Config, rng: np.random.Generator) -> np.ndarray:
    """Local numbers of ``m`` negatives a positive, from the draws that the unit got."""
    return drawn(kind, Rows(part, unit), np.arange(len(part)), pools, c, rng)


def drawn(kind: str, rows: Rows, part: np.ndarray, pools: dict[str, np.ndarray], c: Config, rng: np.random.Generator) -> np.ndarray:
    """``draw`` for the examples ``part`` of ``rows``."""
    neg = rng.choice(pools[kind], (len(part), c.m))
    if kind == "g" and c.negatives == "group":  # sparse mixture: touched items by popularity, the others evenly
        count = rows.count[part][:, None]
        hit = (rng.random(neg.shape) < rows.share[part][:, None]) & (count > 0)
        at = rows.first[part][:, None] + (rng.random(neg.shape) * count).astype(np.int64)
        neg[hit] = rows.touched[at[hit]]
    return neg


def train_unit(unit: Unit, examples: dict[str, list[Example]], P: dict[str, np.ndarray], c: Config, stage: str, rng: np.random.Generator, pools: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, dict, float]:
    """Local epochs over a unit's examples; returns what changed. ``pools``: local numbers of drawn items.

    Rows of vectors have one more column: the mean square of the gradients that the row has seen.
    """
    U, V = unit.U.copy(), unit.V.copy()
    acc = {"U": np.full_like(U, ACC), "V": np.full_like(V, ACC)}
    # shared parameters lie in one array, so that a step moves them at once
    flat = np.concatenate([np.ravel(v) for v in P.values()]) if P else np.zeros(0)
    start, moves, sq = flat.copy(), np.zeros_like(flat), np.full_like(flat, ACC)
    cuts = np.cumsum([0, *(np.size(v) for v in P.values())]).tolist()
    place = {k: slice(i, j) for k, i, j in zip(P, cuts[:-1], cuts[1:], strict=True)}
    params = {k: flat[place[k]].reshape(np.shape(v)) for k, v in P.items()}
    total, steps = 0.0, 0
    packs = {k: Rows(rows, unit) for k, rows in examples.items()}
    plain = c.loss == "ns" and c.aggregate not in ("metric", "ncf")
    pick = np.zeros((1 + c.m, 1))
    pick[0] = 1
    rest = np.eye(1 + c.m)[:, 1:]
    # the influence baseline learns its weights on vectors that the first stage has fixed
    frozen = c.aggregate == "influence" and stage == "group"

    n_g, n_u = len(examples["g"]), len(examples["u"])
    for _ in range(c.local):
        size = {"simple": n_g, "group": n_g, "user": n_u}.get(stage, n_g + n_u)
        for _ in range(-(-size // c.batch)):
            if stage in ("simple", "group"):
                kind = "g"
            elif stage == "user":
                kind = "u"
            elif stage == "pooled":
                kind = "g" if rng.random() < n_g / max(1, n_g + n_u) else "u"
            else:
                kind = "g" if rng.random() < 1 / (1 + c.eta) else "u"
            rows = packs[kind]
            if not rows.rows:
                continue
            # edges are drawn in proportion to their weight
            part = np.searchsorted(rows.run, rng.random(c.batch) * rows.run[-1], side="right").clip(0, len(rows.rows) - 1)
            Uv, Vv, Pv = Table(U), Table(V), {k: Var(v) for k, v in params.items()}
            if kind == "g":
                at, mask = rows.groups(part)
                tied = None
                if c.aggregate == "voting":
                    some = [rows.rows[i] for i in part.tolist()]
                    tied = unit.tied([[u for u in e.members if u in unit.user_at] for e in some], [e.ties or [] for e in some], at.shape[1])
                g, _ = unit.pooled(at, mask, Uv, Pv, c, tied)
            else:
                uniq, at = np.unique(rows.members[rows.start[part]], return_inverse=True)
                g = unit.users(uniq, Uv, Pv, c).rows(at)
            neg = drawn(kind, rows, part, pools, c, rng)
            v = Vv.rows(np.concatenate([rows.item[part][:, None], neg], 1))
            if plain:
                loss = product_loss(g, v)
            else:
                s = pair_scores(g, v, Pv, c)
                loss = loss_of(s @ pick, s @ rest, c)
            loss = loss * (1 / len(part))
            loss.backward()
            total, steps = total + float(loss.data), steps + 1
            for name, value, table in (("U", U, Uv), ("V", V, Vv)) if not frozen else ():
                at, grad = table.touched()
                acc[name][at] = seen = acc[name][at] + grad**2
                value[at] -= c.lr * grad / np.sqrt(seen)
            for name, p in Pv.items():
                moves[place[name]] = 0.0 if p.grad is None else p.grad.ravel()
            sq += moves * moves
            flat -= c.lr * c.dense * moves / np.sqrt(sq)
            if c.aggregate == "metric":
                for m in (U, V):
                    m /= np.maximum(1, np.sqrt((m**2).sum(1, keepdims=True)))
    moved = lambda new, old, a: np.c_[new - old, (a - ACC).mean(1)]
    change = {k: (flat - start)[place[k]].reshape(v.shape) for k, v in params.items()}
    return moved(U, unit.U, acc["U"]), moved(V, unit.V, acc["V"]), change, total / max(1, steps)


__all__ = ["Config", "Example", "Unit", "draw", "exp", "loss_of", "pair_scores", "parameters", "product_loss", "stack", "train_unit"]
