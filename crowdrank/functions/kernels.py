"""Forward kernels: attention over members, pooling, convolution over neighbours, view mixing.

Batches are padded: ``x`` is (groups, members, d) with a boolean mask. Readings: queries, keys and
values are projected twice (d x d, then d x d/h a head); scores are scaled by the root of ``d``
(``scale='head'``: of d/h); the pooled vector sums the tanh layer (``over='input'``: its input).

Training runs heads, pooling, convolution and mixing in every step, so each is one node of the tape with
its gradient written out; the two projections of a head are multiplied first, as they are small.
"""

from __future__ import annotations

import numpy as np

from crowdrank.functions.tape import Var, concat, normalise, relu, shares, softmax, var


def self_attention(x: Var, mask: np.ndarray, wq, wk, wv) -> Var:
    d = x.shape[-1]
    q, k, v = x @ var(wq).T, x @ var(wk).T, x @ var(wv).T
    return softmax((q @ k.T) * (1 / np.sqrt(d)), mask[:, None, :]) @ v


def masked_heads(x: Var, pairs: np.ndarray, p: dict, heads: int, scale: str = "model") -> Var:
    """Heads over the pairs of members that ``pairs`` (groups, members, members) allows."""
    b, n, d = x.shape
    if d % heads:
        raise ValueError(f"dimension {d} is not divisible by {heads} heads")
    w = d // heads
    names = [f"{m}{c}" for c in "qkv" for m in "WH"]
    P, wo = [var(p[n]) for n in names], var(p["Wo"])
    twice = [(P[i].data, P[i + 1].data) for i in (0, 2, 4)]
    both = np.concatenate([h @ a for a, h in twice])
    flat, factor = x.data.reshape(b * n, d), 1 / np.sqrt(d if scale == "model" else w)
    q, k, v = np.ascontiguousarray((flat @ both.T).reshape(b, n, 3, heads, w).transpose(2, 0, 3, 1, 4))
    s = shares((q @ np.swapaxes(k, 2, 3)) * factor, pairs[:, None])
    o = np.swapaxes(s @ v, 1, 2).reshape(b * n, d)

    def back(g):
        g = g.reshape(b * n, len(wo.data))
        do = np.swapaxes((g @ wo.data).reshape(b, n, heads, w), 1, 2)
        ds = do @ np.swapaxes(v, 2, 3)
        ds = s * (ds - (ds * s).sum(-1, keepdims=True)) * factor
        parts = np.stack([ds @ k, np.swapaxes(ds, 2, 3) @ q, np.swapaxes(s, 2, 3) @ do])
        dx = parts.transpose(1, 3, 0, 2, 4).reshape(b * n, 3 * d)
        dp = [m for (a, h), t in zip(twice, (dx.T @ flat).reshape(3, d, d), strict=True) for m in (h.T @ t, t @ a.T)]
        return ((dx @ both).reshape(b, n, d), *dp, g.T @ o)

    return Var((o @ wo.data.T).reshape(b, n, len(wo.data)), (x, *P, wo), back)


def multi_head(x: Var, mask: np.ndarray, p: dict, heads: int, scale: str = "model") -> Var:
    return masked_heads(x, np.broadcast_to(mask[:, None, :], (*mask.shape, mask.shape[1])), p, heads, scale)


def attentive_pool(o: Var, mask: np.ndarray, p: dict, over: str = "hidden") -> tuple[Var, Var]:
    """The pooled vectors and the member weights."""
    ws, bs, ctx = (var(p[k]) for k in ("Ws", "bs", "ctx"))
    b, n, d = o.shape
    flat, c = o.data.reshape(b * n, d), ctx.data.ravel()
    a = np.tanh(flat @ ws.data.T + bs.data)
    w = shares((a @ c).reshape(b, n), mask)
    base = (a if over == "hidden" else flat).reshape(b, n, d)

    def weights(dw, da=0.0, do=0.0):
        dl = (w * (dw - (dw * w).sum(1, keepdims=True))).reshape(b * n)
        dz = (dl[:, None] * c + da) * (1 - a * a)
        return (dz @ ws.data + do).reshape(b, n, d), dz.T @ flat, dz.sum(0), (dl @ a).reshape(ctx.shape)

    def pooled(g):
        each = (w[:, :, None] * g[:, None]).reshape(b * n, d)
        dw = (base @ g[:, :, None])[:, :, 0]
        return weights(dw, each) if over == "hidden" else weights(dw, do=each)

    parents = (o, ws, bs, ctx)
    return Var((w[:, None] @ base)[:, 0], parents, pooled), Var(w, parents, weights)


def crowd_attention(x: Var, mask: np.ndarray, p: dict, heads: int) -> tuple[Var, Var]:
    return attentive_pool(multi_head(x, mask, p, heads), mask, p)


def convolve(own: Var, near: Var, mask: np.ndarray, p: dict, view: str, pool: str = "mean", weights: np.ndarray | None = None) -> Var:
    """``own`` (n, d), ``near`` (n, k, d): dense layer on neighbours, pool, join, dense layer, unit length."""
    n, k, d = near.shape
    if pool == "max":
        r = relu(near @ p[f"P{view}"].T + p[f"p{view}"])
        masked = np.where(mask[:, :, None], r.data, -np.inf)
        at = np.where(mask.any(1)[:, None], masked.argmax(1), 0)
        pick = np.zeros((n, k, d))
        pick[np.arange(n)[:, None], at, np.arange(d)[None, :]] = mask.any(1)[:, None]
        return normalise(relu(concat([own, (r * pick).sum(1)]) @ p[f"W{view}"].T + p[f"w{view}"]))
    pn, bn, pw, bw = (var(p[f"{c}{view}"]) for c in "PpWw")
    w = mask.astype(float) if pool == "mean" or weights is None else weights * mask
    w = w / np.maximum(w.sum(1, keepdims=True), 1e-12)
    flat, first, rest = near.data.reshape(n * k, d), pw.data[:, :d], pw.data[:, d:]
    r = flat @ pn.data.T
    r += bn.data
    np.maximum(r, 0, out=r)
    h = (w[:, None] @ r.reshape(n, k, len(pn.data)))[:, 0]
    z = own.data @ first.T + h @ rest.T
    z += bw.data
    np.maximum(z, 0, out=z)
    size = np.sqrt((z * z).sum(1, keepdims=True))
    size[size == 0] = 1.0
    y = z / size

    def back(g):
        dz = (g - y * (g * y).sum(1, keepdims=True)) / size
        dz *= z > 0
        dr = (w[:, :, None] * (dz @ rest)[:, None]).reshape(n * k, len(pn.data))
        dr *= r > 0
        return dz @ first, (dr @ pn.data).reshape(n, k, d), dr.T @ flat, dr.sum(0), np.concatenate([dz.T @ own.data, dz.T @ h], 1), dz.sum(0)

    return Var(y, (own, near, pn, bn, pw, bw), back)


def mix_views(views: list[Var], z) -> Var:
    z, c = var(z), len(views)
    x = np.concatenate([v.data for v in views], 1)
    parts = x.reshape(len(x), c, x.shape[1] // c)
    alpha = shares(x @ z.data.T)

    def back(g):
        da = (parts @ g[:, :, None])[:, :, 0]
        da = alpha * (da - (da * alpha).sum(1, keepdims=True))
        dx = (alpha[:, :, None] * g[:, None]).reshape(x.shape) + da @ z.data
        return (*np.split(dx, c, 1), da.T @ x)

    return Var((alpha[:, None] @ parts)[:, 0], (*views, z), back)


def pseudo(i, k, salt: int):
    """Entries of deterministic stand-ins for parameters, the same arithmetic as in the SQL twins."""
    return ((np.asarray(i, np.int64) * 7919 + np.asarray(k, np.int64) * 104729 + salt * 1299709) % 1000003) / 1000003.0 - 0.5


def pseudo_matrix(rows: int, cols: int, salt: int) -> np.ndarray:
    return pseudo(np.arange(rows)[:, None], np.arange(cols)[None, :], salt)


def pseudo_parameters(d: int, views: int = 0) -> dict[str, Var]:
    salts = {"Wq": 11, "Wk": 12, "Wv": 13, "Hq": 111, "Hk": 112, "Hv": 113, "Wo": 14, "Ws": 15}
    p = {name: Var(pseudo_matrix(d, d, s)) for name, s in salts.items()}
    p |= {"ctx": Var(pseudo(0, np.arange(d), 16)), "bs": Var(pseudo(0, np.arange(d), 17))}
    p |= {"P0": Var(pseudo_matrix(d, d, 21)), "p0": Var(pseudo(0, np.arange(d), 22)), "W0": Var(pseudo_matrix(d, 2 * d, 23)), "w0": Var(pseudo(0, np.arange(d), 24))}
    return p
