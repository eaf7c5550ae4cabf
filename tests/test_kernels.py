"""Gradients against central differences, and closed-form values of kernels."""

import numpy as np
import pytest

from crowdrank.functions import kernels as kn
from crowdrank.functions.tape import Table, Var, log_sigmoid
from crowdrank.operators.models import Config, Unit, loss_of, pair_scores, parameters

RNG = np.random.default_rng(0)


def check(f, arrays, eps=1e-6):
    vs = [Var(a) for a in arrays]
    f(*vs).backward()
    for i, (a, v) in enumerate(zip(arrays, vs, strict=True)):
        at = tuple(RNG.integers(0, n) for n in a.shape)
        up, down = [x.copy() for x in arrays], [x.copy() for x in arrays]
        up[i][at] += eps
        down[i][at] -= eps
        want = (f(*map(Var, up)).data - f(*map(Var, down)).data) / (2 * eps)
        assert np.isclose(v.grad[at], want, rtol=1e-4, atol=1e-6)


@pytest.mark.parametrize("round_", range(4))
def test_attention_gradients(round_):
    mask = np.array([[1, 1, 1], [1, 1, 0]], bool)
    names = ("Wq", "Wk", "Wv", "Hq", "Hk", "Hv", "Wo", "Ws", "bs", "ctx")
    arrays = [RNG.normal(size=(2, 3, 4))] + [RNG.normal(size=4 if n in ("bs", "ctx") else (4, 4)) for n in names]
    check(lambda x, *p: (kn.crowd_attention(x, mask, dict(zip(names, p, strict=True)), 2)[0] * np.arange(4.0)).sum(), arrays)


@pytest.mark.parametrize("pool", ["mean", "weighted", "max"])
def test_convolution_gradients(pool):
    mask = np.array([[1, 1], [1, 0]], bool)
    arrays = [RNG.normal(size=s) for s in ((2, 3), (2, 2, 3), (3, 3), (3,), (3, 6), (3,))]
    check(lambda u, n, a, b, c, d: (kn.convolve(u, n, mask, {"P0": a, "p0": b, "W0": c, "w0": d}, "0", pool, np.array([[1.0, 3.0], [2.0, 0.0]])) * np.arange(3.0)).sum(), arrays)


def test_view_mix_gradients():
    arrays = [RNG.normal(size=s) for s in ((2, 3), (2, 3), (2, 6))]
    check(lambda a, b, z: (kn.mix_views([a, b], z) * np.arange(3.0)).sum(), arrays)


@pytest.mark.parametrize("aggregate,loss", [("attention", "ns"), ("voting", "pair"), ("metric", "hinge"), ("ncf", "ns"), ("influence", "ns"), ("mean", "ns")])
def test_model_gradients(aggregate, loss):
    c = Config(aggregate=aggregate, loss=loss, d=4, heads=2, m=2)
    P = parameters(c, 2)
    unit = Unit({1: RNG.normal(size=4), 2: RNG.normal(size=4), 5: RNG.normal(size=4)}, {7: np.ones(4)}, {"ties": {1: [2], 2: [1]}}, {1: np.array([0.5, 1.0])})
    items = RNG.normal(size=(2, 3, 4))
    names = sorted(P)

    def f(U, V, *p):
        params = dict(zip(names, p, strict=True))
        g, _ = unit.groups([[1, 2], [5, 1, 2]], U, params, c)
        s = pair_scores(g, V, params, c)
        return loss_of(s @ np.array([[1.0], [0], [0]]), s @ np.eye(3)[:, 1:], c)

    check(f, [unit.U, items, *(P[n] for n in names)])


def test_closed_forms():
    u, near = Var([[1.0, 0.0]]), Var([[[0.0, 1.0], [0.0, 3.0]]])
    p = {"P0": Var(np.eye(2)), "p0": Var(np.zeros(2)), "W0": Var(np.concatenate([np.eye(2)] * 2, 1)), "w0": Var(np.zeros(2))}
    assert np.allclose(kn.convolve(u, near, np.ones((1, 2), bool), p, "0").data, np.array([[1, 2]]) / np.sqrt(5))
    assert np.allclose(kn.convolve(u, near, np.zeros((1, 2), bool), p, "0").data, [[1, 0]])
    x, mask = Var(RNG.normal(size=(1, 3, 4))), np.ones((1, 3), bool)
    flat = kn.self_attention(x, mask, np.zeros((4, 4)), np.zeros((4, 4)), np.eye(4))
    assert np.allclose(flat.data, x.data.mean(1, keepdims=True))
    pooled, w = kn.attentive_pool(x, mask, {"Ws": Var(np.eye(4)), "bs": Var(np.zeros(4)), "ctx": Var(np.zeros(4))})
    assert np.allclose(pooled.data, np.tanh(x.data).mean(1)) and np.allclose(w.data, 1 / 3)
    assert np.allclose(-log_sigmoid(Var(np.zeros(7))).data.sum(), 7 * np.log(2))


def test_permutation_and_padding_do_not_matter():
    p = kn.pseudo_parameters(4)
    x = RNG.normal(size=(1, 3, 4))
    a, _ = kn.crowd_attention(Var(x), np.ones((1, 3), bool), p, 2)
    b, _ = kn.crowd_attention(Var(x[:, [2, 0, 1]]), np.ones((1, 3), bool), p, 2)
    wide = np.concatenate([x, np.full((1, 2, 4), 9.0)], 1)
    c, w = kn.crowd_attention(Var(wide), np.array([[1, 1, 1, 0, 0]], bool), p, 2)
    assert np.allclose(a.data, b.data) and np.allclose(a.data, c.data) and np.allclose(w.data.sum(), 1)


def test_heads_must_divide():
    with pytest.raises(ValueError, match="not divisible"):
        kn.multi_head(Var(np.zeros((1, 1, 4))), np.ones((1, 1), bool), kn.pseudo_parameters(4), 3)


def test_table_keeps_gradients_of_touched_rows_only():
    """The rows that a step took, with the gradients that the whole table would have got."""
    x, at = RNG.normal(size=(50, 3)), [np.array([[4, 7], [4, 9]]), np.array([9, 30])]
    whole, table = Var(x), Table(x)
    for v in (whole, table):
        ((v.rows(at[0]) * v.rows(at[0])).sum() + (v.rows(at[1]) * 3.0).sum()).backward()
    rows, grad = table.touched()
    assert rows.tolist() == [4, 7, 9, 30] and np.allclose(grad, whole.grad[rows]) and table.grad is None


def test_network_scores_equal_pair_scores():
    """One matrix a group gives the scores of the network, without a row a pair."""
    from types import SimpleNamespace

    from crowdrank.operators import train as tr

    c = Config(aggregate="ncf", d=4)
    P, g, v = {k: x + 0.3 for k, x in parameters(c).items()}, RNG.normal(size=(5, 4)), RNG.normal(size=(7, 4))
    want = pair_scores(Var(g), Var(np.broadcast_to(v, (5, 7, 4))), {k: Var(x) for k, x in P.items()}, c).data
    score = tr.scorer(SimpleNamespace(config=c, params=P))
    assert np.allclose(score(g, v), want) and "pair_scores" not in score.__code__.co_names
