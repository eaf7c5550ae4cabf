"""Training: draws, weights, limits of the graph weight, variants, and what a round leaves alone."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from crowdrank.operators import graph as g
from crowdrank.operators import sampling as sm
from crowdrank.operators import train as tr
from crowdrank.operators.models import Config, Example, Unit, draw, parameters, train_unit
from crowdrank.plans.training_queries import METHODS

SMALL = Config(aggregate="mean", d=4, rounds=1, local=2, pool=64)


@pytest.fixture(scope="module")
def toy(spark):
    uv = spark.createDataFrame([(u, 100 + (u * k) % 7, float(1 + k)) for u in range(8) for k in range(1, 4)], "user_id long, item_id long, w double")
    uu = g.symmetrise(spark.createDataFrame([(u, (u + 1) % 8) for u in range(8)], "src long, dst long"))
    records = spark.createDataFrame([(f"{u}-{u + 1}", [u, u + 1], 100 + u) for u in range(7)], "group_key string, members array<long>, item_id long")
    return uv, uu, records


def unit_of(n=6, d=4, seed=1):
    r = np.random.default_rng(seed)
    return Unit({u: r.normal(size=d) for u in range(n)}, {100 + v: r.normal(size=d) for v in range(n)}, {})


def test_graph_weight_limits():
    """With a weight of 0 only groups move, with an endless one only users."""
    unit = unit_of()
    examples = {"g": [Example([0, 1], 100)], "u": [Example([4], 105)]}
    pools = {"g": np.array([1, 2]), "u": np.array([3, 4])}
    for eta, moved, still in ((0.0, [0, 1], [2, 3, 4, 5]), (1e12, [4], [0, 1, 2, 3, 5])):
        dU, *_ = train_unit(unit, examples, {}, replace(SMALL, eta=eta), "joint", np.random.default_rng(0), pools)
        assert np.abs(dU[moved]).min() > 0 and np.abs(dU[still]).max() == 0
    dU, *_ = train_unit(unit, examples, {}, SMALL, "user", np.random.default_rng(0), pools)
    assert np.abs(dU[[0, 1]]).max() == 0 < np.abs(dU[4]).max()


def test_edges_are_drawn_by_weight():
    """An edge of no weight is never drawn."""
    unit = unit_of()
    examples = {"g": [], "u": [Example([0], 100, 3.0), Example([1], 101, 0.0), Example([2], 102, 1.0)]}
    dU, *_ = train_unit(unit, examples, {}, replace(SMALL, batch=8), "user", np.random.default_rng(0), {"g": np.array([5]), "u": np.array([5])})
    assert np.abs(dU[1]).max() == 0 and np.abs(dU[[0, 2]]).min() > 0


def test_group_negatives_follow_the_mixture():
    unit, c = unit_of(), replace(SMALL, negatives="group", m=4)
    part = [Example([0], 100, touched=[101, 102], share=0.75)] * 5000
    neg = draw("g", part, {"g": np.array([4, 5])}, unit, c, np.random.default_rng(2))
    assert abs(np.isin(neg, [1, 2]).mean() - 0.75) < 0.02 and abs((neg == 1).mean() - (neg == 2).mean()) < 0.02


def test_draws_follow_each_graphs_noise(spark, toy):
    uv, _, records = toy
    for kind, edges in (("u", uv), ("g", records.select("item_id", F.lit(1.0).alias("w")))):
        got = {r["id"]: r["n"] for r in tr.noise_draws(uv, records, replace(SMALL, pool=4000), 5).filter(f"what = 'd:{kind}'").groupBy("id").agg(F.count("*").alias("n")).collect()}
        assert sum(got.values()) == 20_000
        for r in sm.degree_noise(edges).collect():
            assert abs(got.get(r["item_id"], 0) / 20_000 - r["p"]) < 0.02


def test_items_of_tiny_shares_can_be_drawn(spark):
    noise = sm.ranges(spark.createDataFrame([(0, 1e9), (1, 1.0)], "item_id long, mass double"))
    hit = spark.createDataFrame([(0.5,), (1 - 2e-10,)], "u double")
    assert sorted(r["neg"] for r in sm.look_up(hit, noise).collect()) == [0, 1]


def test_touched_draws(spark, toy):
    uv, uu, records = toy
    ex, _ = tr.dealt_examples(uv, uu, records, replace(SMALL, negatives="group"))
    items = {}
    for r in uv.collect():
        items.setdefault(r["user_id"], {}).setdefault(r["item_id"], 0.0)
        items[r["user_id"]][r["item_id"]] += r["w"]
    for r in tr.touched_draws(ex, uv, SMALL).collect():
        pop = {}
        for u in r["members"]:
            for i, w in items[u].items():
                pop[i] = pop.get(i, 0) + w
        mass = sum((w + 1) ** 0.75 for w in pop.values())
        n_items = len({i for own in items.values() for i in own})
        assert set(r["touched"]) <= set(pop) and len(r["touched"]) == SMALL.touched
        assert abs(r["share"] - mass / (mass + n_items - len(pop))) < 1e-9


def test_ties_of_groups_are_exact(spark, toy):
    _, uu, records = toy
    got = {r["group_key"]: r["ties"] for r in tr.group_ties(records, uu).collect()}
    assert got["0-1"] == [0, 1, 1, 0] and len(got) == 7


def test_unit_rows_do_not_grow_with_the_items(spark, toy):
    """A unit pulls the items of its examples and draws, not all of them."""
    uv, uu, records = toy
    many = uv.union(spark.range(1000, 6000).select(F.lit(0).cast("long"), "id", F.lit(1e-9)))
    draws = tr.noise_draws(many, records, SMALL, 3)
    assert draws.count() == 3 * 2 * SMALL.pool


@pytest.mark.parametrize("name", ["consensus", "skip_connection", "input_pooling", "five_views", "plain_convolution", "voting", "influence", "metric", "neural_cf", "pooled", "two_stage", "simple"])
def test_variants_train_and_rank(spark, toy, name):
    uv, uu, records = toy
    c = replace(METHODS[name], d=4, rounds=2, local=1, pool=32, neighbours=2)
    m = tr.fit(uv, uu, records, c)
    ranks = tr.evaluate_groups(m, records, records.limit(0)).collect()
    assert len(ranks) == 7 and all(1 <= r["rnk"] <= r["candidates"] for r in ranks)
    assert set(m.params) == set(parameters(c, len(g.MEASURES) + tr.WALK_D))


def test_first_stage_of_influence_fixes_vectors(spark, toy):
    uv, uu, records = toy
    c = replace(METHODS["influence"], d=4, rounds=2, local=1, pool=32)
    one = tr.fit(uv, uu, records, replace(c, rounds=2))
    unit = unit_of()
    P = parameters(c, len(g.MEASURES) + tr.WALK_D)
    unit.features = {u: np.ones(len(g.MEASURES) + tr.WALK_D) for u in range(6)}
    dU, dV, dP, _ = train_unit(unit, {"g": [Example([0, 1], 100)], "u": []}, P, c, "group", np.random.default_rng(0), {"g": np.array([1]), "u": np.array([1])})
    assert np.abs(dU).max() == 0 and np.abs(dV).max() == 0 and one.users.count() == 8


def test_changes_of_units_add_up(spark):
    """Units with few gradients add their changes; with many, steps shrink as in one large unit."""
    rows = [("u", 1, [0.5, -0.2, 0.0]), ("u", 1, [0.25, 0.0, 0.0]), ("u", 2, [1.0, 1.0, 7.0]), ("u", 3, [1.0, 0.0, 100.0]), ("u", 3, [1.0, 0.0, 100.0]), ("v", 1, [9.0, 9.0, 0.0])]
    got = {r["id"]: r["g"] for r in tr.added(spark.createDataFrame(rows, "what string, id long, x array<double>"), "u", 2).collect()}
    assert np.allclose(got[1], [0.75, -0.2]) and np.allclose(got[2], [1.0, 1.0]) and np.allclose(got[3], [2**0.5, 0.0], atol=1e-4)


def test_users_who_share_items_meet_in_one_unit(spark):
    """Sixteen neighbourhoods of forty edges stay whole; one of many more edges than a unit holds is dealt out."""
    uv = spark.createDataFrame([(100 * k + u, 1000 * k + i, 1.0, 0) for k in range(16) for u in range(8) for i in range(5)], "user_id long, item_id long, w double, ts long")
    none = uv.select(F.lit("").alias("group_key"), F.array("user_id").alias("members"), "item_id").limit(0)
    ex, units = tr.dealt_examples(uv, uv.select(F.col("user_id").alias("src"), F.col("user_id").alias("dst")).limit(0), none, replace(SMALL, unit_rows=80))
    per = ex.groupBy(F.floor(F.col("members")[0] / 100).alias("k")).agg(F.count_distinct("unit").alias("n"), F.count("*").alias("rows")).collect()
    assert units == 8 and [(r["n"], r["rows"]) for r in per] == [(1, 40)] * 16
    ex, units = tr.dealt_examples(uv.withColumn("item_id", F.col("item_id") % 5), uv.select(F.col("user_id").alias("src"), F.col("user_id").alias("dst")).limit(0), none, replace(SMALL, unit_rows=80))
    assert ex.count() == 640 and ex.select("unit").distinct().count() > 1 and ex.groupBy("unit").count().agg(F.max("count")).first()[0] < 320


def test_units_are_filled_evenly(spark):
    """Equal parts follow each other into units; by hash some units got several times as many as others."""
    sizes = spark.range(40).select(F.col("id").alias("label"), F.lit(0).alias("part"), F.lit(90).alias("count"))
    places, units = tr.packed(sizes, 100)
    rows = places.groupBy("unit").count().collect()
    assert units == 36 and places.count() == 40 and max(r["count"] for r in rows) <= 2 and {r["unit"] for r in rows} == set(range(36))


def test_a_step_is_few_nodes_of_the_tape(monkeypatch):
    """A step of the whole model took some hundred nodes, each with several small arrays; now it takes a few."""
    from crowdrank.functions.tape import Var

    c = replace(METHODS["consensus"], d=4, local=1)
    near = {v: {u: [(u + 1) % 6, (u + 2) % 6] for u in range(6)} for v in c.views}
    unit, made, init = unit_of(), [0], Var.__init__
    unit.near = near
    P = parameters(c)

    def counted(self, *args, **kw):
        made[0] += 1
        init(self, *args, **kw)

    monkeypatch.setattr(Var, "__init__", counted)
    for stage in ("group", "user"):
        made[0] = 0
        train_unit(unit, {"g": [Example([0, 1, 2], 100, touched=[101], share=0.5)], "u": [Example([4], 105)]}, P, c, stage, np.random.default_rng(0), {"g": np.array([1, 2]), "u": np.array([3])})
        assert 0 < made[0] - len(P) <= 20


def test_product_loss_equals_the_loss_of_scores():
    from crowdrank.functions.tape import Var
    from crowdrank.operators.models import loss_of, pair_scores, product_loss

    r, c, got = np.random.default_rng(4), SMALL, []
    arrays = [r.normal(size=(3, 4)), r.normal(size=(3, 5, 4))]
    for whole in (False, True):
        x, v = map(Var, arrays)
        s = None if whole else pair_scores(x, v, {}, c)
        loss = product_loss(x, v) if whole else loss_of(s @ np.eye(5)[:, :1], s @ np.eye(5)[:, 1:], c)
        (loss * 0.25).backward()
        got.append((loss.data, x.grad, v.grad))
    assert all(np.allclose(a, b) for a, b in zip(*got, strict=True))
