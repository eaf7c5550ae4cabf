"""Ranks counted by boxes of items, and what is left on disk behind a stored table."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from crowdrank.operators import graph as g
from crowdrank.operators import rank as rk


@pytest.mark.parametrize("d, kind", [(1, "tied"), (3, "free"), (16, "free"), (4, "curve")])
def test_box_counts_equal_products(d, kind):
    from crowdrank.operators import halfspace as h

    r = np.random.default_rng(d)
    v = {"tied": r.integers(0, 9, (4000, d)) * 1.0, "free": r.normal(size=(4000, d)), "curve": (r.permutation(4000)[:, None] * 7919 + np.arange(d) * 104729) % 1000003 / 1000003 - 0.5}[kind]
    q, ids, own_at = np.ones((200, d)) if kind == "tied" else r.normal(size=(200, d)), r.permutation(4000), r.integers(0, 4000, 200)
    own, t = (q * v[own_at]).sum(1), ids[own_at]
    s = q @ v.T - own[:, None]
    want = ((s > h.TIE) | (np.abs(s) <= h.TIE) & (ids < t[:, None])).sum(1)
    assert (h.Boxes(ids, v).above(q, own, t) == want).all() and (h.count_above(q, own, t, ids, v) == want).all()


def test_a_test_pair_meets_few_blocks_of_items(spark):
    """20,000 items are one block: test pairs are not copied, and ranks leave out what was seen."""
    items = spark.range(20_000).select("id", F.array(F.col("id") * 1.0).alias("vec"))
    groups = spark.createDataFrame([("a", [1.0]), ("b", [-1.0]), ("c", [0.0])], "group_key string, vec array<double>")
    truth = spark.createDataFrame([("a", 19_990), ("b", 5), ("c", 7)], "group_key string, item_id long")
    seen = spark.createDataFrame([("a", 19_999), ("a", 3), ("a", 19_990), ("c", 2)], "group_key string, item_id long")
    out = rk.truth_rank_blocks(truth, groups, items, seen)
    assert sorted(map(tuple, out.collect())) == [("a", 19_990, 9, 19_998), ("b", 5, 6, 20_000), ("c", 7, 7, 19_999)]
    assert "[0,1,2]" not in out._jdf.queryExecution().executedPlan().toString()


def test_stored_tables_leave_no_shuffle_files(spark):
    disk = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: {f for f in (lambda a: [a.apply(i).name() for i in range(a.size())])(disk.getAllBlocks().toList()) if f.startswith("shuffle_")}
    before = files()
    assert g.store(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()).count() == 7
    assert len({f.split("_")[1] for f in files() - before}) <= 1  # the count above has its own


def test_scores_by_a_function_are_made_once_a_group(spark):
    """Ranks by a function equal those by products, and test pairs of one group share its scores."""
    r = np.random.default_rng(3)
    vec = lambda n: r.normal(size=(n, 3)).tolist()
    items = spark.createDataFrame([(i, v) for i, v in enumerate(vec(300))], "id long, vec array<double>")
    groups = spark.createDataFrame([(f"g{i}", v) for i, v in enumerate(vec(150))], "group_key string, vec array<double>")
    pairs = [(f"g{i}", (7 * i + k) % 300) for i in range(150) for k in (0, 5, 90)]
    truth, seen = (spark.createDataFrame(x, "group_key string, item_id long") for x in (pairs, [(g, (i * 3) % 300) for g, i in pairs]))
    scored = spark.sparkContext.accumulator(0)

    def score(g, v):
        if len(v) > 1:
            scored.add(len(g))
        return g @ v.T

    got = {tuple(x) for x in rk.truth_rank_blocks(truth, groups, items, seen=seen, score=score).collect()}
    assert got == {tuple(x) for x in rk.truth_rank_blocks(truth, groups, items, seen=seen).collect()} and len(got) == 450
    assert scored.value == 150


def test_split_sorts_only_days_that_a_cut_falls_into(spark):
    """The exact split equals that of a sort of all rows; whole days are split without a window."""
    from crowdrank.operators import evaluate as ev

    r = np.random.default_rng(5)
    rows = [(f"g{i}", int(i % 7), int(x)) for i, x in enumerate(r.integers(0, 20 * 86400, 400))]
    gv = spark.createDataFrame(rows, "group_key string, item_id long, s long").select("group_key", "item_id", F.timestamp_seconds("s").alias("ts"))
    order = sorted(rows, key=lambda x: (x[2], x[0], x[1]))
    want = {x[0]: "test" if i >= 320 else "valid" if i >= 288 else "train" for i, x in enumerate(order)}
    got = ev.time_split(gv, exact=True)
    assert {x["group_key"]: x["split"] for x in got.collect()} == want and got.columns == [*gv.columns, "split"]
    assert "Range" not in (plan := got._jdf.queryExecution().optimizedPlan().toString()) and plan.count("Window [") <= 2
    assert all("Filter" in part.split("Window [")[0] for part in plan.split("Window [")[1:])


def test_ranked_teams_need_the_join_of_lines_and_orders_once(spark, tmp_path):
    """Edges, items and popularity come from one table of orders: those of the workload."""
    from crowdrank.plans import model_queries as mq
    from crowdrank.sources.workloads import teams

    d = "/root/testdata/sf0.001"
    w, full = mq.RankedTeams(spark, d), teams(spark, d)
    pairs = lambda df, *c: sorted(map(tuple, df.select(*c).collect()))
    assert pairs(w.gv, "group_key", "item_id", "ts") == pairs(full.gv, "group_key", "item_id", "ts")
    total = lambda df: df.groupBy("item_id").agg(F.sum("w").alias("w"))
    assert pairs(total(w.bought), "item_id", "w") == pairs(total(full.uv), "item_id", "w")
    keys = w.test.select("group_key").distinct()
    assert pairs(w.members(), "group_key", "user_id") == pairs(full.membership.join(keys, "group_key", "left_semi"), "group_key", "user_id")
