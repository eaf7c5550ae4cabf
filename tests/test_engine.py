"""Operators on hand-made inputs, SQL twins on the smallest tables, and plan shapes."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from crowdrank.operators import evaluate as ev
from crowdrank.operators import graph as g
from crowdrank.operators import rank as rk
from crowdrank.operators import sampling as sm

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events embeddings".split()
TWINS = (
    "uv_edges_w2 groups_w1 stats_w2 cold_groups pagerank_10 betweenness_small noise_group_aware noise_report multi_head attentive_pool "
    "convolve_mean exact_loss group_ns_loss user_ns_loss joint_loss negatives_drawn negatives_unobserved sgd_step truth_rank rank_static "
    "paired_test planted_records join_asof_popularity join_range_mass agg_cube window_range_days fn_array stream_session_groups stream_late_rows"
).split()


@pytest.mark.parametrize("name", TWINS)
def test_twin(spark, name):
    df = __spark_entry__.queries()[name](spark, DIR)
    cols = sorted(df.columns)
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    cur = con.execute(__spark_entry__.oracle_sql()[name])
    at = [[c[0] for c in cur.description].index(c) for c in cols]
    want = sorted(str(tuple(r[i] for i in at)) for r in cur.fetchall())
    assert sorted(str(tuple(r)) for r in df.select(*cols).collect()) == want


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 0


def ties(spark, pairs):
    return g.symmetrise(spark.createDataFrame(pairs, "src long, dst long"))


def test_group_modes(spark):
    log = spark.createDataFrame([(1, 9), (2, 9), (3, 9), (4, 9)], "user_id long, item_id long").withColumn("ts", F.timestamp_seconds(F.lit(0))).withColumn("b", F.lit(0))
    uu = ties(spark, [(1, 2), (2, 3)])
    cell = [F.col("item_id"), F.col("b").alias("bucket")]
    keys = lambda mode: {r[0] for r in g.mine_groups(log, uu, cell, mode=mode).select("group_key").collect()}
    assert keys("component") == {"1-2-3"}
    assert keys("clique") == keys("pairwise") == {"1-2", "2-3"}


def test_centralities_on_a_path_and_a_cycle(spark):
    path, cycle = ties(spark, [(1, 2), (2, 3)]), ties(spark, [(1, 2), (2, 3), (3, 4), (4, 1)])
    score = lambda df: {r["user_id"]: round(r["score"], 6) for r in df.collect()}
    assert score(g.centrality_betweenness(path)) == {1: 0.0, 2: 1.0, 3: 0.0}
    assert set(score(g.centrality_pagerank(cycle)).values()) == {0.25}
    assert score(g.centrality_closeness(path))[2] == 1.0


def test_ranked_neighbours_break_ties_by_id(spark):
    uu = ties(spark, [(0, 1), (0, 2), (0, 3)])
    scores = spark.createDataFrame([(0, 1.0), (1, 5.0), (2, 5.0), (3, 3.0)], "user_id long, score double")
    assert [r["nbr"] for r in g.top_neighbours(uu, scores, 2).filter("user_id = 0").orderBy("rnk").collect()] == [1, 2]


def test_noise(spark):
    edges = spark.createDataFrame([(1, 1.0), (2, 16.0), (3, 81.0)], "item_id long, w double")
    assert [round(r["p"] * 36, 6) for r in sm.degree_noise(edges).orderBy("item_id").collect()] == [1, 8, 27]
    uv = spark.createDataFrame([(1, 10, 15.0), (1, 11, 80.0), (2, 12, 1.0), (2, 13, 1.0), (2, 14, 1.0)], "user_id long, item_id long, w double")
    m = spark.createDataFrame([("g", 1)], "group_key string, user_id long")
    assert [round(r["p"] * 38, 6) for r in sm.group_aware_noise(m, uv, 1.0).orderBy("item_id").collect()] == [8, 27]


def test_measures(spark):
    ranks = spark.createDataFrame([("a", 1, 1), ("b", 1, 2), ("c", 1, 4)], "group_key string, item_id long, rnk long")
    assert [round(r["hits"], 6) for r in ev.hits(ranks).orderBy("n").collect()][:2] == [round(1 / 3, 6), 1.0]
    assert round(ev.mrr(ranks).first()["mrr"], 9) == round(7 / 12, 9)
    assert ev.plateau([(1, 0.1), (2, 0.5), (3, 0.5)]) == 2


def test_static_strategies(spark):
    users = spark.createDataFrame([(1, [1.0, 5.0]), (2, [3.0, 2.0])], "id long, vec array<double>")  # scores of items x, y
    items = spark.createDataFrame([(7, [1.0, 0.0]), (8, [0.0, 1.0])], "id long, vec array<double>")
    m = spark.createDataFrame([("g", 1), ("g", 2)], "group_key string, user_id long")
    got = {how: {r["item_id"]: r["score"] for r in rk.static_rank(m, users, items, how).collect()} for how in ("avg", "min", "max")}
    assert got == {"avg": {7: 2.0, 8: 3.5}, "min": {7: 1.0, 8: 2.0}, "max": {7: 3.0, 8: 5.0}}


def test_empty_inputs(spark):
    none = spark.createDataFrame([], "src long, dst long")
    assert g.centrality_pagerank(none).count() == 0 and g.centrality_betweenness(none).count() == 0
    log = spark.createDataFrame([], "user_id long, item_id long, ts timestamp")
    assert g.build_uv(log).count() == 0


def test_scans_are_pruned_and_filtered(spark):
    plan = __spark_entry__.queries()["scan_projected"](spark, DIR)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_orderdate)" in plan and "o_totalprice" not in plan
    plan = __spark_entry__.queries()["join_bucketed"](spark, DIR)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan


def test_synthetic_graph_grows_with_a_given_table(spark):
    df = __spark_entry__.queries()["synthetic_graph"](spark, DIR)
    assert "orders.parquet" in df._jdf.queryExecution().executedPlan().toString() and df.count() == spark.read.parquet(f"{DIR}/orders.parquet").count()
