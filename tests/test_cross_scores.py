"""Scores of all groups and items: products of vectors, block by block."""

import duckdb

import __spark_entry__
from crowdrank.operators import rank as rk

DIR = "/root/testdata/sf0.01"


def test_all_groups_meet_all_items(spark, monkeypatch):
    """The entry scored keys of nations and regions by a formula; it has to multiply group and item vectors."""
    monkeypatch.setattr(rk, "CROSS_GROUPS", 16, raising=False)
    monkeypatch.setattr(rk, "CROSS_ITEMS", 32, raising=False)
    df = __spark_entry__.queries()["join_cross_scores"](spark, DIR)
    assert df.columns == ["group_key", "item_id", "score"]
    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM '{DIR}/events.parquet'")
    want = db.execute(__spark_entry__.oracle_sql()["join_cross_scores"]).fetchall()
    got = [tuple(r) for r in df.select("group_key", "item_id", "score").collect()]
    assert sorted(map(str, got)) == sorted(map(str, want))
    assert len(got) == len({r[0] for r in got}) * len({r[1] for r in got}) > 7000
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Broadcast" not in plan[plan.index("CartesianProduct") :]


def test_products_of_odd_vectors(spark, monkeypatch):
    monkeypatch.setattr(rk, "CROSS_ITEMS", 2)
    groups = spark.createDataFrame([("1-2", [1.0, 2.0]), ("3-4", [0.0, 0.0]), ("5-6", None)], "group_key string, vec array<double>")
    items = spark.createDataFrame([(7, [3.0, 4.0]), (8, [-1.0, 0.5]), (9, [0.0, 1.0]), (None, [1.0, 1.0]), (11, None)], "id long, vec array<double>")
    got = {(r["group_key"], r["item_id"]): r["score"] for r in rk.cross_scores(groups, items).collect()}
    assert len(got) == 15 and all(got["5-6", i] is None for i in (7, 8, 9, None, 11)) and got["1-2", 11] is None
    assert [got["1-2", i] for i in (7, 8, 9, None)] == [11.0, 0.0, 2.0, 3.0] and got["3-4", 7] == 0.0
    assert rk.cross_scores(groups.limit(0), items).count() == rk.cross_scores(groups, items.limit(0)).count() == 0
