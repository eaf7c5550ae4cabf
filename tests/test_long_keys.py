"""Groups of many members: what a kernel sees at once, and what their keys cost."""

from pyspark.sql import functions as F

from crowdrank.operators import represent as rp
from crowdrank.operators import sampling as sm


def test_a_kernel_sees_few_large_groups_at_once(spark):
    vectors = spark.range(40).select("id", F.array(F.col("id").cast("double")).alias("vec"))
    members = spark.range(40).select("id", F.explode(F.sequence(F.lit(1), F.lit(6))).alias("g")).select(F.concat(F.lit("g"), "g").alias("group_key"), F.col("id").alias("user_id"))
    groups = rp.gather(members.union(members), vectors).coalesce(1)
    seen = rp.transform(groups, lambda x, m: [[float(len(m))] * len(m)], 1, out="n double", pairs=3200, keep="members").collect()
    assert len(seen) == 6 and all(r["n"] == 2 and r["members"] == list(range(40)) for r in seen)
    assert [r["vec"] for r in rp.mean_vectors(members, vectors, 1).collect()] == [[19.5]] * 6


def test_noise_is_added_up_in_shares(spark, monkeypatch):
    monkeypatch.setattr(sm, "MEMBER_ROWS", 2)
    members = spark.createDataFrame([("a-b", 1), ("a-b", 2), ("b-c", 2), ("b-c", 3), ("d", 4)], "group_key string, user_id long")
    uv = spark.createDataFrame([(1, 7, 1.0), (2, 7, 2.0), (2, 8, 1.0), (3, 9, 4.0)], "user_id long, item_id long, w double")
    got = sm.group_aware_noise(members, uv)
    assert sorted((r["group_key"], r["item_id"], r["pop"], r["touched"]) for r in got.collect()) == [("a-b", 7, 3.0, 2), ("a-b", 8, 1.0, 2), ("b-c", 7, 2.0, 3), ("b-c", 8, 1.0, 3), ("b-c", 9, 4.0, 3)]
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan  # no row a member and item passes a shuffle
