"""Groups, degrees and ranked neighbours from shared contexts, against listed ties."""

import random

from pyspark.sql import functions as F

from crowdrank.operators import graph as g


def log_of(spark):
    """Users with copies that share all their contexts, lone users, nulls and users of one context."""
    r = random.Random(5)
    rows = [(u + 100 * copy, u % 7 and item, place, t) for u in range(30) for item, place, t in [(r.randrange(4), r.randrange(9), r.randrange(40)) for _ in range(3)] for copy in range(3)]
    rows += [(900, 1, None, 3), (901, 1, None, 3), (None, 1, 2, 3), (902, None, 2, 3), (903, 2, 77, 4)]
    return spark.createDataFrame(rows, "user_id long, item_id long, place long, t long").withColumn("ts", F.timestamp_seconds("t")).withColumn("b", (F.col("t") / 20).cast("long"))


def test_groups_without_listed_ties(spark, monkeypatch):
    monkeypatch.setattr(g, "CELL_ROWS", 16)
    log = log_of(spark)
    uu, cell = g.store(g.derive_ties(log, ["place"])), [F.col("item_id"), F.col("b").alias("bucket")]
    rows = lambda df: sorted(map(str, df.select("group_key", "members", "item_id", "ts").collect()))
    for mode in ("component", "clique"):
        want = rows(g.mine_groups(log, uu, cell, mode=mode))
        assert want and rows(g.mine_groups(log, None, cell, mode=mode, context=["place"])) == want


def test_degrees_and_neighbours_without_listed_ties(spark, monkeypatch):
    monkeypatch.setattr(g, "TIE_BLOCK", 16)
    log = log_of(spark)
    uu, lists = g.store(g.derive_ties(log, ["place"])), g.shared_contexts(log, ["place"])
    rows = lambda df: sorted(map(str, df.collect()))
    degree = g.store(g.context_degrees(lists))
    assert rows(degree) == rows(g.centrality_degree(uu))
    cols = ["user_id", "rnk", "nbr", "score"]
    assert rows(g.context_neighbours(lists, degree, 3).select(*cols)) == rows(g.top_neighbours(uu, degree, 3).select(*cols))


def test_lists_travel_as_few_bytes(spark):
    """Gaps of context numbers take a byte or two; the numbers themselves took eight and had gaps of their own."""
    import pyarrow as pa

    lists = [[], [0], [5, 6, 300, 70_000, 1 << 40], [], [1, 2, 3], list(range(0, 60_000, 600))]
    df = spark.createDataFrame(list(enumerate(lists)), "user_id long, at array<long>").repartition(3)
    rows = g.packed_lists(df).collect()
    half = len(rows) // 2
    at = pa.chunked_array([pa.array([bytes(r["at"]) for r in part], pa.binary()) for part in (rows[:half], [], rows[half:])])
    cuts, flat = g.unpacked_lists(at)
    assert [flat[a:b].tolist() for a, b in zip(cuts[:-1], cuts[1:], strict=True)] == [lists[r["user_id"]] for r in rows]
    cuts, flat = g.unpacked_lists(at[2:5])
    assert [flat[a:b].tolist() for a, b in zip(cuts[:-1], cuts[1:], strict=True)] == [lists[r["user_id"]] for r in rows[2:5]]
    assert {r["user_id"]: len(r["at"]) for r in rows} == {0: 0, 1: 1, 2: 13, 3: 0, 4: 3, 5: 199}
    log = log_of(spark).repartition(7)
    numbers = {k for r in g.shared_contexts(log, ["place"]).collect() for k in r["at"]}
    assert max(numbers) <= len(numbers)  # the context without a place has a number too, but ties nobody
