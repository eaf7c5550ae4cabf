"""Graphs of large diameter: nothing ends before the far end is reached."""

import pytest

from crowdrank.operators import graph as g
from tests.test_engine import ties


def test_distances_do_not_end_silently(spark):
    path = ties(spark, [(i, i + 1) for i in range(6)])
    ends = path.select("src").filter("src = 0").distinct().withColumnRenamed("src", "user_id")
    assert {r["node"]: r["dist"] for r in g.distances(path, ends).collect()} == {i: i for i in range(7)}
    with pytest.raises(RuntimeError):
        g.distances(path, ends, limit=2)


def test_closeness_sketch_reaches_the_far_end(spark):
    score = {r["user_id"]: r["score"] for r in g.centrality_closeness_sketch(ties(spark, [(i, i + 1) for i in range(6)])).collect()}
    assert abs(score[0] - sum(1 / h for h in range(1, 7))) < 0.01
