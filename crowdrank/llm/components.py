"""Connected components of an edge table by label minima and shortcuts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import cut


def star(rows: DataFrame, node: str, lead: str) -> DataFrame:
    """Few edges ``a, b`` that connect what the rows ``node, lead`` connect.

    A node that several leads claim keeps one edge, to its smallest lead; what the leads have in
    common is said once for each pair of a lead and a smallest lead, not once a node.
    """
    own = rows.groupBy(F.col(node).alias("n")).agg(F.min(lead).alias("b"), F.collect_set(lead).alias("leads"))
    ends = F.explode(F.array_union(F.array("n"), F.array_except("leads", F.array("b"))))
    return own.select(ends.alias("a"), "b").filter("a <> b").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 100) -> DataFrame:
    """``id, root`` for each node of an undirected edge table; ``root`` is the smallest id reached.

    In every round a node takes the smallest label of its neighbours and then the label of that
    label, which shortens chains by doubling; the labels are written to the shared folder once a
    round. Minima are aggregated partially before they are shuffled and labels are joined from a
    stored table, so a hub neither gathers its neighbours in a task nor blocks a join.
    """
    one = edges.select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a <> b")
    both = cut(one.union(one.select("b", "a")).distinct(), thin=True)
    now = cut(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("root")), thin=True)
    for _ in range(rounds):
        low = both.join(now.withColumnRenamed("id", "b"), "b").groupBy("a").agg(F.min("root").alias("m"))
        new = now.join(low.withColumnRenamed("a", "id"), "id").select("id", F.least("root", "m").alias("near"), F.col("root").alias("was"))
        jump = now.select(F.col("id").alias("near"), F.col("root").alias("far"))
        new = cut(new.join(jump, "near").select("id", F.least("near", "far").alias("root"), "was"), thin=True)
        if not new.filter("root <> was").limit(1).count():
            return new.select("id", "root")
        now = new.select("id", "root")
    raise RuntimeError("labels did not settle")
