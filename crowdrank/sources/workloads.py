"""Readers and the three input graphs of the experiments on the given tables.

Every builder returns plain edge tables: ``uv(user_id, item_id, w, ts)`` and
``records(group_key, members, item_id, ts)``; ``uu(src, dst)`` is symmetric without loops. A group is
its sorted member set; ``group_key`` is the member ids joined by ``-`` and ``group_id`` its hash.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowdrank.operators import graph


Graph = DataFrame | Callable[[], DataFrame]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Workload:
    """Graphs of one experiment, each built when it is first asked for.

    Groups are mined by a loop over stored tables, so nobody who wants edges alone should pay for it.
    ``shared``: a log and its context, if a tie is one shared context; degrees and ranked neighbours
    are then counted from it, as the ties of large contexts are too many to list.
    """

    def __init__(self, uv: Graph, uu: Graph, records: Graph, shared: tuple[DataFrame, graph.Cols] | None = None) -> None:
        self._uv, self._uu, self._records, self._shared = uv, uu, records, shared

    @cached_property
    def uv(self) -> DataFrame:
        return _built(self._uv)

    @cached_property
    def uu(self) -> DataFrame:
        return _built(self._uu)

    @cached_property
    def records(self) -> DataFrame:
        return _built(self._records)

    @cached_property
    def contexts(self) -> DataFrame | None:
        return graph.shared_contexts(*self._shared) if self._shared else None

    @cached_property
    def degree(self) -> DataFrame:
        """Ties of each user."""
        return graph.centrality_degree(self.uu) if self.contexts is None else graph.store(graph.context_degrees(self.contexts))

    def near(self, k: int = 4) -> DataFrame:
        """Each user's ``k`` neighbours with the most ties."""
        return graph.top_neighbours(self.uu, self.degree, k) if self.contexts is None else graph.context_neighbours(self.contexts, self.degree, k)

    @property
    def gv(self) -> DataFrame:
        return graph.group_items(self.records)

    @property
    def membership(self) -> DataFrame:
        return graph.membership(self.records)


def _built(graph: Graph) -> DataFrame:
    return graph() if callable(graph) else graph


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a line: customer, part, supplier, ship date, order, order date."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def touches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event log with the item taken from the JSON property."""
    e = read(spark, sf_dir, "events")
    return e.select("user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id"), "event_type", "ts")


def crowds(spark: SparkSession, sf_dir: str) -> Workload:
    """W1: customers and parts; ties share a supplier in a week, groups share a part in a quarter."""
    log = purchases(spark, sf_dir).select(F.col("o_custkey").alias("user_id"), F.col("l_partkey").alias("item_id"), F.col("l_suppkey").alias("place"), F.col("l_shipdate").alias("ts"))
    uu = graph.derive_ties(log, ["place", F.date_trunc("week", "ts").alias("week")])
    return Workload(graph.build_uv(log), uu, lambda: graph.mine_groups(log, uu, [F.col("item_id"), F.date_trunc("quarter", "ts").alias("bucket")]))


def team_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = purchases(spark, sf_dir)
    return lines.select(F.col("l_suppkey").alias("user_id"), F.col("o_custkey").alias("item_id"), F.col("o_orderdate").alias("ts"), F.col("o_orderkey").alias("key"))


def teams(spark: SparkSession, sf_dir: str) -> Workload:
    """W2: suppliers and customers; a team is the suppliers of an order, ties share a nation."""
    log = team_log(spark, sf_dir)
    nation = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("user_id"), F.col("s_nationkey").alias("place"))
    return Workload(graph.build_uv(log), graph.derive_ties(nation, ["place"]), graph.explicit_groups(log, "key"))


def gatherings(spark: SparkSession, sf_dir: str, mode: str = "component") -> Workload:
    """W3: event users and items; ties share a kind of event in five minutes, groups an item in an hour."""
    log = touches(spark, sf_dir)
    five = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 300_000_000).alias("five")
    context = ["event_type", five]
    uu = graph.derive_ties(log, context)
    cell = [F.col("item_id"), F.date_trunc("hour", "ts").alias("bucket")]
    return Workload(graph.build_uv(log), uu, lambda: graph.mine_groups(log, uu, cell, mode=mode, context=context), (log, context))


WORKLOADS = {"w1": crowds, "w2": teams, "w3": gatherings}


def planted(spark: SparkSession, sf_dir: str, anchors_per_user: int = 4) -> Workload:
    """W4: users and items with known vectors, so that accuracy can be compared.

    Even ids are users and odd ids items, on the first 8 coordinates. A user's edges are the 12 best
    items; ties are the 8 nearest users. Every user anchors four groups of 3 to 6 near users, whose
    item is the best one for the members weighted by how often each is a neighbour.
    """
    from crowdrank.operators import rank, represent

    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.slice("embedding", 1, 8).cast("array<double>").alias("x"))
    v = graph.store(v.withColumn("n", F.sqrt(represent.dot("x", "x"))).select("id", F.transform("x", lambda c: c / F.col("n")).alias("vec")))
    users, items = v.filter("id % 2 = 0"), v.filter("id % 2 = 1")
    keyed = users.select(F.col("id").cast("string").alias("group_key"), "vec")
    uv = rank.topn(keyed, items, 12).select(F.col("group_key").cast("long").alias("user_id"), "item_id", F.lit(1.0).alias("w"), F.timestamp_seconds(F.lit(0)).alias("ts"))
    own = keyed.select("group_key", F.col("group_key").cast("long").alias("item_id"))
    near = graph.store(rank.topn(keyed, users, 8, seen=own).select(F.col("group_key").cast("long").alias("src"), (F.col("rnk") - 1).alias("at"), F.col("item_id").alias("dst")))
    uu = graph.symmetrise(near.select("src", "dst"))
    count = near.groupBy(F.col("dst").alias("user_id")).agg(F.count("*").alias("k"))
    a = users.select(F.col("id").alias("anchor"), (F.col("id") / 2).cast("long").alias("a")).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(anchors_per_user - 1))))
    a = a.withColumn("m", 2 + (F.col("a") + F.col("rep")) % 4).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("m").cast("int") - 1)))
    a = a.withColumn("at", F.pmod(F.col("j") - 2 * F.col("rep"), F.lit(8)).cast("int"))
    rows = a.join(near.withColumnRenamed("src", "anchor"), ["anchor", "at"]).groupBy("anchor", "a", "rep").agg(F.array_sort(F.array_distinct(F.concat(F.array("anchor"), F.collect_list("dst")))).alias("members"))
    rows = graph.store(rows.withColumn("ts", F.timestamp_seconds(F.pmod(7919 * F.col("a") + 104729 * F.col("rep"), F.lit(1000003)))))
    each = rows.select("anchor", "rep", F.explode("members").alias("user_id")).join(count, "user_id", "left").select(F.concat_ws(":", "anchor", "rep").alias("group_key"), "user_id", (F.coalesce("k", F.lit(0)) / 3.0).alias("influence"))
    weights = represent.influence_weights(each.select("group_key", "user_id"), each.select("user_id", "influence").distinct())
    best = rank.topn(represent.weighted_sum(each.select("group_key", "user_id"), weights, users), items, 1)
    records = rows.withColumn("k", F.concat_ws(":", "anchor", "rep")).join(best.select(F.col("group_key").alias("k"), "item_id"), "k")
    return Workload(graph.store(uv), graph.store(uu), graph.store(records.select(graph.group_key(F.col("members")).alias("group_key"), "members", "item_id", "ts")))
