"""Vectors of groups and users as Arrow kernels over gathered members, and objectives as joins."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdrank.functions.tape import Var


def dot(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def sigmoid(x: Column) -> Column:
    """Stable for either sign."""
    e = F.exp(-F.abs(x))
    return F.when(x >= 0, 1 / (1 + e)).otherwise(e / (1 + e))


def log_sigmoid(x: Column) -> Column:
    return -(F.greatest(-x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x))))


def digest(key: str) -> Column:
    """16 bytes for a key: keys of groups list their members, so they are too long to travel with each."""
    return F.unhex(F.md5(F.col(key)))


def gather(membership: DataFrame, vectors: DataFrame, key: str = "group_key", member: str = "user_id") -> DataFrame:
    """``key, members, vecs``: members in id order; members without a vector are left out."""
    rows = membership.select(digest(key).alias("_k"), F.col(member).alias("m")).join(vectors.select(F.col("id").alias("m"), "vec"), "m")
    sets = rows.groupBy("_k").agg(F.array_sort(F.collect_set(F.struct("m", "vec"))).alias("s"))
    keys = membership.select(key).distinct().withColumn("_k", digest(key))
    return keys.join(sets.toDF(*sets.columns), "_k").select(key, F.col("s.m").alias("members"), F.col("s.vec").alias("vecs"))


def mean_vectors(membership: DataFrame, vectors: DataFrame, d: int) -> DataFrame:
    """``group_key, vec``: the mean of the members' vectors, in id order."""
    mean = [F.aggregate("vecs", F.lit(0.0), lambda s, v: s + F.get(v, F.lit(k))) / F.size("vecs") for k in range(d)]  # noqa: B023
    return gather(membership, vectors).select("group_key", F.array(*mean).alias("vec"))


def padded(lists: list[list], d: int) -> tuple[np.ndarray, np.ndarray]:
    n = max([1, *map(len, lists)])
    x, mask = np.zeros((len(lists), n, d)), np.zeros((len(lists), n), bool)
    for i, rows in enumerate(lists):
        if rows:
            x[i, : len(rows)], mask[i, : len(rows)] = rows, True
    return x, mask


def transform(groups: DataFrame, kernel: Callable, d: int, key: str = "group_key", out: str = "vec array<double>", size: int = 512, pairs: int = 1 << 20, keep: str = "") -> DataFrame:
    """Apply ``kernel(x, mask) -> list of output columns`` to batches of gathered vectors.

    Batches are sorted by the number of members, so padding stays small, and have at most ``size``
    groups with about ``pairs`` pairs of members; parameters travel in the closure and do not grow with
    the data. ``keep``: a column of ``groups`` that goes along.
    """
    names = [c.split()[0] for c in out.split(", ")]
    kept = [key, keep] if keep else [key]

    def run(batches):
        for b in batches:
            n = np.array([len(v) for v in b.column("vecs")], np.int64)
            order, i = np.argsort(n, kind="stable"), 0
            while i < len(order):
                most = n[order[i : i + size]] ** 2 * np.arange(1, len(order[i : i + size]) + 1)
                j = i + max(1, int(np.searchsorted(most, pairs, side="right")))
                part = b.take(pa.array(order[i:j]))
                x, mask = padded(part.column("vecs").to_pylist(), d)
                cols = kernel(Var(x), mask)
                yield pa.RecordBatch.from_arrays([*[part.column(k) for k in kept], *[pa.array(list(c)) for c in cols]], [*kept, *names])
                i = j

    return groups.select(*kept, "vecs").mapInArrow(run, ", ".join([*[f"{k} {groups.schema[k].dataType.simpleString()}" for k in kept], out]))


def exploded(df: DataFrame, key: str = "group_key", digits: int = 6) -> DataFrame:
    """``key, k, x``, rounded."""
    return df.select(key, F.posexplode("vec").alias("k", "x")).withColumn("x", F.round("x", digits) + F.lit(0.0))


def weighted_sum(membership: DataFrame, weights: DataFrame, vectors: DataFrame) -> DataFrame:
    """Group vectors as sums of member vectors with given ``weight`` by (group, user)."""
    rows = membership.join(weights, ["group_key", "user_id"]).join(vectors.withColumnRenamed("id", "user_id"), "user_id")
    flat = rows.select("group_key", "weight", F.posexplode("vec").alias("k", "x")).groupBy("group_key", "k").agg(F.sum(F.col("weight") * F.col("x")).alias("x"))
    return flat.groupBy("group_key").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "x"))), lambda s: s["x"]).alias("vec"))


def influence_weights(membership: DataFrame, influence: DataFrame) -> DataFrame:
    """Softmax within each group of one global number a user, by two partial aggregates."""
    rows = membership.join(influence, "user_id")
    top = rows.groupBy("group_key").agg(F.max("influence").alias("top"))
    e = rows.join(top, "group_key").withColumn("e", F.exp(F.col("influence") - F.col("top")))
    total = e.groupBy("group_key").agg(F.sum("e").alias("total"))
    return e.join(total, "group_key").select("group_key", "user_id", (F.col("e") / F.col("total")).alias("weight"))


# --- objectives


def interaction_logs(left: DataFrame, items: DataFrame) -> DataFrame:
    """``left, lse``: log of the softmax denominator over all items, by a blocked product.

    Items meet left vectors block by block; each block contributes its own log-sum-exp.
    """

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({"id": pa.array([], pa.int64()), "top": pa.array([], pa.float64()), "s": pa.array([], pa.float64())})
        s = np.array(a["vec"].to_pylist()) @ np.array(b["vec"].to_pylist()).T
        top = s.max(1)
        return pa.table({"id": a["id"], "top": top, "s": np.exp(s - top[:, None]).sum(1)})

    x, y = blocked(left, items)
    parts = x.groupBy("lb", "rb").cogroup(y.groupBy("lb", "rb")).applyInArrow(run, "id long, top double, s double")
    best = parts.groupBy("id").agg(F.max("top").alias("best"))
    return parts.join(best, "id").groupBy("id").agg((F.first("best") + F.log(F.sum(F.col("s") * F.exp(F.col("top") - F.col("best"))))).alias("lse"))


def blocked(left: DataFrame, right: DataFrame, left_rows: int = 4096, right_rows: int = 8192, key: str = "id", rkey: str = "id") -> tuple[DataFrame, DataFrame]:
    """Both sides dealt to blocks, each replicated to the blocks of the other side."""
    nl, nr = max(1, -(-left.count() // left_rows)), max(1, -(-right.count() // right_rows))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    x = left.withColumn("lb", F.pmod(F.xxhash64(key), F.lit(nl)).cast("int")).withColumn("rb", every(nr))
    y = right.withColumn("rb", F.pmod(F.xxhash64(rkey), F.lit(nr)).cast("int")).withColumn("lb", every(nl))
    return x.toDF(*x.columns), y.toDF(*y.columns)  # fresh columns, so both sides may share a source


def exact_loss(edges: DataFrame, left: DataFrame, items: DataFrame) -> DataFrame:
    """Weighted negative log softmax over edges ``(left, item_id, w)``."""
    e = edges.join(left.select(F.col("id").alias("left"), F.col("vec").alias("l")), "left").join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("v")), "item_id")
    e = e.join(interaction_logs(left, items).withColumnRenamed("id", "left"), "left")
    loss = F.col("w") * (F.col("lse") - dot("l", "v"))
    return e.agg(F.sum(loss).alias("loss_sum"), F.avg(loss).alias("loss_mean"), F.count("*").alias("n"))


def empirical_prob(edges: DataFrame, left: str) -> DataFrame:
    total = edges.groupBy(left).agg(F.sum("w").alias("d"))
    return edges.join(total, left).select(left, "item_id", (F.col("w") / F.col("d")).alias("p"))


def kl_gap(edges: DataFrame, left: DataFrame, items: DataFrame) -> DataFrame:
    """Degree-weighted divergence of the model from the edges, and its distance to the exact loss."""
    p = empirical_prob(edges, "left").join(edges.groupBy("left").agg(F.sum("w").alias("d")), "left")
    q = p.join(left.select(F.col("id").alias("left"), F.col("vec").alias("l")), "left").join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("v")), "item_id").join(interaction_logs(left, items).withColumnRenamed("id", "left"), "left")
    log_q = dot("l", "v") - F.col("lse")
    return q.agg(F.sum(F.col("d") * F.col("p") * (F.log("p") - log_q)).alias("kl"), F.sum(F.col("d") * F.col("p") * F.log("p")).alias("constant"), F.sum(-F.col("d") * F.col("p") * log_q).alias("loss"))


def sampled_scores(samples: DataFrame, left: DataFrame, items: DataFrame) -> DataFrame:
    """Samples ``(left, item_id, y)`` with both vectors and the error of their score."""
    s = samples.join(left.select(F.col("id").alias("left"), F.col("vec").alias("l")), "left").join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("v")), "item_id")
    return s.withColumn("s", dot("l", "v")).withColumn("e", sigmoid(F.col("s")) - F.col("y"))


def ns_loss(samples: DataFrame, left: DataFrame, items: DataFrame) -> DataFrame:
    s = sampled_scores(samples, left, items)
    loss = -log_sigmoid(F.when(F.col("y") == 1, F.col("s")).otherwise(-F.col("s")))
    return s.agg(F.sum(loss).alias("loss_sum"), F.avg(loss).alias("loss_mean"), F.count("*").alias("n"))


def sgd_step(samples: DataFrame, left: DataFrame, items: DataFrame, lr: float) -> tuple[DataFrame, DataFrame]:
    """One synchronous step: gradients are summed by id and component, then both tables move."""
    s = sampled_scores(samples, left, items)

    def move(table: DataFrame, key: str, other: str) -> DataFrame:
        grad = s.select(F.col(key).alias("id"), "e", F.posexplode(other).alias("k", "o")).groupBy("id", "k").agg(F.sum(F.col("e") * F.col("o")).alias("g"))
        grad = grad.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "g"))), lambda x: x["g"]).alias("g"))
        new = F.when(F.col("g").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "g", lambda x, g: x - lr * g))
        return table.join(grad, "id", "left").select("id", new.alias("vec"))

    return move(left, "left", "v"), move(items, "item_id", "l")
