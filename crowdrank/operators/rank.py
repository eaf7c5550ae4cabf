"""Scoring of groups against items: exact, bounded and approximate top lists, ranks of the truth."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.operators import graph
from crowdrank.operators.halfspace import TIE, count_above
from crowdrank.operators.represent import blocked, dot

#: Rows of a block of test pairs, numbers of a block of items, and pairs of a task, for counts by boxes; blocks
#: of test pairs, as long as their rows allow (items are copied to each).
TRUTH_ROWS, ITEM_NUMBERS, TASK_PAIRS, TRUTH_BLOCKS = 1 << 18, 1 << 23, 1 << 27, 8
#: Groups whose scores by a function are held at a time.
SCORED = 64
#: Groups of a task and items of a block, for scores of all pairs.
CROSS_GROUPS, CROSS_ITEMS = 4096, 1024


def scores(groups: DataFrame, items: DataFrame, pairs: DataFrame) -> DataFrame:
    """Scores of given (group, item) pairs: two equi-joins."""
    x = pairs.join(groups.select("group_key", F.col("vec").alias("g")), "group_key")
    return x.join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("v")), "item_id").select("group_key", "item_id", dot("g", "v").alias("score"))


def cross_scores(groups: DataFrame, items: DataFrame) -> DataFrame:
    """Scores of every group and item: groups are crossed with blocks of items, neither side is broadcast.

    A row of the cross join is a group and a block, and a task has one share of groups and about one
    block, so tasks grow in number, not in size.
    """
    x = graph.store(groups.select("group_key", F.col("vec").alias("g")))
    y = graph.store(items.select(F.col("id").alias("item_id"), F.col("vec").alias("v")))
    shares, blocks = max(1, -(-x.count() // CROSS_GROUPS)), max(1, -(-y.count() // CROSS_ITEMS))
    y = y.groupBy(F.pmod(F.xxhash64("item_id"), F.lit(blocks)).alias("b")).agg(F.collect_list(F.struct("item_id", "v")).alias("block"))
    y = y.select("block").repartition(blocks).hint("shuffle_replicate_nl")
    pairs = x.repartition(shares).crossJoin(y).select("group_key", "g", F.inline("block"))
    return pairs.select("group_key", "item_id", dot("g", "v").alias("score"))


def _top(a: pa.Table, b: pa.Table, n: int) -> pa.Table:
    out = [[], [], []]
    if a.num_rows and b.num_rows:
        ids, v = b["id"].to_numpy(), np.array(b["vec"].to_pylist())
        s = np.array(a["vec"].to_pylist()) @ v.T
        place = {x: i for i, x in enumerate(ids.tolist())}
        for key, row, seen in zip(a["group_key"].to_pylist(), s, a["seen"].to_pylist(), strict=True):
            gone = [place[x] for x in seen or () if x in place]
            row[gone] = -np.inf
            keep = np.flatnonzero(row >= np.partition(row, max(0, len(row) - n))[max(0, len(row) - n)])
            keep = keep[row[keep] > -np.inf]
            keep = keep[np.lexsort((ids[keep], -row[keep]))][:n]
            out[0] += [key] * len(keep)
            out[1] += ids[keep].tolist()
            out[2] += row[keep].tolist()
    return pa.table({"group_key": pa.array(out[0], pa.string()), "item_id": pa.array(out[1], pa.int64()), "score": pa.array(out[2], pa.float64())})


def _ranked(parts: DataFrame, n: int) -> DataFrame:
    order = Window.partitionBy("group_key").orderBy(F.desc("score"), "item_id")
    return parts.withColumn("rnk", F.row_number().over(order)).filter(F.col("rnk") <= n).select("group_key", "rnk", "item_id", "score")


def with_seen(groups: DataFrame, seen: DataFrame | None) -> DataFrame:
    if seen is None:
        return groups.select("group_key", "vec", F.array().cast("array<long>").alias("seen"))
    sets = seen.groupBy("group_key").agg(F.collect_set("item_id").alias("seen"))
    return groups.join(sets, "group_key", "left").select("group_key", "vec", "seen")


def topn(groups: DataFrame, items: DataFrame, n: int = 10, seen: DataFrame | None = None) -> DataFrame:
    """The ``n`` best items of each group not in ``seen``: block products, then a merge of short lists."""
    x, y = blocked(with_seen(groups, seen), items, key="group_key")
    parts = x.groupBy("lb", "rb").cogroup(y.groupBy("lb", "rb")).applyInArrow(lambda a, b: _top(a, b, n), "group_key string, item_id long, score double")
    return _ranked(parts, n)


def topn_bounded(groups: DataFrame, items: DataFrame, n: int = 10, block: int = 256) -> DataFrame:
    """Exact top list that skips item blocks which cannot reach it.

    Items are cut into blocks by falling norm. The first block gives each group an ``n``-th score; a
    later block is visited only if the group's norm times the block's largest norm can beat it, so
    each group visits a prefix of the blocks.
    """
    norm = F.sqrt(dot("vec", "vec"))
    total = items.count()
    blocks = max(1, -(-total // block))
    cuts = items.select(norm.alias("nn")).agg(F.percentile_approx("nn", [1 - (i + 1) / blocks for i in range(blocks - 1)] or [0.0], 10_000).alias("c")).first()["c"] or []
    number = F.lit(0)
    for c in cuts[: blocks - 1]:
        number = number + (F.col("nn") < c).cast("int")
    ranked = items.withColumn("nn", norm).withColumn("rb", number)
    top = ranked.groupBy("rb").agg(F.max("nn").alias("top"))
    g = with_seen(groups, None).withColumn("gn", norm)

    def visit(x: DataFrame) -> DataFrame:
        x, y = x.toDF(*x.columns), ranked.toDF(*ranked.columns)
        return x.groupBy("rb").cogroup(y.groupBy("rb")).applyInArrow(lambda a, b: _top(a, b, n), "group_key string, item_id long, score double")

    first = visit(g.withColumn("rb", F.lit(0)))
    floor = first.groupBy("group_key").agg(F.when(F.count("*") >= n, F.min("score")).alias("floor"))
    rest = g.join(floor, "group_key", "left").join(F.broadcast(top.filter("rb > 0"))).filter("floor IS NULL OR gn * top >= floor")
    return _ranked(first.union(visit(rest)), n)


def topn_lsh(groups: DataFrame, items: DataFrame, n: int = 10, bucket: float = 1.0, tables: int = 8, radius: float = 3.0) -> DataFrame:
    """Approximate top list: inner product turned into distance by one more coordinate, then Spark's LSH."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    sq = dot("vec", "vec")
    top = items.agg(F.max(sq)).first()[0] or 0.0
    y = items.select(F.col("id").alias("item_id"), "vec", array_to_vector(F.concat("vec", F.array(F.sqrt(F.greatest(F.lit(0.0), top - sq))))).alias("f"))
    x = groups.select("group_key", "vec", array_to_vector(F.concat("vec", F.array(F.lit(0.0)))).alias("f"))
    model = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=5).fit(y)
    near = model.approxSimilarityJoin(x, y, radius)
    return _ranked(near.select(F.col("datasetA.group_key").alias("group_key"), F.col("datasetB.item_id").alias("item_id"), dot("datasetA.vec", "datasetB.vec").alias("score")), n)


def truth_rank_blocks(truth: DataFrame, groups: DataFrame, items: DataFrame, seen: DataFrame | None = None, score=None, ragged: bool = False) -> DataFrame:
    """``group_key, item_id, rnk, candidates`` from vectors: each item block counts what beats the truth.

    ``score``: a function of two matrices; the product of vectors if not given, which counts boxes of
    items at once. ``ragged``: groups are lists of different lengths, which only ``score`` understands.
    """
    if score is None:
        return _counted(truth, groups, items, seen)
    own = truth.select("group_key", "item_id").distinct().join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("own")), "item_id")
    left = with_seen(groups, seen).join(own, "group_key")
    x, y = blocked(left, items, key="group_key")

    def count(a: pa.Table, b: pa.Table) -> pa.Table:
        above = candidates = np.zeros(a.num_rows, np.int64)
        if a.num_rows and b.num_rows:
            ids, v = b["id"].to_numpy(), np.array(b["vec"].to_pylist())
            g, own = a["vec"].to_pylist(), np.array(a["own"].to_pylist())
            g = g if ragged else np.array(g)
            t, o = a["item_id"].to_numpy(), np.array([score(g[i : i + 1], own[i : i + 1])[0, 0] for i in range(len(g))])
            place = {q: i for i, q in enumerate(ids.tolist())}
            seen_items = a["seen"].to_pylist()
            above, candidates = np.zeros(a.num_rows, np.int64), np.zeros(a.num_rows, np.int64)
            # test pairs of one group share its scores
            code = a["group_key"].combine_chunks().dictionary_encode().indices.to_numpy()
            order = np.argsort(code, kind="stable")
            cuts = np.searchsorted(code[order], np.arange(0, code.max() + SCORED, SCORED))
            for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                rows = order[i:j]
                _, first, at = np.unique(code[rows], return_index=True, return_inverse=True)
                s = score([g[k] for k in rows[first]] if ragged else g[rows[first]], v)[at]
                ok = ids[None, :] != t[rows, None]
                for k, row in enumerate(rows.tolist()):
                    ok[k, [place[q] for q in seen_items[row] or () if q in place and q != t[row]]] = False
                d = s - o[rows, None]
                near = np.abs(d) <= TIE
                above[rows] = (ok & ((d > TIE) | near & (ids[None, :] < t[rows, None]))).sum(1)
                candidates[rows] = ok.sum(1)
        return pa.table({"group_key": a["group_key"], "item_id": a["item_id"], "above": pa.array(above, pa.int64()), "others": pa.array(candidates, pa.int64())})

    parts = x.groupBy("lb", "rb").cogroup(y.groupBy("lb", "rb")).applyInArrow(count, "group_key string, item_id long, above long, others long")
    return parts.groupBy("group_key", "item_id").agg((F.sum("above") + 1).alias("rnk"), (F.sum("others") + 1).alias("candidates"))


def _counted(truth: DataFrame, groups: DataFrame, items: DataFrame, seen: DataFrame | None) -> DataFrame:
    """Ranks by products: few large blocks of items, so that a test pair is copied to few of them."""
    items = graph.store(items.select("id", "vec"))
    pairs = graph.store(truth.select("group_key", "item_id").distinct())
    keys = pairs.select("group_key").distinct()
    left = with_seen(groups.join(keys, "group_key", "left_semi"), None if seen is None else seen.join(keys, "group_key", "left_semi"))
    own = pairs.join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("own")), "item_id")
    left = left.withColumn("seen", F.coalesce("seen", F.array().cast("array<long>")))
    left = graph.store(left.join(own, "group_key").withColumn("own", dot("vec", "own")))
    size = items.agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("d")).first()
    n, rows = size["n"], left.count()
    tasks = -(-rows * n // TASK_PAIRS)
    per = max(1024, min(TRUTH_ROWS, -(-rows // max(1, min(TRUTH_BLOCKS, tasks)))))
    x, y = blocked(left, items, left_rows=per, right_rows=max(8192, ITEM_NUMBERS // max(1, size["d"] or 1)), key="group_key")

    def count(a: pa.Table, b: pa.Table) -> pa.Table:
        above = candidates = np.zeros(a.num_rows, np.int64)
        if a.num_rows and b.num_rows:
            ids, t = b["id"].to_numpy(), a["item_id"].to_numpy()
            g, v = (x.combine_chunks().flatten().to_numpy().reshape(len(x), -1) for x in (a["vec"], b["vec"]))
            own = a["own"].to_numpy()
            order = np.argsort(ids, kind="stable")
            # seen items, other than the truth, do not compete
            cuts, flat = graph.flat_lists(a["seen"])
            row = np.repeat(np.arange(a.num_rows), np.diff(cuts))
            spot = order[np.searchsorted(ids[order], flat).clip(0, len(ids) - 1)]
            gone = (ids[spot] == flat) & (flat != t[row])
            row, spot = row[gone], spot[gone]
            d = np.einsum("ij,ij->i", g[row], v[spot]) - own[row]
            over = row[(d > TIE) | (np.abs(d) <= TIE) & (ids[spot] < t[row])]
            above = count_above(g, own, t, ids, v) - np.bincount(over, minlength=len(g))
            here = ids[order[np.searchsorted(ids[order], t).clip(0, len(ids) - 1)]] == t
            candidates = len(ids) - here - np.bincount(row, minlength=len(g))
        return pa.table({"group_key": a["group_key"], "item_id": a["item_id"], "above": pa.array(above, pa.int64()), "others": pa.array(candidates, pa.int64())})

    parts = x.groupBy("lb", "rb").cogroup(y.groupBy("lb", "rb")).applyInArrow(count, "group_key string, item_id long, above long, others long")
    return parts.groupBy("group_key", "item_id").agg((F.sum("above") + 1).alias("rnk"), (F.sum("others") + 1).alias("candidates"))


def static_rank(membership: DataFrame, users: DataFrame, items: DataFrame, how: str = "avg") -> DataFrame:
    """Scores of all items by an aggregate of member scores: ``avg``, ``min`` or ``max``.

    The mean of member scores is the score of the mean vector, so only ``min`` and ``max`` look at
    single members; they work on gathered members, block by block.
    """
    from crowdrank.operators.represent import gather

    g = gather(membership, users)
    x, y = blocked(g, items, key="group_key")

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        keys, ids, out = [], [], []
        if a.num_rows and b.num_rows:
            item, v = b["id"].to_numpy(), np.array(b["vec"].to_pylist())
            for key, vecs in zip(a["group_key"].to_pylist(), a["vecs"].to_pylist(), strict=True):
                s = np.array(vecs) @ v.T
                out.append({"avg": s.mean, "min": s.min, "max": s.max}[how](axis=0))
                keys += [key] * len(item)
                ids.append(item)
        return pa.table({"group_key": pa.array(keys, pa.string()), "item_id": pa.array(np.concatenate(ids) if ids else [], pa.int64()), "score": pa.array(np.concatenate(out) if out else [], pa.float64())})

    return x.groupBy("lb", "rb").cogroup(y.groupBy("lb", "rb")).applyInArrow(run, "group_key string, item_id long, score double")


def static_truth_rank(truth: DataFrame, membership: DataFrame, users: DataFrame, items: DataFrame, how: str = "avg", seen: DataFrame | None = None) -> DataFrame:
    """Ranks of the truth by an aggregate of member scores, counted block by block.

    No row a group and item is written: each block of items counts what beats the truth.
    """
    from crowdrank.operators.represent import gather

    groups = gather(membership, users).select("group_key", F.flatten("vecs").alias("vec"))

    def score(g, v: np.ndarray) -> np.ndarray:
        d = v.shape[1]
        rows = [np.asarray(x).reshape(-1, d) @ v.T for x in g]
        return np.array([getattr(r, {"avg": "mean", "min": "min", "max": "max"}[how])(axis=0) for r in rows]).reshape(len(g), len(v))

    return truth_rank_blocks(truth, groups, items, seen=seen, score=score, ragged=True)


def popularity_vectors(uv: DataFrame, groups: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Popularity as one-component vectors, so that it ranks through the same operators."""
    items = uv.groupBy(F.col("item_id").alias("id")).agg(F.array(F.sum("w")).alias("vec"))
    return groups.select("group_key").distinct().withColumn("vec", F.array(F.lit(1.0))), items


def hashed(number: Column, salt: int, d: int) -> Column:
    """A vector of reproducible numbers around 0 in plain integer arithmetic."""
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda k: F.pmod(number * 7919 + k * 104729 + F.lit(salt * 1299709), F.lit(1000003)) / 1000003.0 - 0.5)


def random_vectors(uv: DataFrame, membership: DataFrame, d: int = 8, salt: int = 61) -> tuple[DataFrame, DataFrame]:
    """Random scores as products of hashed vectors; a group's number comes from its members."""
    number = F.pmod(F.sum(F.col("user_id") * 31 + 17), F.lit(1000003))
    groups = membership.groupBy("group_key").agg(number.alias("n")).select("group_key", hashed(F.col("n"), salt, d).alias("vec"))
    return groups, uv.select(F.col("item_id").alias("id")).distinct().select("id", hashed(F.col("id"), salt + 1, d).alias("vec"))
