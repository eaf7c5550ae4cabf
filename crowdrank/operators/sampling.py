"""Noise distributions and reproducible negative draws."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.operators.graph import dealt, flat_lists, store
from crowdrank.operators.represent import digest

#: Members of the groups whose noise one task adds up.
MEMBER_ROWS = 524_288


def ranges(mass: DataFrame) -> DataFrame:
    """``item_id, mass, p, lo, hi``: cumulative shares in item order.

    Blocks of ids are summed first, so the running total over blocks is short and each block adds its
    own running total: no task sorts all items.
    """
    blocked = mass.withColumn("blk", F.floor(F.col("item_id") / 4096))
    sums = blocked.groupBy("blk").agg(F.sum("mass").alias("bm"))
    before = Window.orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("bm").over(before), F.lit(0.0)))
    total = sums.agg(F.sum("bm").alias("total"))
    own = Window.partitionBy("blk").orderBy("item_id")
    out = blocked.withColumn("run", F.sum("mass").over(own)).join(sums.select("blk", "base"), "blk").join(F.broadcast(total))
    hi = (F.col("base") + F.col("run")) / F.col("total")
    return out.select("item_id", "mass", (F.col("mass") / F.col("total")).alias("p"), (hi - F.col("mass") / F.col("total")).alias("lo"), hi.alias("hi"))


def degree_noise(edges: DataFrame, power: float = 0.75) -> DataFrame:
    return ranges(edges.groupBy("item_id").agg(F.pow(F.sum("w"), F.lit(power)).alias("mass")))


def uniform_noise(edges: DataFrame) -> DataFrame:
    return ranges(edges.select("item_id").distinct().withColumn("mass", F.lit(1.0)))


def group_aware_noise(membership: DataFrame, uv: DataFrame, gamma: float = 1.0, power: float = 0.75) -> DataFrame:
    """Sparse noise of groups: only items that members touched have rows.

    ``pop`` is the members' popularity of the item; ``rest`` the mass of each untouched item and
    ``touched`` their number, so the distribution over all items is complete without a dense table.
    """
    sets = membership.groupBy(digest("group_key").alias("_k")).agg(F.collect_set("user_id").alias("members"))
    sets = store(sets.withColumn("n", F.size("members")))
    shares = max(1, -(-(sets.agg(F.sum("n")).first()[0] or 0) // MEMBER_ROWS))
    rows = sets.withColumn("_b", F.pmod(F.xxhash64("_k"), F.lit(shares)).cast("int"))
    taste = uv.groupBy("user_id").agg(F.collect_list(F.struct("item_id", "w")).alias("s")).select("user_id", F.col("s.item_id").alias("ids"), F.col("s.w").alias("x"))
    pops = dealt(rows, rows.select("_b", F.explode("members").alias("user_id")), taste).applyInArrow(_added, "_k binary, ids array<long>, pops array<double>")
    mass = F.transform("pops", lambda x: F.pow(x + gamma, F.lit(power)))
    pops = pops.withColumn("m", F.aggregate(mass, F.lit(0.0), lambda s, x: s + x)).withColumn("touched", F.size("ids").cast("long"))
    keys = membership.select("group_key").distinct().withColumn("_k", digest("group_key"))
    items = uv.agg(F.count_distinct("item_id").alias("items"))
    pop = keys.join(pops.toDF(*pops.columns), "_k").select("group_key", "m", "touched", F.explode(F.arrays_zip("ids", "pops")).alias("z"))
    pop = pop.select("group_key", F.col("z.ids").alias("item_id"), F.col("z.pops").alias("pop"), "m", "touched").withColumn("mass", F.pow(F.col("pop") + gamma, F.lit(power)))
    rest = gamma**power
    out = pop.join(F.broadcast(items))
    return out.select("group_key", "item_id", "pop", "mass", "touched", (F.col("mass") / (F.col("m") + (F.col("items") - F.col("touched")) * rest)).alias("p"), F.lit(rest).alias("rest"))


def _added(a: pa.Table, b: pa.Table) -> pa.Table:
    """The members' popularity of each item that one of them touched, group by group."""
    keys, ids, pops = [], [], []
    if a.num_rows and b.num_rows:
        at = {u: i for i, u in enumerate(b["user_id"].to_pylist())}
        (cuts, item), (_, w) = flat_lists(b["ids"]), flat_lists(b["x"])
        names, codes = np.unique(item, return_inverse=True)
        for key, members in zip(a["_k"].to_pylist(), a["members"].to_pylist(), strict=True):
            own = [slice(cuts[i], cuts[i + 1]) for i in (at[u] for u in members if u in at)]
            if own:
                hit, back = np.unique(np.concatenate([codes[s] for s in own]), return_inverse=True)
                keys.append(key)
                ids.append(names[hit])
                pops.append(np.bincount(back, np.concatenate([w[s] for s in own])))
    cuts = np.cumsum([0, *map(len, ids)]).astype(np.int32)
    flat = lambda x, kind: pa.ListArray.from_arrays(cuts, pa.array(np.concatenate(x) if x else [], kind))
    return pa.table({"_k": pa.array(keys, pa.binary()), "ids": flat(ids, pa.int64()), "pops": flat(pops, pa.float64())})


def unit(a: Column, b: Column, c: Column) -> Column:
    """A reproducible number in (0, 1) for three ids."""
    return (F.pmod(a * 7919 + b * 104729 + c * 1299709, F.lit(1000003)) + 0.5) / 1000003.0


def hashed_unit(*ids: Column) -> Column:
    """The same from 53 bits of a hash: even an item with a tiny share can be drawn."""
    return (F.shiftrightunsigned(F.xxhash64(*ids), 11) + 0.5) / float(1 << 53)


def cells(noise: DataFrame, n: int) -> DataFrame:
    """``cell, neg, lo, hi``: the unit interval in ``n`` cells, each with the items that reach into it.

    An item stands in as many cells as its share covers, so there are at most ``n`` rows more than items.
    """
    rows = noise.select(F.col("item_id").alias("neg"), F.round("lo", 12).alias("lo"), F.round("hi", 12).alias("hi"))
    at = lambda c: F.least(F.lit(n - 1), F.floor(F.col(c) * n).cast("long"))
    return rows.withColumn("cell", F.explode(F.sequence(at("lo"), at("hi"))))


def look_up(draws: DataFrame, noise: DataFrame, u: str = "u", items_a_cell: int = 16) -> DataFrame:
    """Adds ``neg`` to rows with a number ``u`` in (0, 1): an equi-join on cells with a short check.

    Cells grow with the number of items, so each holds about ``items_a_cell`` of even share.
    """
    n = max(1, noise.count() // items_a_cell)
    q = draws.withColumn("cell", F.floor(F.col(u) * n).cast("long"))
    return q.join(cells(noise, n), "cell").filter((F.col(u) >= F.col("lo")) & (F.col(u) < F.col("hi"))).drop("cell", "lo", "hi")


def draw_negatives(pos: DataFrame, noise: DataFrame, m: int, seed: int = 0, observed: DataFrame | None = None, tries: int = 8) -> DataFrame:
    """``m`` draws a positive (columns ``user_id, pos``): adds ``slot, neg``.

    With ``observed`` (``user_id, item_id``) a draw that the user has touched is drawn again, up to
    ``tries`` times; one that still hits stays, as a user may have touched everything.
    """
    q = pos.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    draw = lambda k: unit(F.col("user_id"), F.col("pos"), F.col("slot") + (seed + k) * m)
    if observed is None:
        return look_up(q.withColumn("u", draw(F.lit(0))), noise).drop("u")
    wide = q.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(tries - 1)))).withColumn("u", draw(F.col("k")))
    drawn = look_up(wide, noise).drop("u")
    seen = observed.select("user_id", F.col("item_id").alias("neg"), F.lit(1).alias("hit")).distinct()
    marked = drawn.join(seen, ["user_id", "neg"], "left").withColumn("hit", F.coalesce("hit", F.lit(0)))
    best = marked.groupBy(*pos.columns, "slot").agg(F.min(F.struct("hit", "k", "neg")).alias("b"))
    return best.select(*pos.columns, "slot", "b.neg")


def noise_report(noise: DataFrame, popularity: DataFrame) -> DataFrame:
    """Entropy, variance, distance from uniform and expected popularity of what is drawn."""
    n = noise.agg(F.count("*").alias("n"))
    x = noise.join(popularity.select(F.col("id").alias("item_id"), F.col("degree").alias("pop")), "item_id").join(F.broadcast(n))
    return x.agg(
        F.count("*").alias("n"),
        F.round(-F.sum(F.col("p") * F.log("p")), 6).alias("entropy"),
        F.round(F.var_pop("p") * 1e9, 6).alias("variance_e9"),
        F.round(F.sum(F.abs(F.col("p") - 1 / F.col("n"))) / 2, 6).alias("from_uniform"),
        F.round(F.sum(F.col("p") * F.col("pop")), 6).alias("mean_popularity"),
    )
