"""Distributed training by local updates, and evaluation of trained models.

Examples are dealt to units of work once, and a unit gets a fixed number of draws from the noise of
each graph, looked up by range; for group-aware noise each group example gets draws from the items that
its members touched. So what a unit holds depends on its examples, not on the number of items. In each
round a unit pulls the vectors of its examples, draws and neighbours (equi-joins on id), runs local
steps, and sends back what changed; changes are added up by id with a partial aggregate, and only the
dense parameters, whose size the data does not raise, pass through the driver. Tables are written to
the shared folder after each round.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.functions.tape import Var
from crowdrank.operators import evaluate, graph, rank, represent, sampling
from crowdrank.operators.models import ACC, Config, Example, Unit, parameters, train_unit

#: Rows of a unit: vectors (u, v), neighbours (n:view), features (f), means around a user (a), draws
#: (d:graph) and examples (e:graph, with weight and share in ``x``, drawn items in ``more``, ties in ``ties``).
PART = ["unit", "what", "id", "ids", "x", "more", "ties"]
LONGS, DOUBLES = "array<long>", "array<double>"
#: Distances of the closeness and betweenness views are taken to so many nodes.
LANDMARKS = 64
#: Up to so many tasks, units get four times as many tasks as they are, so that few meet in one.
UNIT_TASKS = 1024


@dataclass
class Trained:
    config: Config
    params: dict[str, np.ndarray]
    users: DataFrame
    items: DataFrame
    near: DataFrame | None
    features: DataFrame | None
    losses: list[float]
    uv: DataFrame
    uu: DataFrame


def start_vectors(ids: DataFrame, d: int, seed: int) -> DataFrame:
    """``id, vec``: small hashed numbers, the same wherever they are computed."""
    k = F.sequence(F.lit(0), F.lit(d - 1))
    return ids.select("id", F.transform(k, lambda j: (F.pmod(F.xxhash64("id", j, F.lit(seed)), F.lit(1 << 30)) / float(1 << 30) - 0.5) * 0.6).alias("vec"))


def centrality(uu: DataFrame, measure: str) -> DataFrame:
    """A centrality for views and features; distances go to landmarks, so all are affordable."""
    if measure in ("closeness", "betweenness"):
        k = min(LANDMARKS, uu.select("src").distinct().count())
        return graph.MEASURES[measure](uu, k) if k else graph.MEASURES[measure](uu)
    return graph.MEASURES[measure](uu, iters=10) if measure in ("pagerank", "eigenvector") else graph.MEASURES[measure](uu)


def neighbour_lists(uu: DataFrame, c: Config) -> DataFrame | None:
    """``view, id, ids``: one list a user and view, ranked by the view's centrality (or sampled)."""
    out = None
    for v in c.views:
        near = graph.sample_neighbours(uu, c.neighbours, c.seed) if v == "uniform" else graph.top_neighbours(uu, graph.store(centrality(uu, v)), c.neighbours)
        part = near.groupBy(F.col("user_id").alias("id")).agg(F.collect_list("nbr").alias("ids")).select(F.lit(v).alias("view"), "id", "ids")
        out = part if out is None else out.union(part)
    return None if out is None else graph.store(out)


#: Walk vectors have so many components in the influence baseline's features.
WALK_D = 8


def influence_features(uu: DataFrame) -> DataFrame:
    """``id, x``: five centralities scaled by their largest value, and a walk embedding."""
    out = None
    for m in graph.MEASURES:
        score = graph.store(centrality(uu, m))
        top = score.agg(F.max("score")).first()[0] or 1.0
        part = score.select(F.col("user_id").alias("id"), (F.log1p("score") / np.log1p(top) if m == "degree" else F.col("score") / top).alias(m))
        out = part if out is None else out.join(part, "id")
    walks = graph.store(graph.walk_corpus(uu, length=6))
    if walks.limit(1).count():
        out = out.join(graph.walk_embedding(walks, d=WALK_D).withColumnRenamed("user_id", "id"), "id")
    else:
        out = out.withColumn("vec", F.array_repeat(F.lit(0.0), WALK_D))
    return graph.store(out.select("id", F.concat(F.array(*graph.MEASURES), F.col("vec").cast(DOUBLES)).alias("x")))


def group_ties(records: DataFrame, uu: DataFrame) -> DataFrame:
    """``group_key, ties``: the tied members of each group, pair after pair; an exact join."""
    rows = graph.membership(records)
    pairs = rows.withColumnRenamed("user_id", "src").join(rows.toDF("group_key", "dst"), "group_key").filter("src <> dst")
    tied = pairs.join(uu.select("src", "dst").distinct(), ["src", "dst"])
    return tied.groupBy("group_key").agg(F.flatten(F.array_sort(F.collect_list(F.array("src", "dst")))).alias("ties"))


def mean_around(uv: DataFrame, uu: DataFrame, users: DataFrame, items: DataFrame, d: int) -> DataFrame:
    """``id, x``: the mean vector of a user's items by weight, then that of its friends."""

    def mean(edges: DataFrame, table: DataFrame, name: str) -> DataFrame:
        rows = edges.join(table.withColumnRenamed("id", "other"), "other")
        total = [F.sum(F.get("vec", k) * F.col("w")) / F.sum("w") for k in range(d)]
        return rows.groupBy("id").agg(F.array(*total).alias(name))

    a = mean(uv.select(F.col("user_id").alias("id"), F.col("item_id").alias("other"), "w"), items, "a")
    b = mean(uu.select(F.col("src").alias("id"), F.col("dst").alias("other"), F.lit(1.0).alias("w")), users, "b")
    none = F.array_repeat(F.lit(0.0), d)
    return a.join(b, "id", "full").select("id", F.concat(F.coalesce("a", none), F.coalesce("b", none)).alias("x"))


def part_rows(df: DataFrame, what, key="id", **cols) -> DataFrame:
    """Rows of a unit; columns that are not given are empty."""
    kinds = {"ids": LONGS, "x": DOUBLES, "more": LONGS, "ties": LONGS}
    rest = [F.col(cols[c]).cast(k).alias(c) if c in cols else F.array().cast(k).alias(c) for c, k in kinds.items()]
    return df.select("unit", (F.lit(what) if isinstance(what, str) else what).alias("what"), F.col(key).cast("long").alias("id"), *rest)


def dealt_examples(uv: DataFrame, uu: DataFrame, records: DataFrame, c: Config) -> tuple[DataFrame, int]:
    """``unit, kind, members, item_id, w, ties`` of all examples, and the number of units.

    Users who share items go to one unit, whose local steps then see how their items go together; a
    neighbourhood of more examples than a unit holds is dealt to several. Sizes sent to all tasks are
    those of such neighbourhoods only, at most one a unit.
    """
    none = F.array().cast(LONGS)
    ex = uv.select(F.lit("u").alias("kind"), F.array("user_id").alias("members"), "item_id", F.col("w").cast("double").alias("w"), none.alias("ties"), F.xxhash64("user_id", "item_id").alias("h"))
    gr = records.select("group_key", "members", "item_id")
    gr = gr.join(group_ties(records, uu), "group_key", "left") if c.aggregate == "voting" else gr.withColumn("ties", none)
    gr = gr.select(F.lit("g").alias("kind"), "members", "item_id", F.lit(1.0).alias("w"), F.coalesce("ties", none).alias("ties"), F.xxhash64("group_key", "item_id").alias("h"))
    ex = gr if c.mode == "simple" else ex.union(gr)
    near = neighbourhoods(uv)
    ex = graph.store(ex.join(near, F.col("members")[0] == F.col("user_id"), "left").withColumn("label", F.coalesce("label", "h")).drop("user_id"))
    sizes = ex.groupBy("label").count().filter(F.col("count") > c.unit_rows).select("label", F.ceil(F.col("count") / c.unit_rows).cast("int").alias("parts"))
    ex = graph.store(ex.join(F.broadcast(sizes), "label", "left").withColumn("part", F.pmod("h", F.coalesce("parts", F.lit(1)))).drop("parts"))
    places, units = packed(ex.groupBy("label", "part").count(), c.unit_rows)
    return graph.store(ex.join(places, ["label", "part"]).select("unit", "kind", "members", "item_id", "w", "ties")), units


def packed(sizes: DataFrame, most: int) -> tuple[DataFrame, int]:
    """``label, part, unit`` and the number of units: parts follow each other, ``most`` rows of them a unit.

    A unit ends with the part that fills it, so it has less than ``most`` rows and one part. Running sums
    go by shares of labels, as many as units, so that no task sees all parts.
    """
    sizes = graph.store(sizes)
    n = max(1, -(-(sizes.agg(F.sum("count")).first()[0] or 0) // most))
    sizes = sizes.withColumn("share", F.pmod(F.xxhash64("label", "part"), F.lit(n)))
    before = Window.orderBy("share").rowsBetween(Window.unboundedPreceding, -1)
    base = sizes.groupBy("share").agg(F.sum("count").alias("n")).select("share", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inner = Window.partitionBy("share").orderBy("label", "part").rowsBetween(Window.unboundedPreceding, -1)
    at = F.col("base") + F.coalesce(F.sum("count").over(inner), F.lit(0))
    return sizes.join(base, "share").select("label", "part", F.floor(at / most).cast("int").alias("unit")), n


def neighbourhoods(uv: DataFrame) -> DataFrame:
    """``user_id, label``: users that share items, or items with users who do, tend to have one label.

    The label is the least hash of an item at most three edges away.
    """
    e = graph.store(uv.select("user_id", "item_id", F.xxhash64("item_id").alias("h")))
    users = e.groupBy("user_id").agg(F.min("h").alias("h"))
    items = e.select("user_id", "item_id").join(users, "user_id").groupBy("item_id").agg(F.min("h").alias("h"))
    return e.select("user_id", "item_id").join(items, "item_id").groupBy("user_id").agg(F.min("h").alias("label"))


def noise_draws(uv: DataFrame, records: DataFrame, c: Config, units: int) -> DataFrame:
    """``unit, what, id``: ``pool`` draws a unit from the noise of each graph, items repeated as drawn."""
    groups = records.select("item_id").withColumn("w", F.lit(1.0))
    both = uv.select("item_id", "w").union(groups)
    flat = sampling.uniform_noise(both)
    by_graph = {
        "u": flat if c.negatives == "uniform" else sampling.degree_noise(uv),
        "g": flat if c.negatives in ("uniform", "group") else sampling.degree_noise(groups),
    }
    slots = uv.sparkSession.range(units).select(F.col("id").cast("int").alias("unit"), F.explode(F.sequence(F.lit(0), F.lit(c.pool - 1))).alias("slot"))
    out = None
    for k, (kind, noise) in enumerate(by_graph.items()):
        u = sampling.hashed_unit(F.col("unit"), F.col("slot"), F.lit(c.seed * 2 + k))
        part = sampling.look_up(slots.withColumn("u", u), graph.store(noise)).select("unit", F.lit(f"d:{kind}").alias("what"), F.col("neg").alias("id"))
        out = part if out is None else out.union(part)
    return out


def touched_draws(ex: DataFrame, uv: DataFrame, c: Config) -> DataFrame:
    """Group examples with ``touched`` (draws by the members' popularity) and ``share``, unit by unit.

    The lists of items stay here; only the draws travel on.
    """
    n_items = uv.select("item_id").distinct().count()
    taste = uv.groupBy(F.col("user_id").alias("id")).agg(F.array_sort(F.collect_list(F.struct("item_id", "w"))).alias("s")).select("id", F.col("s.item_id").alias("ids"), F.col("s.w").alias("x"))
    wanted = ex.filter("kind = 'g'").select("unit", F.explode("members").alias("id")).distinct().join(taste, "id")

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        lists = dict(zip(b["id"].to_pylist(), zip(_lists(b["ids"]), _lists(b["x"]), strict=True), strict=True))
        rng = np.random.default_rng([c.seed, 99, a["unit"][0].as_py() if a.num_rows else 0])
        touched, share = [], []
        for members in a["members"].to_pylist():
            own = [lists[u] for u in members if u in lists]
            if not own:
                touched.append([])
                share.append(0.0)
                continue
            t, at = np.unique(np.concatenate([i for i, _ in own]), return_inverse=True)
            run = np.cumsum((np.bincount(at, np.concatenate([w for _, w in own])) + c.gamma) ** 0.75)
            touched.append(t[np.searchsorted(run, rng.random(c.touched) * run[-1], side="right").clip(0, len(t) - 1)].tolist())
            share.append(float(run[-1] / (run[-1] + max(0, n_items - len(t)) * c.gamma**0.75)))
        out = a.select(["unit", "members", "item_id", "w", "ties"])
        return out.append_column("touched", pa.array(touched, pa.list_(pa.int64()))).append_column("share", pa.array(share, pa.float64()))

    groups = ex.filter("kind = 'g'").select("unit", "members", "item_id", "w", "ties")
    return groups.groupBy("unit").cogroup(wanted.toDF(*wanted.columns).groupBy("unit")).applyInArrow(run, "unit int, members array<long>, item_id long, w double, ties array<long>, touched array<long>, share double")


def added(moved: DataFrame, what: str, d: int) -> DataFrame:
    """``id, g``: the change of each vector over all units that moved it, with partial sums.

    Units hold different examples of a vector, so their changes add up; a mean would learn the slower
    the more units there are. Each step was divided by the root of the squared gradients that its own
    unit saw; the sum is divided by the root of what all units saw.
    """
    root = F.sqrt(ACC + F.get("x", d))
    total = F.sqrt(ACC + F.sum(F.get("x", d)))
    return moved.filter(F.col("what") == what).groupBy("id").agg(F.array(*[F.sum(F.get("x", k) * root) / total for k in range(d)]).alias("g"))


def fit(uv: DataFrame, uu: DataFrame, records: DataFrame, c: Config, users: DataFrame | None = None, items: DataFrame | None = None) -> Trained:
    """``records``: training rows of ``group_key, members, item_id``."""
    near, features = neighbour_lists(uu, c), influence_features(uu) if c.aggregate == "influence" else None
    ex, units = dealt_examples(uv, uu, records, c)
    one = ex.filter("kind = 'u'").select("unit", F.lit("e:u").alias("what"), "item_id", "members", F.array("w", F.lit(0.0)).alias("x"), F.array().cast(LONGS).alias("touched"), "ties")
    if c.negatives == "group":
        many = touched_draws(ex, uv, c)
    else:
        many = ex.filter("kind = 'g'").withColumn("touched", F.array().cast(LONGS)).withColumn("share", F.lit(0.0))
    rows = graph.store(one.union(many.select("unit", F.lit("e:g"), "item_id", "members", F.array("w", "share"), "touched", "ties")))
    pools = graph.store(noise_draws(uv, records, c, units))
    need_v = graph.store(rows.select("unit", F.explode(F.concat(F.array("item_id"), "touched")).alias("id")).union(pools.select("unit", "id")).distinct())
    need_u = ex.select("unit", F.explode("members").alias("id")).distinct()
    fixed = part_rows(rows, F.col("what"), "item_id", ids="members", x="x", more="touched", ties="ties").union(part_rows(pools, F.col("what")))
    if near is not None:
        lists = graph.store(need_u.join(near, "id").select("unit", F.concat(F.lit("n:"), "view").alias("what"), "id", "ids"))
        need_u = need_u.union(lists.select("unit", F.explode("ids"))).distinct()
        fixed = fixed.union(part_rows(lists, F.col("what"), ids="ids"))
    need_u = graph.store(need_u)
    if features is not None:
        fixed = fixed.union(part_rows(need_u.join(features, "id"), "f", x="x"))
    fixed = graph.store(fixed)
    if users is None:
        users = graph.store(start_vectors(uv.select(F.col("user_id").alias("id")).union(uu.select("src")).union(records.select(F.explode("members"))).distinct(), c.d, c.seed))
        items = graph.store(start_vectors(uv.select(F.col("item_id").alias("id")).union(records.select("item_id")).distinct(), c.d, c.seed + 1))
    P = parameters(c, len(graph.MEASURES) + WALK_D)
    losses = []
    stages = [{"two_stage": "user" if r < c.rounds // 2 else "group", "simple": "simple"}.get(c.mode, c.mode) for r in range(c.rounds)]
    for r, stage in enumerate(stages):
        rows = fixed.union(part_rows(need_u.join(users, "id"), "u", x="vec")).union(part_rows(need_v.join(items, "id"), "v", x="vec"))
        if c.aggregate == "voting":
            rows = rows.union(part_rows(need_u.join(mean_around(uv, uu, users, items, c.d), "id"), "a", x="x"))
        rows = rows.repartition(min(4 * units, max(units, UNIT_TASKS)), "unit")
        moved = graph.store(rows.groupBy("unit").applyInArrow(_step(P, c, stage, r), "what string, id long, x array<double>"))
        add = F.when(F.col("g").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "g", lambda a, b: a + b))
        if c.aggregate == "metric":  # sums of changes can leave the ball that each unit kept to
            norm = F.greatest(F.lit(1.0), F.sqrt(represent.dot(add, add)))
            add = F.transform(F.arrays_zip(add.alias("x"), F.array_repeat(norm, c.d).alias("n")), lambda z: z["x"] / z["n"])
        users, items = (graph.store(table.join(added(moved, what, c.d), "id", "left").select("id", add.alias("vec"))) for table, what in ((users, "u"), (items, "v")))
        flat = moved.filter("what NOT IN ('u', 'v')").select("what", F.posexplode("x").alias("k", "g"))
        dense = flat.groupBy("what", "k").agg(F.avg("g").alias("g")).groupBy("what").agg(F.array_sort(F.collect_list(F.struct("k", "g"))).alias("g")).collect()
        got = {row["what"]: np.array([z["g"] for z in row["g"]]) for row in dense}
        losses.append(float(got.pop("loss")[0]) if "loss" in got else 0.0)
        P = {k: v + got[f"p:{k}"].reshape(v.shape) if f"p:{k}" in got else v for k, v in P.items()}
    return Trained(c, P, users, items, near, features, losses, uv, uu)


def _lists(column: pa.ChunkedArray) -> list[np.ndarray]:
    """List cells as slices of one array, without a Python object for each number."""
    out: list[np.ndarray] = []
    for c in column.chunks:
        flat, cuts = c.values.to_numpy(zero_copy_only=False), c.offsets.to_numpy()
        out += [flat[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
    return out


def _unit(t: pa.Table) -> tuple[Unit, dict[str, list[Example]], dict[str, np.ndarray]]:
    users, items, near, features, around, examples, drawn = {}, {}, {}, {}, {}, {"g": [], "u": []}, {"g": [], "u": []}
    cells = (t["what"].to_pylist(), t["id"].to_pylist(), *(_lists(t[c]) for c in ("ids", "x", "more", "ties")))
    for what, key, ids, x, more, ties in zip(*cells, strict=True):
        if what == "u":
            users[key] = x
        elif what == "v":
            items[key] = x
        elif what == "f":
            features[key] = x
        elif what == "a":
            around[key] = x
        elif what[:2] == "n:":
            near.setdefault(what[2:], {})[key] = ids.tolist()
        elif what[:2] == "d:":
            drawn[what[2:]].append(key)
        else:
            examples[what[2:]].append(Example(ids.tolist(), key, float(x[0]), more.tolist(), float(x[1]), ties.tolist()))
    users, items = dict(sorted(users.items())), dict(sorted(items.items()))
    unit = Unit(users, items, near, features, around)
    pools = {k: np.array([unit.item_at[i] for i in sorted(v)], np.int64) for k, v in drawn.items()}
    return unit, {k: sorted(v, key=lambda e: (e.item, e.members)) for k, v in examples.items()}, pools


def _work(t: pa.Table, P: dict, c: Config, stage: str, r: int) -> pa.Table:
    unit, examples, pools = _unit(t)
    rng = np.random.default_rng([c.seed, r, t["unit"][0].as_py()])
    dU, dV, dP, loss = train_unit(unit, examples, P, c, stage, rng, pools)
    what = ["u"] * len(dU) + ["v"] * len(dV) + [f"p:{k}" for k in dP] + ["loss"]
    ids = [*unit.user_at, *unit.item_at, *[-1] * (len(dP) + 1)]
    return pa.table({"what": pa.array(what), "id": pa.array(ids, pa.int64()), "x": pa.array([*dU.tolist(), *dV.tolist(), *[v.ravel().tolist() for v in dP.values()], [loss]], pa.list_(pa.float64()))})


def user_vectors(t: Trained) -> DataFrame:
    """Vectors of users after convolution and mixing, block by block over gathered neighbours."""
    if not t.config.views:
        return t.users
    c, P = t.config, t.params
    lists = t.near.filter(F.col("view").isin(*c.views)).select("view", F.col("id").alias("own"), F.posexplode("ids").alias("at", "id")).join(t.users, "id")
    sets = lists.groupBy("own", "view").agg(F.array_sort(F.collect_list(F.struct("at", "vec"))).alias("s")).groupBy("own").agg(F.map_from_entries(F.collect_list(F.struct("view", F.col("s.vec").alias("s")))).alias("m"))
    rows = t.users.join(sets.withColumnRenamed("own", "id"), "id", "left").select("id", "vec", *[F.coalesce(F.col("m")[v], F.array().cast("array<array<double>>")).alias(f"n_{v}") for v in c.views])

    def run(batches):
        Pv = {k: Var(v) for k, v in P.items()}
        from crowdrank.functions import kernels as kn

        for b in batches:
            own = Var(np.array(b.column("vec").to_pylist()).reshape(-1, c.d))
            views = []
            for v in c.views:
                x, mask = represent.padded(b.column(f"n_{v}").to_pylist(), c.d)
                y = kn.convolve(own, Var(x), mask, Pv, v)
                views.append(own + y if c.skip else y)
            out = views[0] if len(views) == 1 else kn.mix_views(views, Pv["Z"])
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(out.data.tolist(), pa.list_(pa.float64()))], ["id", "vec"])

    return graph.store(rows.mapInArrow(run, "id long, vec array<double>"))


def group_vectors(t: Trained, records: DataFrame, users: DataFrame | None = None) -> DataFrame:
    """``group_key, vec`` for groups never seen before: only their members matter."""
    c, P = replace(t.config, views=()), t.params
    base = user_vectors(t) if users is None else users
    rows = graph.membership(records).join(base.withColumnRenamed("id", "user_id"), "user_id")
    item = ["user_id", "vec"]
    if c.aggregate == "influence":
        rows = rows.join(t.features.select(F.col("id").alias("user_id"), F.col("x").alias("f")), "user_id", "left")
        item.append("f")
    if c.aggregate == "voting":
        around = mean_around(t.uv, t.uu, t.users, t.items, c.d)
        rows = rows.join(around.select(F.col("id").alias("user_id"), F.col("x").alias("a")), "user_id", "left")
        item.append("a")
    sets = rows.groupBy("group_key").agg(F.array_sort(F.collect_list(F.struct(*item))).alias("s"))
    none = F.array().cast(LONGS)
    if c.aggregate == "voting":
        sets = sets.join(group_ties(records, t.uu), "group_key", "left").select("group_key", "s", F.coalesce("ties", none).alias("ties"))
    else:
        sets = sets.withColumn("ties", none)

    def run(batches):
        Pv = {k: Var(v) for k, v in P.items()}
        for b in batches:
            groups = b.column("s").to_pylist()
            users = {m["user_id"]: m["vec"] for g in groups for m in g}
            extra = {k: {m["user_id"]: np.array(m[k]) for g in groups for m in g if m.get(k)} for k in ("f", "a")}
            unit = Unit(users, {}, {}, extra["f"], extra["a"])
            v, _ = unit.groups([[m["user_id"] for m in g] for g in groups], Var(unit.U), Pv, c, b.column("ties").to_pylist())
            yield pa.RecordBatch.from_arrays([b.column("group_key"), pa.array(v.data.tolist(), pa.list_(pa.float64()))], ["group_key", "vec"])

    return graph.store(sets.select("group_key", "s", "ties").mapInArrow(run, "group_key string, vec array<double>"))


def scorer(t: Trained):
    """Scores of all group vectors with all item vectors of a block."""
    if t.config.aggregate == "ncf":
        P = t.params

        def score(g: np.ndarray, v: np.ndarray) -> np.ndarray:
            # as ``pair_scores``; for one group the layer on v and g * v is one matrix
            a, b, m = np.split(P["M1"], 3, axis=1)
            out = np.empty((len(g), len(v)))
            for i, x in enumerate(g):
                h = v @ (b.T + x[:, None] * m.T)
                h += a @ x + P["m1"]
                out[i] = np.maximum(h, 0, out=h) @ P["M2"][0] + v @ (x * P["m2"][0])
            return out

        return score
    if t.config.aggregate == "metric":
        return lambda g, v: 2 * g @ v.T - (v**2).sum(1)[None, :] - (g**2).sum(1)[:, None]
    return lambda g, v: g @ v.T


def evaluate_groups(t: Trained, test: DataFrame, seen: DataFrame) -> DataFrame:
    return rank.truth_rank_blocks(test, group_vectors(t, test), t.items, seen=seen, score=scorer(t))


def measures(ranks: DataFrame, method: str) -> DataFrame:
    """``method, metric, value`` for hits at five cut-offs and the mean reciprocal rank."""
    h = evaluate.hits(ranks).select(F.concat(F.lit("hits_"), F.col("n")).alias("metric"), F.col("hits").alias("value"))
    m = evaluate.mrr(ranks).select(F.lit("mrr").alias("metric"), F.col("mrr").alias("value"))
    return h.union(m).select(F.lit(method).alias("method"), "metric", F.round("value", 6).alias("value"))


def _step(P: dict, c: Config, stage: str, r: int):
    return lambda t: _work(t, P, c, stage, r)
