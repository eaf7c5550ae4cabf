"""Training modes, baselines and the experiments, on the planted workload (rows-only checks)."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdrank.operators import evaluate as ev
from crowdrank.operators import graph as g
from crowdrank.operators import rank as rk
from crowdrank.operators import train as tr
from crowdrank.operators.models import Config
from crowdrank.plans.graph_queries import full, query_maker
from crowdrank.sources.workloads import WORKLOADS, planted

QUERIES, SQL = {}, {}
query = query_maker(QUERIES, SQL)
VIEWS = ("degree", "pagerank")
FULL = Config(views=VIEWS, negatives="group")

#: Settings of one estimator: the paper's model, its ablations and the learned baselines.
METHODS = {
    "consensus": FULL,
    "no_convolution": replace(FULL, views=()),
    "plain_convolution": replace(FULL, views=("uniform",)),
    "ranked_one_view": replace(FULL, views=("degree",)),
    "simple": replace(FULL, mode="simple", views=()),
    "two_stage": replace(FULL, mode="two_stage", negatives="degree"),
    "joint_degree": replace(FULL, negatives="degree"),
    "pooled": replace(FULL, mode="pooled"),
    "uniform_negatives": replace(FULL, negatives="uniform"),
    "mean_aggregation": Config(aggregate="mean"),
    "input_pooling": replace(FULL, over="input"),
    "skip_connection": replace(FULL, skip=True),
    "five_views": replace(FULL, views=tuple(g.MEASURES)),
    "influence": Config(aggregate="influence", mode="two_stage", rounds=4),
    "voting": Config(aggregate="voting"),
    "metric": Config(aggregate="metric", loss="hinge", mode="simple"),
    "neural_cf": Config(aggregate="ncf", mode="simple"),
}
#: Local epochs a round where the tables carry no preference to learn and edges are many.
SHORT = 6
#: The settings of the overall comparisons; popularity and random vectors come as floors.
OVERALL = ("consensus", "voting", "influence", "metric", "neural_cf")


def split(w) -> tuple[DataFrame, DataFrame]:
    sp = g.store(ev.time_split(w.records, exact=True))
    return sp.filter("split <> 'test'").drop("split"), sp.filter("split = 'test'").drop("split")


def run(w, name: str, c: Config, parts=None) -> DataFrame:
    train, test = parts or split(w)
    return tr.measures(tr.evaluate_groups(tr.fit(w.uv, w.uu, train, c), test, train), name)


def short(methods: dict[str, Config]) -> dict[str, Config]:
    return {k: replace(c, local=SHORT) for k, c in methods.items()}


def compare(w, methods: dict[str, Config], floors: bool = False) -> DataFrame:
    parts = train, test = split(w)
    out = None
    if floors:
        for name, vectors in (("popularity", rk.popularity_vectors), ("random", rk.random_vectors)):
            part = g.store(tr.measures(rk.truth_rank_blocks(test, *vectors(w.uv, g.membership(test)), seen=train), name))
            out = part if out is None else out.union(part)
        out = out.union(static_rows(w, parts, next(iter(methods.values())).local))
    for name, c in methods.items():
        part = g.store(run(w, name, c, parts))
        out = part if out is None else out.union(part)
    return out


#: The planted workload in SQL: normalised vectors, nearest items and users, groups, truth and its split.
PLANTED = """WITH v AS (SELECT vec_id AS id, list_transform(embedding[1:8], lambda c: c::DOUBLE) AS x FROM embeddings),
p AS (SELECT id, list_transform(x, lambda c: c / n) AS x FROM (SELECT id, x, sqrt(list_sum(list_transform(x, lambda c: c * c))) AS n FROM v)),
us AS (SELECT * FROM p WHERE id % 2 = 0), it AS (SELECT * FROM p WHERE id % 2 = 1),
uv AS (SELECT user_id, item_id FROM (SELECT u.id AS user_id, i.id AS item_id, row_number() OVER (PARTITION BY u.id ORDER BY list_dot_product(u.x, i.x) DESC, i.id) AS r FROM us u CROSS JOIN it i) WHERE r <= 12),
nn AS (SELECT src, r - 1 AS at, dst FROM (SELECT u.id AS src, o.id AS dst, row_number() OVER (PARTITION BY u.id ORDER BY list_dot_product(u.x, o.x) DESC, o.id) AS r FROM us u JOIN us o ON o.id <> u.id) WHERE r <= 8),
uu AS (SELECT src, dst FROM nn UNION SELECT dst, src FROM nn),
cn AS (SELECT dst AS user_id, count(*) AS k FROM nn GROUP BY 1),
an AS (SELECT id AS anchor, id // 2 AS a, rep, 2 + (id // 2 + rep) % 4 AS m FROM us CROSS JOIN (SELECT unnest(range(0, 4)) AS rep)),
pl AS (SELECT anchor, a, rep, ((j - 2 * rep) % 8 + 8) % 8 AS at FROM (SELECT *, unnest(range(0, m)) AS j FROM an)),
rw AS (SELECT pl.anchor, a, rep, list_sort(list_distinct(list_append(list(dst), pl.anchor))) AS members FROM pl JOIN nn ON nn.src = pl.anchor AND nn.at = pl.at GROUP BY pl.anchor, a, rep),
ea AS (SELECT anchor, rep, user_id, exp(coalesce(k, 0) / 3.0) AS e FROM (SELECT anchor, rep, unnest(members) AS user_id FROM rw) LEFT JOIN cn USING (user_id)),
la AS (SELECT anchor, rep, user_id, e / sum(e) OVER (PARTITION BY anchor, rep) AS l FROM ea),
gx AS (SELECT anchor, rep, k, sum(l * us.x[k]) AS x FROM la JOIN us ON us.id = la.user_id CROSS JOIN (SELECT unnest(range(1, 9)) AS k) GROUP BY ALL),
gl AS (SELECT anchor, rep, list(x ORDER BY k) AS x FROM gx GROUP BY 1, 2),
tr AS (SELECT anchor, rep, item_id FROM (SELECT anchor, rep, it.id AS item_id, row_number() OVER (PARTITION BY anchor, rep ORDER BY list_dot_product(gl.x, it.x) DESC, it.id) AS r FROM gl CROSS JOIN it) WHERE r = 1),
rec AS (SELECT array_to_string(members, '-') AS group_key, members, item_id, make_timestamp(((7919 * a + 104729 * rep) % 1000003)::BIGINT * 1000000) AS ts FROM rw JOIN tr USING (anchor, rep)),
sp AS (SELECT *, row_number() OVER (ORDER BY ts, group_key, item_id) > floor(0.8 * count(*) OVER ()) AS test FROM rec),
known AS (SELECT item_id FROM uv UNION SELECT item_id FROM sp WHERE NOT test)
"""


@query("planted_edges", PLANTED + "SELECT user_id, item_id FROM uv")
def _(spark, d):
    return planted(spark, d).uv.select("user_id", "item_id")


@query("planted_ties", PLANTED + "SELECT src, dst FROM uu")
def _(spark, d):
    return planted(spark, d).uu.select("src", "dst")


@query("planted_records", PLANTED + "SELECT group_key, item_id, epoch(ts)::BIGINT AS at FROM rec")
def _(spark, d):
    return planted(spark, d).records.select("group_key", "item_id", F.unix_seconds("ts").alias("at"))


def judged(ranks: DataFrame, method: str) -> DataFrame:
    """What holds for a trained model whatever it learned: all test pairs are ranked, better than by chance.

    Chance has a mean reciprocal rank of the harmonic number of the candidates over their number.
    """
    by_chance = (F.log(F.col("candidates")) + 0.5772) / F.col("candidates")
    return ranks.agg(F.count("*").alias("n_test"), (F.avg(1 / F.col("rnk")) > 2 * F.avg(by_chance)).alias("beats_chance")).select(F.lit(method).alias("method"), "n_test", "beats_chance")


def judged_sql(method: str) -> str:
    return PLANTED + f"SELECT '{method}' AS method, count(*) AS n_test, TRUE AS beats_chance FROM (SELECT DISTINCT group_key, item_id FROM sp WHERE test AND item_id IN (SELECT item_id FROM known))"


def ranks_of(w, c: Config, parts=None) -> DataFrame:
    train, test = parts or split(w)
    return tr.evaluate_groups(tr.fit(w.uv, w.uu, train, c), test, train)


FITS = {
    "fit_simple": "simple", "fit_two_stage": "two_stage", "fit_joint_degree": "joint_degree", "fit_joint_group": "consensus", "fit_pooled": "pooled", "fit_five_views": "five_views",
    "fit_uniform_negatives": "uniform_negatives", "influence_baseline": "influence", "voting_baseline": "voting", "metric_baseline": "metric", "neural_cf_baseline": "neural_cf",
}
for _name, _key in FITS.items():
    query(_name, judged_sql(_key))(lambda spark, d, k=_key: judged(ranks_of(planted(spark, d), METHODS[k]), k))


@query("virtual_user_embedder", PLANTED + "SELECT count(*) AS n_groups, count(*) FILTER (group_key IN (SELECT group_key FROM sp WHERE NOT test)) AS with_vector FROM (SELECT DISTINCT group_key FROM sp WHERE test)")
def _(spark, d):
    """Groups as virtual users: no vector exists for groups of the test part that are unseen."""
    w = planted(spark, d)
    train, test = split(w)
    known = virtual_vectors(w, train)[0]
    return test.select("group_key").distinct().join(known, "group_key", "left").agg(F.count("*").alias("n_groups"), F.count("vec").alias("with_vector"))


def virtual_vectors(w, train):
    """Vectors of the training groups, each a user of its own, and of the items."""
    ids = train.select("group_key").distinct().select("group_key", F.xxhash64("group_key").alias("user_id"))
    uv = train.join(ids, "group_key").select("user_id", "item_id", F.lit(1.0).alias("w"), "ts")
    none = uv.select(F.col("user_id").cast("string").alias("group_key"), F.array("user_id").alias("members"), "item_id").limit(0)
    m = tr.fit(uv, uv.select(F.col("user_id").alias("src"), F.col("user_id").alias("dst")).limit(0), none, Config(aggregate="virtual", eta=1e9))
    return ids.join(m.users.withColumnRenamed("id", "user_id"), "user_id").select("group_key", "vec"), m.items


def virtual_ranks(w, train, test) -> DataFrame:
    """Unseen groups have no vector; all items score alike for them."""
    known, items = virtual_vectors(w, train)
    zero = F.array_repeat(F.lit(0.0), Config().d)
    vec = test.select("group_key").distinct().join(known, "group_key", "left").select("group_key", F.coalesce("vec", zero).alias("vec"))
    return rk.truth_rank_blocks(test, vec, items, seen=train)


@query("fit_bipartite", PLANTED + "SELECT 'embedder' AS method, count(*) AS n_test, TRUE AS beats_chance FROM uv WHERE (user_id * 7919 + item_id * 104729) % 1000003 % 5 = 0 AND item_id IN (SELECT item_id FROM uv WHERE (user_id * 7919 + item_id * 104729) % 1000003 % 5 <> 0)")
def _(spark, d):
    """User and item vectors from user-item edges alone, and their held-out ranks."""
    return judged(personal_ranks(planted(spark, d), "embedder"), "embedder")


def personal_parts(w):
    """A hashed fifth of every user's edges is held out (all planted edges have one time)."""
    held = F.pmod(F.col("user_id") * 7919 + F.col("item_id") * 104729, F.lit(1000003)) % 5 == 0
    return g.store(w.uv.filter(~held)), g.store(w.uv.filter(held))


def personal_ranks(w, method: str, parts=None, local: int = Config().local) -> DataFrame:
    train, test = parts or personal_parts(w)
    keyed = lambda df: df.select(F.col("user_id").cast("string").alias("group_key"), "item_id")
    if method == "als":
        from pyspark.ml.recommendation import ALS

        as_int = [F.col(c).cast("int").alias(c) for c in ("user_id", "item_id")]
        als = ALS(rank=16, maxIter=10, regParam=0.05, alpha=20.0, implicitPrefs=True, userCol="user_id", itemCol="item_id", ratingCol="w", seed=7).fit(train.select(*as_int, "w"))
        wide = lambda df: df.select(F.col("id").cast("long").alias("id"), F.col("features").cast("array<double>").alias("vec"))
        users, items, score = wide(als.userFactors), wide(als.itemFactors), None
    else:
        c = {"embedder": Config(aggregate="mean"), "pairwise_mf": Config(aggregate="mean", loss="pair"), "neural_cf": Config(aggregate="ncf")}[method]
        m = tr.fit(train, w.uu, no_records(train), replace(c, eta=1e9, local=local))
        users, items, score = m.users, m.items, tr.scorer(m)
    return rk.truth_rank_blocks(keyed(test), users.select(F.col("id").cast("string").alias("group_key"), "vec"), items, seen=keyed(train), score=score)


def no_records(uv: DataFrame) -> DataFrame:
    return uv.select(F.lit("").alias("group_key"), F.array("user_id").alias("members"), "item_id").limit(0)


PERSONAL = {"als_personal": "als", "pairwise_personal": "pairwise_mf", "neural_cf_personal": "neural_cf"}
for _name, _key in PERSONAL.items():
    query(_name, SQL["fit_bipartite"].replace("'embedder'", f"'{_key}'"))(lambda spark, d, k=_key: judged(personal_ranks(planted(spark, d), k), k))


@query("exp_overall_w4")
def _(spark, d):
    return compare(planted(spark, d), {k: METHODS[k] for k in OVERALL}, floors=True)


@query("exp_overall_w3")
def _(spark, d):
    return compare(WORKLOADS["w3"](spark, d), {k: METHODS[k] for k in OVERALL}, floors=True)


def static_rows(w, parts, local: int = Config().local) -> DataFrame:
    """The three static strategies over vectors of the bipartite embedder, and groups as virtual users."""
    train, test = parts
    m = tr.fit(w.uv, w.uu, train.limit(0), Config(aggregate="mean", eta=1e9, local=local))
    out = g.store(tr.measures(virtual_ranks(w, train, test), "virtual_user"))
    for how in ("avg", "min", "max"):
        out = out.union(g.store(tr.measures(rk.static_truth_rank(test, g.membership(test), m.users, m.items, how, seen=train), how)))
    return out


@query("exp_static_w4")
def _(spark, d):
    w = planted(spark, d)
    return static_rows(w, split(w))


EMBEDDING = {k: METHODS[k] for k in ("no_convolution", "plain_convolution", "consensus")}
TRAINING = {k: replace(METHODS[k], views=()) for k in ("simple", "two_stage", "joint_degree", "consensus")}
for _w, _cut in (("w1", short), ("w2", short), ("w3", dict)):
    query(f"exp_user_embedding_{_w}")(lambda spark, d, w=_w, f=_cut: compare(WORKLOADS[w](spark, d), f(EMBEDDING)))
    query(f"exp_training_{_w}")(lambda spark, d, w=_w, f=_cut: compare(WORKLOADS[w](spark, d), f(TRAINING)))


@query("exp_user_embedding_w4")
def _(spark, d):
    return compare(planted(spark, d), {k: METHODS[k] for k in ("no_convolution", "plain_convolution", "ranked_one_view", "consensus", "skip_connection", "input_pooling")})


@query("exp_training_w4")
def _(spark, d):
    """Training modes without convolution, so that only the procedure differs."""
    return compare(planted(spark, d), {k: replace(METHODS[k], views=()) for k in ("simple", "two_stage", "joint_degree", "consensus", "pooled", "uniform_negatives")})


@query("exp_significance_w4")
def _(spark, d):
    """The consensus model against each learned baseline: paired tests on the same test pairs."""
    w = planted(spark, d)
    parts = split(w)
    ranks, out = {k: g.store(ranks_of(w, METHODS[k], parts)) for k in OVERALL}, None
    for k in OVERALL[1:]:
        part = ev.paired_test(ranks["consensus"], ranks[k]).select(F.lit(k).alias("against"), "*")
        out = part if out is None else out.union(part)
    return out


def sweep(spark, d, name: str, values, change) -> DataFrame:
    """One row a value and metric, then a column a metric."""
    out = compare(planted(spark, d), {str(v): change(v) for v in values})
    return out.groupBy(F.col("method").alias(name)).pivot("metric", ["hits_1", "hits_5", "hits_10", "hits_15", "hits_20", "mrr"]).agg(F.first("value"))


SWEEPS = {
    "dim": ((4, 8, 16, 32, 64, 128), lambda v: replace(FULL, d=v)),
    "heads": ((1, 2, 4, 8, 16, 32), lambda v: replace(FULL, d=32, heads=v)),
    "steps": ((1, 2, 3, 4, 5, 6), lambda v: replace(FULL, rounds=v)),
    "negatives": ((2, 3, 4, 5, 6, 7), lambda v: replace(FULL, m=v)),
    "neighbours": ((1, 2, 4, 6, 8, 10), lambda v: replace(FULL, neighbours=v)),
}
for _name, (_values, _change) in SWEEPS.items():
    query(f"exp_{_name}")(lambda spark, d, n=_name, v=_values, f=_change: sweep(spark, d, n, v, f))


def personal_rows(w, local: int = Config().local) -> DataFrame:
    parts, out = personal_parts(w), None
    for method in ("embedder", "pairwise_mf", "als", "neural_cf"):
        part = g.store(tr.measures(personal_ranks(w, method, parts, local), method))
        out = part if out is None else out.union(part)
    return out


@query("exp_personal")
def _(spark, d):
    return personal_rows(planted(spark, d))


@query("exp_personal_w1")
def _(spark, d):
    """Customers and parts: the tables carry no preference to learn, so this checks scale, not order."""
    return personal_rows(WORKLOADS["w1"](spark, d), SHORT)


@query("convergence_curve")
def _(spark, d):
    """Loss and test measure by number of steps, and from where the measure stays within a tenth of its end."""
    w = planted(spark, d)
    parts, rows = split(w), []
    c = replace(FULL, views=())
    edges = w.uv.count() + parts[0].count()
    for rounds in (1, 2, 3, 4, 5, 6):
        m = tr.fit(w.uv, w.uu, parts[0], replace(c, rounds=rounds))
        mrr = ev.mrr(tr.evaluate_groups(m, parts[1], parts[0])).first()["mrr"]
        rows.append((rounds * c.local * edges, m.losses[-1], mrr))
    at = ev.plateau([(n, x) for n, _, x in rows], 0.1)
    return spark.createDataFrame([(n, loss, x, n >= at) for n, loss, x in rows], "steps long, loss double, mrr double, stable boolean")


@query("grid_search")
def _(spark, d):
    """A grid over negatives and the graph weight, judged on folds in time order before the test part."""
    w = planted(spark, d)
    folds = [(g.store(a), g.store(b)) for a, b in ev.time_folds(split(w)[0], 2)]
    out = None
    for m in (2, 4):
        for eta in (0.5, 2.0):
            for k, parts in enumerate(folds):
                part = run(w, f"m={m} eta={eta}", replace(FULL, views=(), m=m, eta=eta), parts).filter("metric = 'mrr'")
                part = g.store(part.withColumn("fold", F.lit(k)))
                out = part if out is None else out.union(part)
    return out.groupBy("method").agg(F.round(F.avg("value"), 6).alias("mrr"), F.count("*").alias("folds"))


@query("step_cost", full("w2") + "SELECT d::INT AS d, m::INT AS m, v::INT AS views, d * (1 + m) * v AS step, e AS edges, e * d * (1 + m) * v AS total FROM (SELECT (SELECT count(*) FROM uv) + (SELECT count(*) FROM gv) AS e), (SELECT unnest([16, 32, 64, 128]) AS d), (SELECT unnest([2, 6]) AS m), (SELECT unnest([1, 5]) AS v)")
def _(spark, d):
    """Multiply-adds of a step, and of one pass over the edges of both graphs."""
    w = WORKLOADS["w2"](spark, d)
    edges = w.uv.count() + w.gv.count()
    costs = [(a, m, v, ev.cost_model(a, m, v, edges)) for a in (16, 32, 64, 128) for m in (2, 6) for v in (1, 5)]
    return spark.createDataFrame([(a, m, v, c["step"], c["steps"], c["total"]) for a, m, v, c in costs], "d int, m int, views int, step long, edges long, total long")


@query("exp_overall_w2")
def _(spark, d):
    """Explicit teams; the tables carry no preference to learn, so this checks scale, not order."""
    return compare(WORKLOADS["w2"](spark, d), short({k: METHODS[k] for k in (*OVERALL, "mean_aggregation")}), floors=True)


@query("bench_step_cost")
def _(spark, d):
    """Seconds of one round by dimension and number of steps, next to the multiply-adds of the cost model."""
    import time

    w, rows = WORKLOADS["w2"](spark, d), []
    uv, uu, records = g.store(w.uv), g.store(w.uu), g.store(w.records)
    edges = uv.count() + records.count()
    for dim, local in ((8, 1), (16, 1), (32, 1), (16, 2), (16, 4)):
        c = replace(FULL, views=(), d=dim, rounds=1, local=local)
        began = time.time()
        tr.fit(uv, uu, records, c)
        cost = ev.cost_model(dim, c.m, 1, edges, local)
        rows.append((dim, cost["steps"], cost["step"], cost["total"], time.time() - began))
    return spark.createDataFrame(rows, "d int, steps long, step long, total long, seconds double")
