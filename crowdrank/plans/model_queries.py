"""Representation, objective, ranking and evaluation queries on deterministic pseudo-parameters."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from crowdrank.functions import kernels as kn
from crowdrank.functions.tape import Var
from crowdrank.operators import evaluate as ev
from crowdrank.operators import graph as g
from crowdrank.operators import rank as rk
from crowdrank.operators import represent as rp
from crowdrank.operators import sampling as sm
from crowdrank.plans.graph_queries import DRAWS, SPLIT, full, query_maker, uv_of
from crowdrank.sources.workloads import gatherings, team_log, teams

QUERIES, SQL = {}, {}
query = query_maker(QUERIES, SQL)
D, HEADS = 4, 2


def pp(i: str, k: str, salt: int) -> str:
    return f"((({i}) * 7919 + ({k}) * 104729 + {salt * 1299709}) % 1000003 / 1000003.0 - 0.5)"


def vectors(ids, salt: int, d: int = D):
    """``id, vec`` of pseudo vectors."""
    k = F.sequence(F.lit(0), F.lit(d - 1))
    return ids.select("id", F.transform(k, lambda j: F.pmod(F.col("id") * 7919 + j * 104729 + salt * 1299709, F.lit(1000003)) / 1000003.0 - 0.5).alias("vec"))


def users(w, d: int = D):
    return vectors(w.membership.select(F.col("user_id").alias("id")).distinct(), 1, d)


def all_users(w):
    return vectors(w.uv.select(F.col("user_id").alias("id")).distinct(), 1)


def items(w):
    return vectors(w.uv.select(F.col("item_id").alias("id")).distinct(), 2)


KS = f"ks AS (SELECT unnest(range(0, {D})) AS k)"
USERS = f"ux AS (SELECT user_id AS u, k, {pp('user_id', 'k', 1)} AS x FROM (SELECT DISTINCT user_id FROM mem) CROSS JOIN ks)"


def proj(name: str, source: str, salt: int) -> str:
    """CTE: rows (u, k, x) times a pseudo matrix."""
    return f"{name} AS (SELECT u, j.k AS k, sum(x * {pp('j.k', 's.k', salt)}) AS x FROM {source} s CROSS JOIN ks j GROUP BY u, j.k)"


def attention(q: str, k: str, v: str, heads: int) -> str:
    w = D // heads
    return f"""sc AS (SELECT a.group_key, a.user_id AS u, b.user_id AS v, q.k // {w} AS h, sum(q.x * k.x) / sqrt({D}) AS s FROM mem a JOIN mem b USING (group_key) JOIN {q} q ON q.u = a.user_id JOIN {k} k ON k.u = b.user_id AND k.k = q.k GROUP BY ALL),
pa AS (SELECT *, exp(s - max(s) OVER z) AS e FROM sc WINDOW z AS (PARTITION BY group_key, u, h)),
pb AS (SELECT group_key, u, v, h, e / sum(e) OVER (PARTITION BY group_key, u, h) AS p FROM pa),
mh AS (SELECT group_key, pb.u AS u, k, sum(p * x) AS x FROM pb JOIN {v} vv ON vv.u = pb.v AND vv.k // {w} = h GROUP BY ALL)"""


SINGLE = full("w3") + ", " + ", ".join((KS, USERS, proj("q1", "ux", 11), proj("k1", "ux", 12), proj("v1", "ux", 13), attention("q1", "k1", "v1", 1)))
MULTI = full("w3") + ", " + ", ".join((KS, USERS, proj("q0", "ux", 11), proj("k0", "ux", 12), proj("v0", "ux", 13), proj("q1", "q0", 111), proj("k1", "k0", 112), proj("v1", "v0", 113), attention("q1", "k1", "v1", HEADS), f"oo AS (SELECT group_key, u, i.k AS k, sum(x * {pp('i.k', 'm.k', 14)}) AS x FROM mh m CROSS JOIN ks i GROUP BY ALL)"))


def pool(source: str) -> str:
    return f"""zz AS (SELECT group_key, u, i.k AS k, tanh(sum(x * {pp('i.k', 'o.k', 15)}) + any_value({pp('0', 'i.k', 17)})) AS z FROM {source} o CROSS JOIN ks i GROUP BY ALL),
tt AS (SELECT group_key, u, exp(sum(z * {pp('0', 'k', 16)})) AS e FROM zz GROUP BY ALL),
lm AS (SELECT group_key, u, e / sum(e) OVER (PARTITION BY group_key) AS l FROM tt),
gx AS (SELECT group_key, k, sum(l * z) AS x FROM zz JOIN lm USING (group_key, u) GROUP BY ALL)"""


FLAT = "xx AS (SELECT group_key, user_id AS u, k, x FROM mem JOIN ux ON ux.u = user_id)"
PARAMS = kn.pseudo_parameters(D)


def member_rows(w, kernel):
    """One row a member and component of a kernel that returns member vectors."""
    groups = rp.gather(w.membership, users(w))
    out = rp.transform(groups, lambda x, m: [[row[ok].tolist() for row, ok in zip(kernel(x, m).data, m, strict=True)]], D, out="rows array<array<double>>", keep="members")
    both = out.select("group_key", F.posexplode("rows").alias("i", "vec"), "members")
    return both.select("group_key", F.expr("members[i]").alias("user_id"), F.posexplode("vec").alias("k", "x")).withColumn("x", F.round("x", 6) + F.lit(0.0))


@query("self_attention", SINGLE + "SELECT group_key, u AS user_id, k::INT AS k, round(x, 6) + 0.0 AS x FROM mh")
def _(spark, d):
    m = [kn.pseudo_matrix(D, D, s) for s in (11, 12, 13)]
    return member_rows(gatherings(spark, d), lambda x, mask: kn.self_attention(x, mask, *m))


@query("multi_head", MULTI + "SELECT group_key, u AS user_id, k::INT AS k, round(x, 6) + 0.0 AS x FROM oo")
def _(spark, d):
    return member_rows(gatherings(spark, d), lambda x, mask: kn.multi_head(x, mask, PARAMS, HEADS))


@query("attentive_pool", full("w2") + ", " + ", ".join((KS, USERS, FLAT, pool("xx"))) + "SELECT group_key, k::INT AS k, round(x, 6) + 0.0 AS x FROM gx")
def _(spark, d):
    w = teams(spark, d)
    return rp.exploded(rp.transform(rp.gather(w.membership, users(w)), lambda x, m: [kn.attentive_pool(x, m, PARAMS)[0].data.tolist()], D))


@query("crowd_attention", MULTI + ", " + pool("oo") + "SELECT group_key, k::INT AS k, round(x, 6) + 0.0 AS x FROM gx")
def _(spark, d):
    w = gatherings(spark, d)
    return rp.exploded(rp.transform(rp.gather(w.membership, users(w)), lambda x, m: [kn.crowd_attention(x, m, PARAMS, HEADS)[0].data.tolist()], D))


@query("member_weights", MULTI + ", " + pool("oo") + "SELECT group_key, u AS user_id, round(l, 6) AS weight FROM lm")
def _(spark, d):
    w = gatherings(spark, d)
    groups = rp.gather(w.membership, users(w))
    out = rp.transform(groups, lambda x, m: [[r[ok].tolist() for r, ok in zip(kn.crowd_attention(x, m, PARAMS, HEADS)[1].data, m, strict=True)]], D, out="l array<double>", keep="members")
    return out.select("group_key", F.explode(F.arrays_zip("members", "l")).alias("z")).select("group_key", F.col("z.members").alias("user_id"), F.round("z.l", 6).alias("weight"))


@query("weighted_sum", full("w2") + f", {KS}, {USERS} SELECT group_key, k::INT AS k, round(sum({pp('user_id', '0', 50)} * x), 6) + 0.0 AS x FROM mem JOIN ux ON ux.u = user_id GROUP BY ALL")
def _(spark, d):
    w = teams(spark, d)
    weight = F.pmod(F.col("user_id") * 7919 + 50 * 1299709, F.lit(1000003)) / 1000003.0 - 0.5
    return rp.exploded(rp.weighted_sum(w.membership, w.membership.withColumn("weight", weight), users(w)))


INFLUENCE = full("w2") + f", {KS}, {USERS}, e AS (SELECT group_key, user_id, exp({pp('user_id', '1', 51)}) AS e FROM mem), l AS (SELECT group_key, user_id, e / sum(e) OVER (PARTITION BY group_key) AS weight FROM e) "


def influence(w):
    return w.membership.select("user_id").distinct().withColumn("influence", F.pmod(F.col("user_id") * 7919 + 104729 + 51 * 1299709, F.lit(1000003)) / 1000003.0 - 0.5)


@query("influence_attention", INFLUENCE + "SELECT group_key, k::INT AS k, round(sum(weight * x), 6) + 0.0 AS x FROM l JOIN ux ON ux.u = user_id GROUP BY ALL")
def _(spark, d):
    w = teams(spark, d)
    return rp.exploded(rp.weighted_sum(w.membership, rp.influence_weights(w.membership, influence(w)), users(w)))


# --- users: convolution and view mixing

#: Ranked neighbours of the users ``us``, and their convolution, as CTEs over ``uu`` and ``ks``.
NEAR = "deg AS (SELECT src AS user_id, count(*)::DOUBLE AS score FROM uu GROUP BY 1), nb AS (SELECT * FROM (SELECT src AS u, dst AS n, row_number() OVER (PARTITION BY src ORDER BY score DESC, dst) AS r, score FROM uu JOIN deg ON deg.user_id = dst) WHERE r <= 4)"


def conv(agg: str) -> str:
    return f"""{NEAR}, rr AS (SELECT nb.u, nb.n, nb.score, i.k AS k, greatest(0, sum({pp('nb.n', 'j.k', 1)} * {pp('i.k', 'j.k', 21)}) + any_value({pp('0', 'i.k', 22)})) AS r FROM nb CROSS JOIN ks i CROSS JOIN ks j GROUP BY nb.u, nb.n, nb.score, i.k),
hh AS (SELECT u, k, {agg} AS h FROM rr GROUP BY u, k),
inp AS (SELECT u, k, {pp('u', 'k', 1)} AS x FROM us CROSS JOIN ks UNION ALL SELECT us.u, k + {D}, coalesce(h, 0) FROM us CROSS JOIN ks LEFT JOIN hh USING (u, k)),
yy AS (SELECT u, i.k AS k, greatest(0, sum(x * {pp('i.k', 'inp.k', 23)}) + any_value({pp('0', 'i.k', 24)})) AS y FROM inp CROSS JOIN ks i GROUP BY u, i.k),
ux AS (SELECT u, k, y / greatest(sqrt(sum(y * y) OVER (PARTITION BY u)), 1e-300) AS x FROM yy)"""


def convolved(ids, near, pool: str = "mean"):
    """``id, vec`` of pseudo vectors after one convolution over ranked neighbours."""
    own = vectors(ids, 1)
    gathered = near.join(own.withColumnRenamed("id", "nbr"), "nbr").groupBy(F.col("user_id").alias("id")).agg(F.array_sort(F.collect_list(F.struct("rnk", "vec", "score"))).alias("s"))
    rows = own.join(gathered, "id", "left").select("id", "vec", F.coalesce("s.vec", F.array().cast("array<array<double>>")).alias("vecs"), F.coalesce("s.score", F.array().cast("array<double>")).alias("scores"))

    def run(batches):
        import pyarrow as pa

        for b in batches:
            near, mask = rp.padded(b.column("vecs").to_pylist(), D)
            scores = np.zeros(mask.shape)
            scores[mask] = [x for row in b.column("scores").to_pylist() for x in row]
            y = kn.convolve(Var(np.array(b.column("vec").to_pylist()).reshape(-1, D)), Var(near), mask, PARAMS, "0", pool, scores)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(y.data.tolist(), pa.list_(pa.float64()))], ["id", "vec"])

    return rows.mapInArrow(run, "id long, vec array<double>")


def convolved_teams(spark, d, pool: str):
    sup = spark.read.parquet(f"{d}/supplier.parquet").select(F.col("s_suppkey").alias("id"))
    return rp.exploded(convolved(sup, teams(spark, d).near(4), pool).withColumnRenamed("id", "user_id"), "user_id")


CONV = uv_of("w2")[:-1] + f", {KS}, us AS (SELECT DISTINCT s_suppkey AS u FROM supplier), "
for _pool, _agg in (("mean", "avg(r)"), ("weighted", "sum(r * score) / sum(score)"), ("max", "max(r)")):
    query(f"convolve_{_pool}", CONV + conv(_agg) + " SELECT u AS user_id, k::INT AS k, round(x, 6) + 0.0 AS x FROM ux")(lambda spark, d, p=_pool: convolved_teams(spark, d, p))

C = 3
MIX = f"""WITH {KS}, cs AS (SELECT unnest(range(0, {C})) AS c), us AS (SELECT s_suppkey AS u FROM supplier),
vw AS (SELECT u, c, k, ((u * 7919 + k * 104729 + (40 + c) * 1299709) % 1000003 / 1000003.0 - 0.5) AS x FROM us CROSS JOIN cs CROSS JOIN ks),
t AS (SELECT vw.u, z.c AS c, exp(sum(x * ((z.c * 7919 + (vw.c * {D} + vw.k) * 104729 + {31 * 1299709}) % 1000003 / 1000003.0 - 0.5))) AS e FROM vw CROSS JOIN cs z GROUP BY vw.u, z.c),
a AS (SELECT u, c, e / sum(e) OVER (PARTITION BY u) AS a FROM t)
SELECT u AS user_id, k::INT AS k, round(sum(a * x), 6) + 0.0 AS x FROM vw JOIN a USING (u, c) GROUP BY ALL"""


@query("view_mix", MIX)
def _(spark, d):
    ids = spark.read.parquet(f"{d}/supplier.parquet").select(F.col("s_suppkey").alias("id"))
    views = ids.withColumn("v", F.lit(0)).select("id")
    for c in range(C):
        views = views.join(vectors(ids, 40 + c).withColumnRenamed("vec", f"v{c}"), "id")
    z = kn.pseudo_matrix(C, C * D, 31)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            m = kn.mix_views([Var(np.array(b.column(f"v{c}").to_pylist()).reshape(-1, D)) for c in range(C)], z)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(m.data.tolist(), pa.list_(pa.float64()))], ["id", "vec"])

    return rp.exploded(views.mapInArrow(run, "id long, vec array<double>").withColumnRenamed("id", "user_id"), "user_id")


# --- objectives

ITEMS = "it AS (SELECT DISTINCT item_id FROM uv)"
LEFT = "lf AS (SELECT DISTINCT user_id FROM uv)"


def dots(a: str, sa: int, b: str, sb: int) -> str:
    return "(" + " + ".join(f"{pp(a, str(k), sa)} * {pp(b, str(k), sb)}" for k in range(D)) + ")"


SOFT = uv_of("w2")[:-1] + f", {ITEMS}, {LEFT}, z AS (SELECT user_id, ln(sum(exp({dots('user_id', 1, 'item_id', 2)}))) AS lse FROM lf CROSS JOIN it GROUP BY 1) "


def edges(w):
    return w.uv.select(F.col("user_id").alias("left"), "item_id", "w")


@query("interaction_softmax", SOFT + f"SELECT user_id, item_id, round(exp({dots('user_id', 1, 'item_id', 2)} - lse), 9) AS p FROM uv JOIN z USING (user_id)")
def _(spark, d):
    w = teams(spark, d)
    left, right = all_users(w), items(w)
    e = edges(w).join(rp.interaction_logs(left, right).withColumnRenamed("id", "left"), "left").join(left.select(F.col("id").alias("left"), F.col("vec").alias("l")), "left").join(right.select(F.col("id").alias("item_id"), F.col("vec").alias("v")), "item_id")
    return e.select(F.col("left").alias("user_id"), "item_id", F.round(F.exp(rp.dot("l", "v") - F.col("lse")), 9).alias("p"))


@query("empirical_prob", uv_of("w2") + "SELECT user_id, item_id, round(w / sum(w) OVER (PARTITION BY user_id), 9) AS p FROM uv")
def _(spark, d):
    return rp.empirical_prob(teams(spark, d).uv, "user_id").withColumn("p", F.round("p", 9))


@query("exact_loss", SOFT + f"SELECT round(sum(w * (lse - {dots('user_id', 1, 'item_id', 2)})), 4) AS loss_sum, round(avg(w * (lse - {dots('user_id', 1, 'item_id', 2)})), 6) AS loss_mean, count(*) AS n FROM uv JOIN z USING (user_id)")
def _(spark, d):
    w = teams(spark, d)
    return rp.exact_loss(edges(w), all_users(w), items(w)).select(F.round("loss_sum", 4).alias("loss_sum"), F.round("loss_mean", 6).alias("loss_mean"), "n")


@query("kl_gap", SOFT + f", e AS (SELECT user_id, item_id, w, sum(w) OVER (PARTITION BY user_id) AS dg FROM uv), f AS (SELECT dg * (w / dg) AS m, ln(w / dg) AS lp, {dots('user_id', 1, 'item_id', 2)} - lse AS lq FROM e JOIN z USING (user_id)) SELECT round(sum(m * (lp - lq)), 3) AS kl, round(sum(m * lp), 3) AS constant, round(sum(-m * lq), 3) AS loss FROM f")
def _(spark, d):
    w = teams(spark, d)
    return rp.kl_gap(edges(w), all_users(w), items(w)).select(*[F.round(c, 3).alias(c) for c in ("kl", "constant", "loss")])


SAMPLES = DRAWS[: DRAWS.rindex("SELECT q.user_id")].rstrip() + ", dr AS (SELECT q.user_id, ns.item_id FROM q JOIN ns ON q.u >= ns.lo AND q.u < ns.hi), sa AS (SELECT user_id AS l, item_id, 1.0::DOUBLE AS y FROM uv UNION ALL SELECT user_id, item_id, 0.0::DOUBLE FROM dr) "


def samples(w):
    uv = w.uv
    pos = uv.select("user_id", F.col("item_id").alias("pos"))
    neg = sm.draw_negatives(pos, sm.degree_noise(uv), 2)
    return pos.select(F.col("user_id").alias("left"), F.col("pos").alias("item_id"), F.lit(1.0).alias("y")).union(neg.select("user_id", "neg", F.lit(0.0)))


@query("ns_loss", SAMPLES + f", s AS (SELECT y, {dots('l', 1, 'item_id', 2)} AS s FROM sa) SELECT round(sum(ln(1 + exp(CASE WHEN y = 1 THEN -s ELSE s END))), 4) AS loss_sum, round(avg(ln(1 + exp(CASE WHEN y = 1 THEN -s ELSE s END))), 6) AS loss_mean, count(*) AS n FROM s")
def _(spark, d):
    w = teams(spark, d)
    return rp.ns_loss(samples(w), all_users(w), items(w)).select(F.round("loss_sum", 4).alias("loss_sum"), F.round("loss_mean", 6).alias("loss_mean"), "n")


@query("sgd_step", SAMPLES + f", {KS}, e AS (SELECT l, item_id, 1 / (1 + exp(-{dots('l', 1, 'item_id', 2)})) - y AS e FROM sa), gu AS (SELECT l, k, sum(e * {pp('item_id', 'k', 2)}) AS g FROM e CROSS JOIN ks GROUP BY 1, 2), gi AS (SELECT item_id, k, sum(e * {pp('l', 'k', 1)}) AS g FROM e CROSS JOIN ks GROUP BY 1, 2) SELECT 'user' AS side, user_id AS id, ks.k::INT AS k, round({pp('user_id', 'ks.k', 1)} - 0.1 * coalesce(g, 0), 6) + 0.0 AS x FROM (SELECT DISTINCT user_id FROM uv) CROSS JOIN ks LEFT JOIN gu ON gu.l = user_id AND gu.k = ks.k UNION ALL SELECT 'item', i.item_id, ks.k::INT, round({pp('i.item_id', 'ks.k', 2)} - 0.1 * coalesce(g, 0), 6) + 0.0 FROM (SELECT DISTINCT item_id FROM uv) i CROSS JOIN ks LEFT JOIN gi ON gi.item_id = i.item_id AND gi.k = ks.k")
def _(spark, d):
    w = teams(spark, d)
    u, v = rp.sgd_step(samples(w), all_users(w), items(w), 0.1)
    return rp.exploded(u, "id").select(F.lit("user").alias("side"), "id", "k", "x").union(rp.exploded(v, "id").select(F.lit("item"), "id", "k", "x"))


#: The objectives of the whole model on the gatherings: users convolved over ranked neighbours, groups
#: by crowd attention over them, negatives of each graph from its own noise, two a positive.
WHOLE = full("w3") + ", " + ", ".join((
    KS, "us AS (SELECT DISTINCT user_id AS u FROM uv)", conv("avg(r)"),
    proj("q0", "ux", 11), proj("k0", "ux", 12), proj("v0", "ux", 13), proj("q1", "q0", 111), proj("k1", "k0", 112), proj("v1", "v0", 113),
    attention("q1", "k1", "v1", HEADS),
    f"oo AS (SELECT group_key, u, i.k AS k, sum(x * {pp('i.k', 'm.k', 14)}) AS x FROM mh m CROSS JOIN ks i GROUP BY ALL)",
    pool("oo"),
    "gn AS (SELECT group_key, sum(user_id) AS gid FROM mem GROUP BY 1)",
    "pg AS (SELECT group_key AS l, gid AS a, item_id AS pos FROM gv JOIN gn USING (group_key))",
    "pu AS (SELECT user_id AS l, user_id AS a, item_id AS pos FROM uv)",
))


def sampled_objective(side: str, positives: str, edges: str, left: str) -> str:
    """CTEs up to ``l{side}(l)``: one row a sample with its loss."""
    return f""", m{side} AS (SELECT item_id, pow(sum(w), 0.75) AS mass FROM {edges} GROUP BY 1),
n{side} AS (SELECT item_id, round(coalesce(lag(c) OVER (ORDER BY item_id), 0), 12) AS lo, round(c, 12) AS hi FROM (SELECT item_id, sum(mass) OVER (ORDER BY item_id) / sum(mass) OVER () AS c FROM m{side})),
d{side} AS (SELECT p.l, n.item_id FROM {positives} p CROSS JOIN (SELECT unnest(range(0, 2)) AS slot) JOIN n{side} n ON ((a * 7919 + pos * 104729 + slot * 1299709) % 1000003 + 0.5) / 1000003.0 >= n.lo AND ((a * 7919 + pos * 104729 + slot * 1299709) % 1000003 + 0.5) / 1000003.0 < n.hi),
s{side} AS (SELECT row_number() OVER () AS i, * FROM (SELECT l, pos AS item_id, 1 AS y FROM {positives} UNION ALL SELECT l, item_id, 0 FROM d{side})),
l{side} AS (SELECT ln(1 + exp(CASE WHEN y = 1 THEN -s ELSE s END)) AS l FROM (SELECT i, y, sum(x * {pp('item_id', 'k', 2)}) AS s FROM s{side} JOIN {left} GROUP BY i, y))"""


GROUP_SIDE = sampled_objective("g", "pg", "gv", "gx ON gx.group_key = sg.l")
USER_SIDE = sampled_objective("u", "pu", "uv", "ux ON ux.u = su.l")


def whole_vectors(w):
    """Group and user vectors of the whole model with pseudo parameters."""
    own = g.store(convolved(w.uv.select(F.col("user_id").alias("id")).distinct(), w.near(4)))
    groups = rp.transform(rp.gather(w.membership, own), lambda x, m: [kn.crowd_attention(x, m, PARAMS, HEADS)[0].data.tolist()], D)
    return groups, own


def sampled_loss(positives, noise, left, right):
    """Loss of positives ``l, user_id, pos`` and two draws each."""
    neg = sm.draw_negatives(positives, noise, 2)
    both = positives.select(F.col("l").alias("left"), F.col("pos").alias("item_id"), F.lit(1.0).alias("y")).union(neg.select("l", "neg", F.lit(0.0)))
    return rp.ns_loss(both, left, right)


def group_objective(w):
    number = w.membership.groupBy("group_key").agg(F.sum("user_id").alias("user_id"))
    positives = w.gv.join(number, "group_key").select(F.col("group_key").alias("l"), "user_id", F.col("item_id").alias("pos"))
    return sampled_loss(positives, sm.degree_noise(w.gv), whole_vectors(w)[0].withColumnRenamed("group_key", "id"), items(w))


def user_objective(w):
    positives = w.uv.select(F.col("user_id").alias("l"), "user_id", F.col("item_id").alias("pos"))
    return sampled_loss(positives, sm.degree_noise(w.uv), whole_vectors(w)[1], items(w))


def _loss(df):
    return df.select(F.round("loss_sum", 4).alias("loss_sum"), F.round("loss_mean", 6).alias("loss_mean"), "n")


@query("group_ns_loss", WHOLE + GROUP_SIDE + " SELECT round(sum(l), 4) AS loss_sum, round(avg(l), 6) AS loss_mean, count(*) AS n FROM lg")
def _(spark, d):
    return _loss(group_objective(gatherings(spark, d)))


@query("user_ns_loss", WHOLE + USER_SIDE + " SELECT round(sum(l), 4) AS loss_sum, round(avg(l), 6) AS loss_mean, count(*) AS n FROM lu")
def _(spark, d):
    return _loss(user_objective(gatherings(spark, d)))


@query("joint_loss", WHOLE + GROUP_SIDE + USER_SIDE + " SELECT round((SELECT avg(l) FROM lg), 6) AS group_loss, round((SELECT avg(l) FROM lu), 6) AS user_loss, round((SELECT avg(l) FROM lg) + 2.0 * (SELECT avg(l) FROM lu), 6) AS joint_loss")
def _(spark, d):
    """Both objectives with their negatives, the user side weighted by two."""
    w = gatherings(spark, d)
    both = group_objective(w).select(F.col("loss_mean").alias("a")).join(user_objective(w).select(F.col("loss_mean").alias("b")))
    return both.select(F.round("a", 6).alias("group_loss"), F.round("b", 6).alias("user_loss"), F.round(F.col("a") + 2.0 * F.col("b"), 6).alias("joint_loss"))


@query("pooled_draw_shares", full("w2") + "SELECT round(count(*) FILTER (k = 'gv') / count(*), 9) AS group_share, round(count(*) FILTER (k = 'uv') / count(*), 9) AS user_share FROM (SELECT 'gv' AS k FROM gv UNION ALL SELECT 'uv' FROM uv)")
def _(spark, d):
    w = teams(spark, d)
    both = w.gv.select(F.lit("gv").alias("k")).union(w.uv.select(F.lit("uv")))
    return both.agg(F.round(F.count_if(F.col("k") == "gv") / F.count("*"), 9).alias("group_share"), F.round(F.count_if(F.col("k") == "uv") / F.count("*"), 9).alias("user_share"))


# --- ranking and evaluation over mean group vectors

MEAN = ", gm AS (SELECT group_key, " + ", ".join(f"avg({pp('user_id', str(k), 1)}) AS g{k}" for k in range(D)) + " FROM mem GROUP BY 1)"
SCORE = "(" + " + ".join(f"g{k} * {pp('item_id', str(k), 2)}" for k in range(D)) + ")"


def group_vectors(w):
    return rp.mean_vectors(w.membership, users(w), D)


@query("group_scores", full("w2") + MEAN + f" SELECT group_key, item_id, round({SCORE}, 6) + 0.0 AS score FROM gv JOIN gm USING (group_key)")
def _(spark, d):
    w = teams(spark, d)
    return rk.scores(group_vectors(w), items(w), w.gv.select("group_key", "item_id")).withColumn("score", F.round("score", 6) + F.lit(0.0))


TOPN = full("w3") + MEAN + f", it AS (SELECT DISTINCT item_id FROM uv), r AS (SELECT group_key, item_id, {SCORE} AS score, row_number() OVER (PARTITION BY group_key ORDER BY {SCORE} DESC, item_id)::INT AS rnk FROM gm CROSS JOIN it) SELECT group_key, rnk, item_id, round(score, 6) + 0.0 AS score FROM r WHERE rnk <= 10"


def _rounded(df):
    return df.withColumn("score", F.round("score", 6) + F.lit(0.0))


@query("topn", TOPN)
def _(spark, d):
    w = gatherings(spark, d)
    return _rounded(rk.topn(group_vectors(w), items(w), 10))


@query("topn_bounded", TOPN)
def _(spark, d):
    w = gatherings(spark, d)
    return _rounded(rk.topn_bounded(group_vectors(w), items(w), 10, block=16))


@query("topn_lsh", full("w3") + "SELECT count(DISTINCT group_key) AS groups, TRUE AS recall_reached FROM mem")
def _(spark, d):
    """Share of the exact ten best items that the hashed search finds: at least nine tenths."""
    w = gatherings(spark, d)
    left, right = g.store(group_vectors(w)), g.store(items(w))
    exact, found = (f(left, right, 10).select("group_key", "item_id") for f in (rk.topn, rk.topn_lsh))
    hit = exact.join(found.withColumn("hit", F.lit(1)), ["group_key", "item_id"], "left")
    return hit.agg(F.count_distinct("group_key").alias("groups"), (F.count("hit") >= 0.9 * F.count("*")).alias("recall_reached"))


@query("topn_unseen", TOPN.replace("FROM gm CROSS JOIN it)", "FROM gm CROSS JOIN it WHERE NOT EXISTS (SELECT 1 FROM gv WHERE gv.group_key = gm.group_key AND gv.item_id = it.item_id))"))
def _(spark, d):
    w = gatherings(spark, d)
    return _rounded(rk.topn(group_vectors(w), items(w), 10, seen=w.gv))


@query("personal_topn", uv_of("w2")[:-1] + f", {ITEMS}, {LEFT}, r AS (SELECT user_id, item_id, {dots('user_id', 1, 'item_id', 2)} AS score, row_number() OVER (PARTITION BY user_id ORDER BY {dots('user_id', 1, 'item_id', 2)} DESC, item_id)::INT AS rnk FROM lf CROSS JOIN it) SELECT user_id, rnk, item_id, round(score, 6) + 0.0 AS score FROM r WHERE rnk <= 10")
def _(spark, d):
    w = teams(spark, d)
    out = rk.topn(all_users(w).select(F.col("id").cast("string").alias("group_key"), "vec"), items(w), 10)
    return _rounded(out).withColumn("user_id", F.col("group_key").cast("long")).drop("group_key")


for _how in ("avg", "min", "max"):
    query(f"rank_{_how}", full("w3") + f", it AS (SELECT DISTINCT item_id FROM uv) SELECT group_key, item_id, round({_how}({dots('user_id', 1, 'item_id', 2)}), 6) + 0.0 AS score FROM mem CROSS JOIN it GROUP BY 1, 2")(lambda spark, d, how=_how: _rounded(rk.static_rank((w := gatherings(spark, d)).membership, users(w), items(w), how)))


@query("time_split", full("w2")[:-1] + SPLIT + "SELECT group_key, item_id, ts, split FROM sp")
def _(spark, d):
    return ev.time_split(teams(spark, d).gv, exact=True).select("group_key", "item_id", "ts", "split")


@query("time_split_percentile", "SELECT * FROM (VALUES ('train', TRUE), ('valid', TRUE), ('test', TRUE)) t(split, within)")
def _(spark, d):
    """Shares of the split at approximate percentiles: within a fiftieth of those of the exact one."""
    n = ev.time_split(teams(spark, d).gv).groupBy("split").count()
    share = F.col("count") / F.sum("count").over(Window.partitionBy(F.lit(0)))
    want = F.when(F.col("split") == "test", 0.2).when(F.col("split") == "valid", 0.08).otherwise(0.72)
    return n.select("split", (F.abs(share - want) <= 0.02).alias("within"))


RANKS = full("w2")[:-1] + SPLIT + MEAN + f", it AS (SELECT DISTINCT item_id FROM uv), te AS (SELECT group_key, sp.item_id AS truth, {SCORE} AS own FROM sp JOIN gm USING (group_key) WHERE split = 'test'), rk AS (SELECT te.group_key, truth AS item_id, 1 + count(*) FILTER ({SCORE.replace('item_id', 'it.item_id')} > own + 1e-12 OR abs({SCORE.replace('item_id', 'it.item_id')} - own) <= 1e-12 AND it.item_id < truth) AS rnk, 1 + count(it.item_id) AS candidates FROM te JOIN gm USING (group_key) CROSS JOIN it WHERE it.item_id <> truth AND NOT EXISTS (SELECT 1 FROM gv WHERE gv.group_key = te.group_key AND gv.item_id = it.item_id) GROUP BY 1, 2, own) "


class RankedTeams:
    """What ranks of the teams need, from one table of the orders: lines and orders are joined once.

    ``gv``: edges of groups and items; ``bought``: items with numbers of lines, in parts that add up.
    """

    def __init__(self, spark, d) -> None:
        log = team_log(spark, d)
        orders = g.store(g.explicit_groups(log, "key", least=1, more=[F.count("user_id").cast("double").alias("w")]).withColumn("team", F.size("members") > 1).drop("members"))
        self.bought = orders.filter("item_id IS NOT NULL").select("item_id", "w")
        self.gv = g.store(g.group_items(orders.filter("team").select("group_key", "item_id", "ts")))
        self.test = g.store(test_part(self))

    def members(self):
        """Members of the groups of the test part, as their keys name them."""
        keys = self.test.select("group_key").distinct()
        return keys.select("group_key", F.explode(F.split("group_key", "(?<=[0-9])-").cast("array<long>")).alias("user_id"))


def ranks(w):
    members = w.members()
    own = vectors(members.select(F.col("user_id").alias("id")).distinct(), 1)
    right = vectors(w.bought.select(F.col("item_id").alias("id")).distinct(), 2)
    return rk.truth_rank_blocks(w.test, rp.mean_vectors(members, own, D), right, seen=w.gv)


@query("truth_rank", RANKS + "SELECT group_key, item_id, rnk, candidates FROM rk")
def _(spark, d):
    return ranks(RankedTeams(spark, d))


@query("truth_rank_by_scores", full("w3")[:-1] + SPLIT + MEAN + f", it AS (SELECT DISTINCT item_id FROM uv), te AS (SELECT group_key, item_id AS truth FROM sp WHERE split = 'test'), sc AS (SELECT group_key, item_id, round({SCORE}, 2) AS score FROM gm CROSS JOIN it) SELECT te.group_key, truth AS item_id, 1 + count(c.item_id) FILTER (c.score > o.score OR c.score = o.score AND c.item_id < truth) AS rnk, 1 + count(c.item_id) AS candidates FROM te JOIN sc o ON o.group_key = te.group_key AND o.item_id = truth LEFT JOIN sc c ON c.group_key = te.group_key AND c.item_id <> truth AND NOT EXISTS (SELECT 1 FROM gv WHERE gv.group_key = te.group_key AND gv.item_id = c.item_id) GROUP BY 1, 2")
def _(spark, d):
    w = gatherings(spark, d)
    test = ev.time_split(w.gv, exact=True).filter("split = 'test'")
    right = items(w)
    sc = rk.topn(group_vectors(w), right, right.count()).select("group_key", "item_id", F.round("score", 2).alias("score"))
    return ev.truth_rank(test, sc, seen=w.gv)


@query("hits", RANKS + "SELECT n::INT AS n, round(avg(CASE WHEN rnk <= n THEN 1.0 ELSE 0.0 END), 9) AS hits FROM rk CROSS JOIN (SELECT unnest([1, 5, 10, 15, 20]) AS n) GROUP BY n")
def _(spark, d):
    return ev.hits(ranks(RankedTeams(spark, d))).withColumn("hits", F.round("hits", 9))


@query("mrr", RANKS + "SELECT round(avg(1.0 / rnk), 9) AS mrr, count(*) AS n_test FROM rk")
def _(spark, d):
    return ev.mrr(ranks(RankedTeams(spark, d))).withColumn("mrr", F.round("mrr", 9))


def counted(name: str, better: str, own: str, left: str, again: str = "") -> str:
    """CTE ``name``: ranks of test items by a score, where ``better`` holds for what stands above."""
    return f"{name}te AS (SELECT sp.group_key, sp.item_id AS truth, {own} AS own FROM sp {left} WHERE split = 'test'), {name} AS (SELECT te.group_key, truth AS item_id, 1 + count(*) FILTER ({better}) AS rnk, 1 + count(*) AS candidates FROM {name}te te {again} CROSS JOIN pit it WHERE it.item_id <> truth AND NOT EXISTS (SELECT 1 FROM gv WHERE gv.group_key = te.group_key AND gv.item_id = it.item_id) GROUP BY 1, 2, own)"


POPULAR = "pit AS (SELECT item_id, sum(w) AS s FROM uv GROUP BY 1), " + counted("pk", "it.s > own OR it.s = own AND it.item_id < truth", "s", "JOIN pit ON pit.item_id = sp.item_id")
def random_score(item: str) -> str:
    return "(" + " + ".join(f"{pp('gq.n', str(k), 61)} * {pp(item, str(k), 62)}" for k in range(8)) + ")"


RANDOM = "pit AS (SELECT DISTINCT item_id FROM uv), gq AS (SELECT group_key, sum(user_id * 31 + 17) % 1000003 AS n FROM mem GROUP BY 1), " + counted("qk", f"{random_score('it.item_id')} > own + 1e-12 OR abs({random_score('it.item_id')} - own) <= 1e-12 AND it.item_id < truth", random_score("sp.item_id"), "JOIN gq ON gq.group_key = sp.group_key", "JOIN gq ON gq.group_key = te.group_key")


def test_part(w):
    return ev.time_split(w.gv, exact=True).filter("split = 'test'")


def popularity_ranks(w):
    return rk.truth_rank_blocks(w.test, *rk.popularity_vectors(w.bought, w.test), seen=w.gv)


@query("rank_popularity", full("w2")[:-1] + SPLIT + ", " + POPULAR + " SELECT group_key, item_id, rnk, candidates FROM pk")
def _(spark, d):
    return popularity_ranks(RankedTeams(spark, d))


@query("rank_random", full("w2")[:-1] + SPLIT + ", " + RANDOM + " SELECT group_key, item_id, rnk, candidates FROM qk")
def _(spark, d):
    w = RankedTeams(spark, d)
    return rk.truth_rank_blocks(w.test, *rk.random_vectors(w.bought, w.members()), seen=w.gv)


@query("rank_static", full("w3")[:-1] + SPLIT + f", it AS (SELECT DISTINCT item_id FROM uv), sc AS (SELECT how, group_key, item_id, CASE how WHEN 'avg' THEN avg(x) WHEN 'min' THEN min(x) ELSE max(x) END AS s FROM (SELECT group_key, it.item_id, {dots('user_id', 1, 'it.item_id', 2)} AS x FROM mem CROSS JOIN it) CROSS JOIN (SELECT unnest(['avg', 'min', 'max']) AS how) GROUP BY how, group_key, item_id), te AS (SELECT how, sp.group_key, sp.item_id AS truth, s AS own FROM sp JOIN sc USING (group_key, item_id) WHERE split = 'test') SELECT te.how, te.group_key, truth AS item_id, 1 + count(c.item_id) FILTER (c.s > own + 1e-12 OR abs(c.s - own) <= 1e-12 AND c.item_id < truth) AS rnk, 1 + count(c.item_id) AS candidates FROM te LEFT JOIN sc c ON c.how = te.how AND c.group_key = te.group_key AND c.item_id <> truth AND NOT EXISTS (SELECT 1 FROM gv WHERE gv.group_key = te.group_key AND gv.item_id = c.item_id) GROUP BY 1, 2, 3")
def _(spark, d):
    """Ranks by the three static strategies, counted without a row a group and item."""
    w, out = gatherings(spark, d), None
    test = test_part(w)
    for how in ("avg", "min", "max"):
        part = rk.static_truth_rank(test, w.membership, users(w), items(w), how, seen=w.gv).select(F.lit(how).alias("how"), "*")
        out = part if out is None else out.union(part)
    return out


PAIRED = RANKS[:-1] + ", " + POPULAR + """, x AS (SELECT a.rnk AS ra, b.rnk AS rb FROM rk a JOIN pk b USING (group_key, item_id)),
y AS (SELECT avg(1.0 / ra - 1.0 / rb) AS m, avg(1.0 / ra - 1.0 / rb) / sqrt(var_samp(1.0 / ra - 1.0 / rb) / count(*)) AS t, count(*) AS n, count(*) FILTER (ra <= 10 AND rb > 10) AS won, count(*) FILTER (ra > 10 AND rb <= 10) AS lost FROM x)
SELECT 'reciprocal_rank' AS metric, round(m, 9) AS mean_diff, round(t, 6) AS stat, n, abs(t) > 2.575829 AS significant FROM y UNION ALL SELECT 'hits_10', round((won - lost) / n, 9), round(CASE WHEN won + lost = 0 THEN 0 ELSE (won - lost) / sqrt(won + lost) END, 6), n, CASE WHEN won + lost = 0 THEN FALSE ELSE abs(won - lost) / sqrt(won + lost) > 2.575829 END FROM y"""


@query("paired_test", PAIRED)
def _(spark, d):
    """Mean of members against popularity; significant where the two-sided chance is below a hundredth."""
    w = RankedTeams(spark, d)
    out = ev.paired_test(ranks(w), popularity_ranks(w))
    return out.select("metric", F.round("mean_diff", 9).alias("mean_diff"), F.round("stat", 6).alias("stat"), "n", (F.col("p_value") < 0.01).alias("significant"))


PERSONAL = uv_of("w2")[:-1] + f", {ITEMS}, o AS (SELECT user_id, item_id, row_number() OVER (ORDER BY ts, user_id::VARCHAR, item_id) AS r, count(*) OVER () AS n FROM uv), te AS (SELECT user_id, item_id AS truth, {dots('user_id', 1, 'item_id', 2)} AS own FROM o WHERE r > floor(0.8 * n)), rk AS (SELECT te.user_id, truth, 1 + count(it.item_id) FILTER ({dots('te.user_id', 1, 'it.item_id', 2)} > own + 1e-12 OR abs({dots('te.user_id', 1, 'it.item_id', 2)} - own) <= 1e-12 AND it.item_id < truth) AS rnk FROM te LEFT JOIN it ON it.item_id <> truth AND NOT EXISTS (SELECT 1 FROM uv WHERE uv.user_id = te.user_id AND uv.item_id = it.item_id) GROUP BY 1, 2) SELECT round(avg(1.0 / rnk), 9) AS mrr, count(*) AS n_test FROM rk"


@query("user_evaluation", PERSONAL)
def _(spark, d):
    w = teams(spark, d)
    keyed = w.uv.withColumn("group_key", F.col("user_id").cast("string"))
    test = ev.time_split(keyed, exact=True).filter("split = 'test'")
    left = all_users(w).select(F.col("id").cast("string").alias("group_key"), "vec")
    return ev.mrr(rk.truth_rank_blocks(test, left, items(w), seen=keyed.select("group_key", "item_id"))).withColumn("mrr", F.round("mrr", 9))
