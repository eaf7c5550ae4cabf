"""Graph, group, statistics, centrality and noise queries with SQL twins."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from crowdrank.operators import graph as g
from crowdrank.operators import sampling as s
from crowdrank.sources.workloads import WORKLOADS, crowds, gatherings, teams

#: CTEs of the three workloads; each is used by several twins.
W1 = """log AS (SELECT o_custkey AS user_id, l_partkey AS item_id, l_suppkey AS place, l_shipdate AS ts FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
ctx AS (SELECT DISTINCT user_id, place, date_trunc('week', ts) AS b FROM log),
uu AS (SELECT DISTINCT x.user_id AS src, y.user_id AS dst FROM ctx x JOIN ctx y ON x.place = y.place AND x.b = y.b AND x.user_id <> y.user_id),
cell AS (SELECT user_id, item_id, date_trunc('quarter', ts) AS bucket, max(ts) AS ts FROM log GROUP BY ALL)"""
W3 = """log AS (SELECT user_id, json_extract_string(props, '$.k')::BIGINT AS item_id, event_type, ts FROM events),
ctx AS (SELECT DISTINCT user_id, event_type AS place, epoch_us(ts) // 300000000 AS b FROM log),
uu AS (SELECT DISTINCT x.user_id AS src, y.user_id AS dst FROM ctx x JOIN ctx y ON x.place = y.place AND x.b = y.b AND x.user_id <> y.user_id),
cell AS (SELECT user_id, item_id, date_trunc('hour', ts) AS bucket, max(ts) AS ts FROM log GROUP BY ALL)"""
MINED = """, pr AS (SELECT x.item_id, x.bucket, x.user_id AS a, y.user_id AS b FROM cell x JOIN cell y ON x.item_id = y.item_id AND x.bucket = y.bucket AND x.user_id <> y.user_id JOIN uu ON uu.src = x.user_id AND uu.dst = y.user_id),
rch AS (SELECT item_id, bucket, a, a AS r FROM pr UNION SELECT pr.item_id, pr.bucket, pr.b, rch.r FROM rch JOIN pr ON pr.item_id = rch.item_id AND pr.bucket = rch.bucket AND pr.a = rch.a),
cmp AS (SELECT item_id, bucket, a AS user_id, min(r) AS root FROM rch GROUP BY ALL),
rec AS (SELECT string_agg(user_id::VARCHAR, '-' ORDER BY user_id) AS group_key, cmp.item_id, max(ts) AS ts, list(user_id ORDER BY user_id) AS members FROM cmp JOIN cell USING (item_id, bucket, user_id) GROUP BY cmp.item_id, cmp.bucket, root)"""
W2 = """log AS (SELECT l_suppkey AS user_id, o_custkey AS item_id, o_orderdate AS ts, o_orderkey AS k FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
uu AS (SELECT x.s_suppkey AS src, y.s_suppkey AS dst FROM supplier x JOIN supplier y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey <> y.s_suppkey),
rec AS (SELECT string_agg(DISTINCT user_id::VARCHAR, '-' ORDER BY user_id::VARCHAR) AS unordered, array_to_string(list_sort(list(DISTINCT user_id)), '-') AS group_key, list_sort(list(DISTINCT user_id)) AS members, item_id, max(ts) AS ts FROM log GROUP BY k, item_id HAVING count(DISTINCT user_id) >= 2)"""
W2 = W2.replace("string_agg(DISTINCT user_id::VARCHAR, '-' ORDER BY user_id::VARCHAR) AS unordered, ", "")
BASE = {"w1": W1 + MINED, "w2": W2, "w3": W3 + MINED}
TAIL = ", uv AS (SELECT user_id, item_id, count(*)::DOUBLE AS w, min(ts) AS ts FROM log GROUP BY user_id, item_id), gv AS (SELECT group_key, item_id, 1.0::DOUBLE AS w, min(ts) AS ts FROM rec GROUP BY group_key, item_id), mem AS (SELECT DISTINCT group_key, unnest(members) AS user_id FROM rec)"


def full(w: str) -> str:
    return "WITH RECURSIVE " + BASE[w] + TAIL + " "


def uv_of(w: str) -> str:
    return "WITH " + {"w1": W1, "w2": W2, "w3": W3}[w] + ", uv AS (SELECT user_id, item_id, count(*)::DOUBLE AS w, min(ts) AS ts FROM log GROUP BY user_id, item_id) "


QUERIES, SQL = {}, {}


def query_maker(queries: dict, twins: dict):
    """A decorator that registers a query and, if given, its SQL twin."""

    def query(name: str, sql: str | None = None):
        def add(f):
            queries[name] = f
            if sql:
                twins[name] = sql
            return f

        return add

    return query


query = query_maker(QUERIES, SQL)


for _w, _build in WORKLOADS.items():
    query(f"uv_edges_{_w}", uv_of(_w) + "SELECT user_id, item_id, w, ts FROM uv")(lambda spark, d, b=_build: b(spark, d).uv)
    query(f"ties_{_w}", uv_of(_w) + "SELECT src, dst FROM uu")(lambda spark, d, b=_build: b(spark, d).uu)
    query(f"groups_{_w}", full(_w) + "SELECT group_key, item_id, ts, len(members)::INT AS n FROM rec")(lambda spark, d, b=_build: b(spark, d).records.select("group_key", "item_id", "ts", F.size("members").alias("n")))
    query(f"stats_{_w}", full(_w) + """SELECT (SELECT count(DISTINCT user_id) FROM uv) AS users, (SELECT count(DISTINCT group_key) FROM gv) AS groups, (SELECT count(DISTINCT item_id) FROM uv) AS items,
      (SELECT round(count(*) / count(DISTINCT group_key), 6) FROM mem) AS avg_group_size, (SELECT round(count(*) / count(DISTINCT group_key), 6) FROM gv) AS interactions_per_group,
      (SELECT round(count(*) / count(DISTINCT user_id), 6) FROM uv) AS items_per_user, round((SELECT count(*) FROM uu) / (SELECT count(DISTINCT user_id) FROM uv), 6) AS friends_per_user""")(lambda spark, d, b=_build: _stats(b(spark, d)))


def _stats(w):
    return g.graph_stats(w.uv, w.gv, w.membership, w.degree)


@query("group_items_w2", full("w2") + "SELECT group_key, item_id, w, ts FROM gv")
def _(spark, d):
    return teams(spark, d).gv


@query("groups_pairwise_w1", "WITH RECURSIVE " + W1 + MINED + ", q AS (SELECT a, b, item_id, bucket FROM pr WHERE a < b) SELECT q.a || '-' || q.b AS group_key, q.item_id, greatest(x.ts, y.ts) AS ts FROM q JOIN cell x ON x.user_id = q.a AND x.item_id = q.item_id AND x.bucket = q.bucket JOIN cell y ON y.user_id = q.b AND y.item_id = q.item_id AND y.bucket = q.bucket")
def _(spark, d):
    from crowdrank.sources.workloads import purchases

    log = purchases(spark, d).select(F.col("o_custkey").alias("user_id"), F.col("l_partkey").alias("item_id"), F.col("l_suppkey").alias("place"), F.col("l_shipdate").alias("ts"))
    uu = g.derive_ties(log, ["place", F.date_trunc("week", "ts").alias("week")])
    return g.mine_groups(log, uu, [F.col("item_id"), F.date_trunc("quarter", "ts").alias("bucket")], mode="pairwise").select("group_key", "item_id", "ts")


CLIQUES = full("w3") + """, adj AS (SELECT item_id, bucket, a AS u, list(DISTINCT b) AS ns FROM pr GROUP BY ALL),
cq AS (SELECT item_id, bucket, [u] AS members FROM adj UNION ALL SELECT c.item_id, c.bucket, list_append(c.members, j.u) FROM cq c JOIN adj j ON j.item_id = c.item_id AND j.bucket = c.bucket AND j.u > c.members[-1] AND list_has_all(j.ns, c.members)),
mx AS (SELECT * FROM cq c WHERE len(members) >= 2 AND NOT EXISTS (SELECT 1 FROM adj j WHERE j.item_id = c.item_id AND j.bucket = c.bucket AND NOT list_contains(c.members, j.u) AND list_has_all(j.ns, c.members)))
SELECT array_to_string(members, '-') AS group_key, m.item_id, max(cell.ts) AS ts FROM mx m JOIN cell ON cell.item_id = m.item_id AND cell.bucket = m.bucket AND list_contains(m.members, cell.user_id) GROUP BY m.item_id, m.bucket, m.members"""


@query("groups_clique_w3", CLIQUES)
def _(spark, d):
    return gatherings(spark, d, mode="clique").records.select("group_key", "item_id", "ts")


@query("canonical_groups_w2", full("w2") + "SELECT DISTINCT group_key, len(members)::INT AS n FROM rec")
def _(spark, d):
    return g.canonical_groups(teams(spark, d).records).select("group_key", "n")


@query("group_ids_w2", full("w2") + "SELECT count(DISTINCT group_key) AS n, TRUE AS no_collision FROM rec")
def _(spark, d):
    """Hashed group ids stand for one member set each."""
    ids = g.canonical_groups(teams(spark, d).records)
    return ids.agg(F.count_distinct("group_key").alias("n"), (F.count_distinct("group_key") == F.count_distinct("group_id")).alias("no_collision"))


@query("ties_tau_w1", "WITH " + W1 + " SELECT x.user_id AS src, y.user_id AS dst FROM ctx x JOIN ctx y ON x.place = y.place AND x.b = y.b AND x.user_id <> y.user_id GROUP BY 1, 2 HAVING count(*) >= 2")
def _(spark, d):
    from crowdrank.sources.workloads import purchases

    log = purchases(spark, d).select(F.col("o_custkey").alias("user_id"), F.col("l_suppkey").alias("place"), F.col("l_shipdate").alias("ts"))
    return g.derive_ties(log, ["place", F.date_trunc("week", "ts").alias("week")], tau=2)


@query("ties_symmetrised", "WITH p AS (SELECT l_suppkey AS a, l_partkey % 100 AS b FROM lineitem) SELECT a AS src, b AS dst FROM p WHERE a <> b UNION SELECT b, a FROM p WHERE a <> b")
def _(spark, d):
    return g.symmetrise(spark.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") % 100).alias("dst")))


@query("degrees_items", uv_of("w1") + "SELECT item_id AS id, sum(w) AS degree FROM uv GROUP BY 1")
def _(spark, d):
    return g.degrees(crowds(spark, d).uv, "item_id")


@query("uv_binary_w2", uv_of("w2") + "SELECT user_id, item_id, 1.0::DOUBLE AS w FROM uv")
def _(spark, d):
    from crowdrank.sources.workloads import purchases

    log = purchases(spark, d).select(F.col("l_suppkey").alias("user_id"), F.col("o_custkey").alias("item_id"), F.col("o_orderdate").alias("ts"))
    return g.build_uv(log, "binary").drop("ts")


@query("density", full("w2") + """SELECT 'uv' AS graph, count(*) AS edges, round(count(*) / (count(DISTINCT user_id) * count(DISTINCT item_id)), 9) AS density, round(count(*) / count(DISTINCT user_id), 6) AS per_left FROM uv
 UNION ALL SELECT 'gv', count(*), round(count(*) / (count(DISTINCT group_key) * count(DISTINCT item_id)), 9), round(count(*) / count(DISTINCT group_key), 6) FROM gv""")
def _(spark, d):
    w = teams(spark, d)
    return g.density(w.uv, "user_id", "item_id").select(F.lit("uv").alias("graph"), "*").union(g.density(w.gv, "group_key", "item_id").select(F.lit("gv").alias("graph"), "*"))


SPLIT = ", o AS (SELECT *, row_number() OVER (ORDER BY ts, group_key, item_id) AS r, count(*) OVER () AS n FROM gv), sp AS (SELECT *, CASE WHEN r > floor(0.8 * n) THEN 'test' WHEN r > floor(0.8 * n) - floor(0.1 * floor(0.8 * n)) THEN 'valid' ELSE 'train' END AS split FROM o) "


@query("cold_groups", full("w2")[:-1] + SPLIT + "SELECT DISTINCT group_key FROM sp WHERE split = 'test' AND group_key NOT IN (SELECT group_key FROM sp WHERE split <> 'test')")
def _(spark, d):
    from crowdrank.operators.evaluate import time_split

    sp = time_split(teams(spark, d).gv, exact=True)
    return g.cold_flags(sp.filter("split = 'test'"), sp.filter("split <> 'test'"))


@query("cold_members", full("w2")[:-1] + SPLIT + ", m AS (SELECT DISTINCT group_key, unnest(members) AS user_id FROM rec), kn AS (SELECT DISTINCT user_id FROM m WHERE group_key IN (SELECT group_key FROM sp WHERE split <> 'test')) SELECT group_key, count(*) AS members, count(*) FILTER (user_id NOT IN (SELECT user_id FROM kn)) AS new_members FROM m WHERE group_key IN (SELECT group_key FROM sp WHERE split = 'test') GROUP BY 1")
def _(spark, d):
    """Members of test groups without any group history."""
    from crowdrank.operators.evaluate import time_split

    w = teams(spark, d)
    sp = time_split(w.gv, exact=True).join(g.canonical_groups(w.records).select("group_key", "members"), "group_key")
    return g.cold_members(sp.filter("split = 'test'"), sp.filter("split <> 'test'"))


# --- centralities


def _small(spark, d):
    """A connected sample graph: suppliers linked by nation and by consecutive keys."""
    sup = spark.read.parquet(f"{d}/supplier.parquet").select(F.col("s_suppkey").alias("user_id"), F.col("s_nationkey").alias("place"))
    chain = sup.select(F.col("user_id").alias("src"), (F.col("user_id") + 1).alias("dst")).join(sup.select(F.col("user_id").alias("dst")), "dst", "left_semi")
    return g.store(g.symmetrise(g.derive_ties(sup, ["place"]).union(chain.select("src", "dst"))))


SMALL = """base AS (SELECT x.s_suppkey AS src, y.s_suppkey AS dst FROM supplier x JOIN supplier y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey <> y.s_suppkey UNION SELECT x.s_suppkey, y.s_suppkey FROM supplier x JOIN supplier y ON y.s_suppkey = x.s_suppkey + 1),
uu AS (SELECT src, dst FROM base UNION SELECT dst, src FROM base)"""


@query("degree_centrality", "WITH " + W1 + " SELECT src AS user_id, count(*)::DOUBLE AS score FROM uu GROUP BY 1")
def _(spark, d):
    return g.centrality_degree(crowds(spark, d).uu)


def _unrolled(step, start: str, n: int) -> str:
    """CTEs s1..sn of a fixed number of rounds."""
    return start + "".join(", " + step(i) for i in range(1, n + 1))


PAGERANK = "WITH " + W1 + ", deg AS (SELECT src, count(*) AS k FROM uu GROUP BY 1), nn AS (SELECT count(*) AS n FROM deg), s0 AS MATERIALIZED (SELECT src AS id, 1.0 / n AS x FROM deg, nn)" + _unrolled(lambda i: f"s{i} AS MATERIALIZED (SELECT uu.dst AS id, 0.15 / any_value(n) + 0.85 * sum(p.x / k) AS x FROM uu JOIN s{i - 1} p ON p.id = uu.src JOIN deg ON deg.src = uu.src CROSS JOIN nn GROUP BY 1)", "", 10)


@query("pagerank_10", PAGERANK + " SELECT id AS user_id, round(x, 9) AS score FROM s10")
def _(spark, d):
    return g.centrality_pagerank(g.store(crowds(spark, d).uu), iters=10).withColumn("score", F.round("score", 9))


@query("eigenvector_10", "WITH " + SMALL + ", s0 AS MATERIALIZED (SELECT DISTINCT src AS id, 1.0::DOUBLE AS x FROM uu)" + _unrolled(lambda i: f"s{i} AS MATERIALIZED (SELECT id, y / max(y) OVER () AS x FROM (SELECT uu.dst AS id, sum(p.x) AS y FROM uu JOIN s{i - 1} p ON p.id = uu.src GROUP BY 1))", "", 10) + " SELECT id AS user_id, round(x, 6) AS score FROM s10")
def _(spark, d):
    return g.centrality_eigenvector(_small(spark, d), iters=10).withColumn("score", F.round("score", 6))


@query("eigenvector_w1", "WITH " + W1 + ", s0 AS MATERIALIZED (SELECT DISTINCT src AS id, 1.0::DOUBLE AS x FROM uu)" + _unrolled(lambda i: f"s{i} AS MATERIALIZED (SELECT id, y / max(y) OVER () AS x FROM (SELECT uu.dst AS id, sum(p.x) AS y FROM uu JOIN s{i - 1} p ON p.id = uu.src GROUP BY 1))", "", 5) + " SELECT id AS user_id, round(x, 6) AS score FROM s5")
def _(spark, d):
    return g.centrality_eigenvector(g.store(crowds(spark, d).uu), iters=5).withColumn("score", F.round("score", 6))


BFS = "WITH RECURSIVE " + SMALL + ", walk AS (SELECT DISTINCT src AS s, src AS v, 0 AS dist FROM uu UNION SELECT s, uu.dst, dist + 1 FROM walk JOIN uu ON uu.src = walk.v WHERE dist < 12), lv AS (SELECT s, v, min(dist) AS dist FROM walk GROUP BY 1, 2)"


@query("closeness_small", BFS + ", nn AS (SELECT count(DISTINCT src) AS n FROM uu) SELECT v AS user_id, round(count(*) / sum(dist) * count(*) / any_value(n - 1), 6) AS score FROM lv, nn WHERE dist > 0 GROUP BY 1")
def _(spark, d):
    return g.centrality_closeness(_small(spark, d)).withColumn("score", F.round("score", 6))


SIGMA = BFS + ", sg AS (SELECT s, v, dist, 1.0::DOUBLE AS sigma FROM lv WHERE dist = 0 UNION ALL SELECT sg.s, lv.v, lv.dist, sum(sg.sigma) FROM sg JOIN uu ON uu.src = sg.v JOIN lv ON lv.s = sg.s AND lv.v = uu.dst AND lv.dist = sg.dist + 1 GROUP BY sg.s, lv.v, lv.dist)"


@query("betweenness_small", SIGMA + """, st AS (SELECT a.s, a.v AS t, b.v AS u, a.sigma AS total, b.sigma * c.sigma AS through FROM sg a JOIN sg b ON b.s = a.s AND b.v <> a.s AND b.v <> a.v JOIN sg c ON c.s = a.v AND c.v = b.v AND b.dist + c.dist = a.dist)
 SELECT n.src AS user_id, round(coalesce(x.b, 0), 4) AS score FROM (SELECT DISTINCT src FROM uu) n LEFT JOIN (SELECT u, sum(through / total) / 2 AS b FROM st GROUP BY u) x ON x.u = n.src""")
def _(spark, d):
    return g.centrality_betweenness(_small(spark, d)).withColumn("score", F.round("score", 4))


PICKED = ", pick AS (SELECT src AS id FROM (SELECT DISTINCT src FROM uu) ORDER BY (src * 7919 + 1299709) % 1000003, src LIMIT 16)"


@query("betweenness_pivots", SIGMA + PICKED + """, st AS (SELECT a.s, a.v AS t, b.v AS u, a.sigma AS total, b.sigma * c.sigma AS through FROM sg a JOIN pick ON pick.id = a.s JOIN sg b ON b.s = a.s AND b.v <> a.s AND b.v <> a.v JOIN sg c ON c.s = a.v AND c.v = b.v AND b.dist + c.dist = a.dist)
 SELECT n.src AS user_id, round(coalesce(x.b, 0) * (SELECT count(DISTINCT src) FROM uu) / (SELECT count(*) FROM pick), 3) AS score FROM (SELECT DISTINCT src FROM uu) n LEFT JOIN (SELECT u, sum(through / total) / 2 AS b FROM st GROUP BY u) x ON x.u = n.src""")
def _(spark, d):
    """Sixteen sources instead of all; on smaller graphs every node is one."""
    uu = _small(spark, d)
    return g.centrality_betweenness(uu, pivots=min(16, uu.select("src").distinct().count())).withColumn("score", F.round("score", 3))


def landmark_sql(graph: str) -> str:
    return graph + PICKED + ", walk AS (SELECT id AS s, id AS v, 0 AS dist FROM pick UNION SELECT s, uu.dst, dist + 1 FROM walk JOIN uu ON uu.src = walk.v WHERE dist < 12), lv AS (SELECT s, v, min(dist) AS dist FROM walk GROUP BY 1, 2), c AS (SELECT v, count(*) AS n, sum(dist) AS total FROM lv WHERE dist > 0 GROUP BY 1) SELECT src AS user_id, round(coalesce(n / total * n / 16.0, 0), 6) AS score FROM (SELECT DISTINCT src FROM uu) LEFT JOIN c ON c.v = src"


@query("closeness_landmarks", landmark_sql("WITH RECURSIVE " + SMALL))
def _(spark, d):
    return g.centrality_closeness(_small(spark, d), landmarks=16).withColumn("score", F.round("score", 6))


@query("closeness_landmarks_w1", landmark_sql("WITH RECURSIVE " + W1))
def _(spark, d):
    """Landmarks keep closeness affordable on the whole social network of the crowds."""
    return g.centrality_closeness(g.store(crowds(spark, d).uu), landmarks=16).withColumn("score", F.round("score", 6))


HARMONIC = BFS + " SELECT s AS user_id, round(sum(CASE WHEN dist > 0 THEN 1.0 / dist ELSE 0 END), 6) AS score"


@query("harmonic_small", HARMONIC + " FROM lv GROUP BY 1")
def _(spark, d):
    return g.centrality_harmonic(_small(spark, d)).withColumn("score", F.round("score", 6))


@query("closeness_sketch", HARMONIC + ", TRUE AS within FROM lv GROUP BY 1")
def _(spark, d):
    """The sketched sum against the exact one: within a twentieth for every user."""
    uu = _small(spark, d)
    both = g.centrality_harmonic(uu).join(g.centrality_closeness_sketch(uu).withColumnRenamed("score", "sketched"), "user_id")
    return both.select("user_id", F.round("score", 6).alias("score"), (F.abs(F.col("sketched") - F.col("score")) <= 0.05 * F.col("score") + 1e-9).alias("within"))


@query("top_neighbours_degree", "WITH " + W1 + ", sc AS (SELECT src AS user_id, count(*)::DOUBLE AS score FROM uu GROUP BY 1) SELECT * FROM (SELECT src AS user_id, row_number() OVER (PARTITION BY src ORDER BY score DESC, dst)::INT AS rnk, dst AS nbr, score FROM uu JOIN sc ON sc.user_id = dst) WHERE rnk <= 4")
def _(spark, d):
    uu = crowds(spark, d).uu
    return g.top_neighbours(uu, g.centrality_degree(uu), 4)


@query("top_neighbours_pagerank", PAGERANK + " SELECT user_id, rnk, nbr FROM (SELECT src AS user_id, row_number() OVER (PARTITION BY src ORDER BY round(x, 9) DESC, dst)::INT AS rnk, dst AS nbr FROM uu JOIN s10 ON s10.id = dst) WHERE rnk <= 4")
def _(spark, d):
    uu = g.store(crowds(spark, d).uu)
    scores = g.centrality_pagerank(uu, iters=10).withColumn("score", F.round("score", 9))
    return g.top_neighbours(uu, scores, 4).drop("score")


@query("uniform_neighbours", "WITH " + W1 + " SELECT * FROM (SELECT src AS user_id, row_number() OVER (PARTITION BY src ORDER BY (src * 7919 + dst * 104729 + 1299709) % 1000003, dst)::INT AS rnk, dst AS nbr FROM uu) WHERE rnk <= 4")
def _(spark, d):
    return g.sample_neighbours(crowds(spark, d).uu, 4, seed=1)


WALKS = "WITH " + SMALL + " SELECT src, walk::INT AS walk, 6::INT AS nodes, TRUE AS along_ties FROM (SELECT DISTINCT src FROM uu) CROSS JOIN (SELECT unnest(range(1, 3)) AS walk)"


def walk_checks(uu, walks):
    """Length of each walk, and whether each of its steps is a tie."""
    steps = walks.select("src", "walk", "path", F.posexplode(F.slice("path", 1, 5)).alias("i", "a")).select("src", "walk", F.col("a").alias("x"), F.element_at("path", F.col("i") + 2).alias("y"))
    ties = uu.select(F.col("src").alias("x"), F.col("dst").alias("y"), F.lit(1).alias("tie"))
    checked = steps.join(ties, ["x", "y"], "left").groupBy("src", "walk").agg(F.count("tie").alias("ties"))
    return walks.join(checked, ["src", "walk"]).select("src", "walk", F.size("path").alias("nodes"), (F.col("ties") == 5).alias("along_ties"))


@query("random_walks", WALKS)
def _(spark, d):
    uu = _small(spark, d)
    return walk_checks(uu, g.store(g.walk_corpus(uu, length=6)))


@query("random_walks_w1", "WITH " + W1 + " SELECT src, 1::INT AS walk, 6::INT AS nodes, TRUE AS along_ties FROM (SELECT DISTINCT src FROM uu)")
def _(spark, d):
    uu = g.store(crowds(spark, d).uu)
    return walk_checks(uu, g.store(g.walk_corpus(uu, length=6, per_node=1)))


@query("biased_walks", WALKS)
def _(spark, d):
    uu = _small(spark, d)
    return walk_checks(uu, g.store(g.walk_corpus(uu, length=6, p=0.5, q=2.0)))


@query("walk_embedding", "WITH " + SMALL + " SELECT DISTINCT src AS user_id, 8::INT AS d, TRUE AS finite FROM uu")
def _(spark, d):
    v = g.walk_embedding(g.walk_corpus(_small(spark, d), length=6), d=8)
    return v.select("user_id", F.size("vec").alias("d"), F.forall("vec", lambda x: ~F.isnan(x) & (F.abs(x) < 1e9)).alias("finite"))


# --- noise distributions


def _noise(table: str) -> str:
    return f"SELECT item_id, round(mass, 6) AS mass, round(p, 9) AS p, round(hi - p, 9) AS lo, round(hi, 9) AS hi FROM (SELECT item_id, mass, mass / sum(mass) OVER () AS p, sum(mass) OVER (ORDER BY item_id) / sum(mass) OVER () AS hi FROM {table})"


def _rounded(df):
    return df.select("item_id", F.round("mass", 6).alias("mass"), *[F.round(c, 9).alias(c) for c in ("p", "lo", "hi")])


@query("noise_degree_uv", uv_of("w2")[:-1] + ", m AS (SELECT item_id, pow(sum(w), 0.75) AS mass FROM uv GROUP BY 1) " + _noise("m"))
def _(spark, d):
    return _rounded(s.degree_noise(teams(spark, d).uv))


@query("noise_degree_gv", full("w2")[:-1] + ", m AS (SELECT item_id, pow(sum(w), 0.75) AS mass FROM gv GROUP BY 1) " + _noise("m"))
def _(spark, d):
    return _rounded(s.degree_noise(teams(spark, d).gv))


@query("noise_uniform", uv_of("w2")[:-1] + ", m AS (SELECT DISTINCT item_id, 1.0::DOUBLE AS mass FROM uv) " + _noise("m"))
def _(spark, d):
    return _rounded(s.uniform_noise(teams(spark, d).uv))


@query("noise_group_aware", full("w3") + ", pop AS (SELECT group_key, item_id, sum(w) AS pop FROM mem JOIN uv USING (user_id) GROUP BY 1, 2), t AS (SELECT group_key, sum(pow(pop + 1, 0.75)) AS m, count(*) AS k FROM pop GROUP BY 1), nn AS (SELECT count(DISTINCT item_id) AS n FROM uv) SELECT group_key, item_id, pop, round(pow(pop + 1, 0.75), 6) AS mass, round(pow(pop + 1, 0.75) / (m + (n - k)), 9) AS p FROM pop JOIN t USING (group_key) CROSS JOIN nn")
def _(spark, d):
    w = gatherings(spark, d)
    return s.group_aware_noise(w.membership, w.uv, gamma=1.0).select("group_key", "item_id", "pop", F.round("mass", 6).alias("mass"), F.round("p", 9).alias("p"))


@query("noise_report", uv_of("w2")[:-1] + ", m AS (SELECT item_id, pow(sum(w), 0.75) AS mass, sum(w) AS pop FROM uv GROUP BY 1), q AS (SELECT *, mass / sum(mass) OVER () AS p, count(*) OVER () AS n FROM m) SELECT count(*) AS n, round(-sum(p * ln(p)), 6) AS entropy, round(var_pop(p) * 1e9, 6) AS variance_e9, round(sum(abs(p - 1.0 / n)) / 2, 6) AS from_uniform, round(sum(p * pop), 6) AS mean_popularity FROM q")
def _(spark, d):
    uv = teams(spark, d).uv
    return s.noise_report(s.degree_noise(uv), g.degrees(uv, "item_id"))


DRAWS = uv_of("w2")[:-1] + ", m AS (SELECT item_id, pow(sum(w), 0.75) AS mass FROM uv GROUP BY 1), ns AS (SELECT item_id, round(coalesce(lag(c) OVER (ORDER BY item_id), 0), 12) AS lo, round(c, 12) AS hi FROM (SELECT item_id, sum(mass) OVER (ORDER BY item_id) / sum(mass) OVER () AS c FROM m)), q AS (SELECT user_id, item_id AS pos, slot, ((user_id * 7919 + item_id * 104729 + slot * 1299709) % 1000003 + 0.5) / 1000003.0 AS u FROM uv, (SELECT unnest(range(0, 2)) AS slot)) SELECT q.user_id, q.pos, q.slot::INT AS slot, ns.item_id AS neg FROM q JOIN ns ON q.u >= ns.lo AND q.u < ns.hi"


@query("negatives_drawn", DRAWS)
def _(spark, d):
    uv = teams(spark, d).uv
    return s.draw_negatives(uv.select("user_id", F.col("item_id").alias("pos")), s.degree_noise(uv), 2).select("user_id", "pos", "slot", "neg")


UNSEEN = DRAWS[: DRAWS.rindex(", q AS (")] + """, q AS (SELECT user_id, item_id AS pos, slot, k, ((user_id * 7919 + item_id * 104729 + (slot + k * 2) * 1299709) % 1000003 + 0.5) / 1000003.0 AS u FROM uv, (SELECT unnest(range(0, 2)) AS slot), (SELECT unnest(range(0, 4)) AS k)),
dr AS (SELECT q.user_id, q.pos, q.slot, q.k, ns.item_id AS neg, CASE WHEN EXISTS (SELECT 1 FROM uv o WHERE o.user_id = q.user_id AND o.item_id = ns.item_id) THEN 1 ELSE 0 END AS hit FROM q JOIN ns ON q.u >= ns.lo AND q.u < ns.hi)
SELECT user_id, pos, slot::INT AS slot, neg FROM dr QUALIFY row_number() OVER (PARTITION BY user_id, pos, slot ORDER BY hit, k) = 1"""


@query("negatives_unobserved", UNSEEN)
def _(spark, d):
    """Draws that a user has touched are drawn again."""
    uv = teams(spark, d).uv
    return s.draw_negatives(uv.select("user_id", F.col("item_id").alias("pos")), s.degree_noise(uv), 2, observed=uv, tries=4).select("user_id", "pos", "slot", "neg")


@query("softmax_groups_window", full("w2") + ", x AS (SELECT group_key, user_id, (user_id % 7)::DOUBLE AS i FROM mem) SELECT group_key, user_id, round(exp(i - max(i) OVER p) / sum(exp(i)) OVER p * exp(max(i) OVER p), 9) AS weight FROM x WINDOW p AS (PARTITION BY group_key)")
def _(spark, d):
    m = teams(spark, d).membership.withColumn("i", (F.col("user_id") % 7).cast("double"))
    p = Window.partitionBy("group_key")
    e = F.exp(F.col("i") - F.max("i").over(p))
    return m.withColumn("e", e).select("group_key", "user_id", F.round(F.col("e") / F.sum("e").over(p), 9).alias("weight"))
