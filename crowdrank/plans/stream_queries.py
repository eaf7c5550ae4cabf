"""Streams replayed to their end, with batch SQL over the same rows as twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from crowdrank.operators import rank as rk
from crowdrank.operators import represent as rp
from crowdrank.plans.graph_queries import query_maker
from crowdrank.plans.model_queries import pp, vectors
from crowdrank.streaming import events as ev

QUERIES, SQL = {}, {}
query = query_maker(QUERIES, SQL)
LOG = "WITH e AS (SELECT event_id, user_id, json_extract_string(props, '$.k')::BIGINT AS k, ts, epoch_us(ts) AS us FROM events) "


def _events(spark, d):
    return ev.source(spark, ev.replay(spark, f"{d}/events.parquet", 3))


@query("stream_tumbling_groups", LOG + "SELECT us // 3600000000 * 3600000000 AS start_us, k, count(DISTINCT user_id)::INT AS n FROM e GROUP BY 1, 2")
def _(spark, d):
    return ev.drain(ev.tumbling_groups(_events(spark, d)), "complete").drop("_batch")


@query("stream_sliding_groups", LOG + "SELECT (us // 900000000 - o) * 900000000 AS start_us, k, count(DISTINCT user_id)::INT AS n FROM e, (SELECT unnest(range(0, 4)) AS o) GROUP BY 1, 2")
def _(spark, d):
    return ev.drain(ev.tumbling_groups(_events(spark, d), slide="15 minutes"), "complete").drop("_batch")


@query("stream_session_groups", LOG + ", s AS (SELECT *, CASE WHEN us - lag(us) OVER w >= 1800000000 OR lag(us) OVER w IS NULL THEN 1 ELSE 0 END AS f FROM e WINDOW w AS (PARTITION BY user_id ORDER BY us)), g AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS s FROM s) SELECT user_id, min(us) AS start_us, count(*) AS n FROM g GROUP BY user_id, s")
def _(spark, d):
    return ev.drain(ev.sessions(_events(spark, d)), "complete").drop("_batch")


@query("stream_popularity", LOG + "SELECT k, count(*) AS n FROM e GROUP BY 1")
def _(spark, d):
    return ev.drain(ev.popularity(_events(spark, d)), "complete").drop("_batch")


@query("stream_dedup", LOG + "SELECT DISTINCT user_id, k FROM e")
def _(spark, d):
    return ev.drain(ev.first_touches(_events(spark, d)), "append").drop("_batch")


@query("stream_dedup_watermark", LOG + "SELECT event_id, user_id, k FROM e")
def _(spark, d):
    return ev.drain(ev.repeats_within(_events(spark, d)), "append").drop("_batch")


@query("stream_running_degree", LOG + "SELECT user_id, count(*) AS degree FROM e GROUP BY 1")
def _(spark, d):
    out = ev.drain(ev.running_degree(_events(spark, d)), "update")
    return out.groupBy("user_id").agg(F.max("degree").alias("degree"))


#: Six files of equal spans, one a batch; every twentieth row comes two files later. A row is lost if the
#: watermark that the batch before used has passed its window; the last watermark closes what is written.
LATE = LOG + """, b AS (SELECT min(us) AS lo, max(us) AS hi FROM e),
f AS (SELECT e.*, us // 3600000000 * 3600000000 AS st, least((us - lo) * 6 // (hi - lo + 1) + CASE WHEN event_id % 20 = 0 THEN 2 ELSE 0 END, 5) AS batch FROM e, b),
w AS (SELECT a AS batch, (SELECT max(us) // 1000 * 1000 - 1800000000 FROM f WHERE f.batch <= a - 2) AS passed FROM range(0, 6) t(a)),
z AS (SELECT max(us) // 1000 * 1000 - 1800000000 AS last FROM f)
SELECT st AS start_us, k, count(DISTINCT user_id)::INT AS n FROM f JOIN w USING (batch), z WHERE st + 3600000000 > coalesce(passed, 0) AND st + 3600000000 <= last GROUP BY 1, 2"""


@query("stream_late_rows", LATE)
def _(spark, d):
    """Groups of a replay whose every twentieth row is late: append mode, closed windows only."""
    src = ev.source(spark, ev.replay(spark, f"{d}/events.parquet", 6, late_every=20, late_by=2), files=1)
    return ev.drain(ev.tumbling_groups(src, late="30 minutes"), "append").drop("_batch")


SERVED = LOG + ", u AS (SELECT DISTINCT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') || ':' || k AS group_key, user_id FROM e), gm AS (SELECT group_key, " + ", ".join(f"avg({pp('user_id', str(k), 1)}) AS g{k}" for k in range(4)) + " FROM u GROUP BY 1), r AS (SELECT group_key, i AS item_id, " + " + ".join(f"g{k} * {pp('i', str(k), 2)}" for k in range(4)) + " AS score FROM gm CROSS JOIN range(0, 100) t(i)) SELECT group_key, rnk, item_id, round(score, 6) + 0.0 AS score FROM (SELECT *, row_number() OVER (PARTITION BY group_key ORDER BY score DESC, item_id)::INT AS rnk FROM r) WHERE rnk <= 3"


@query("stream_serving", SERVED)
def _(spark, d):
    """Occasional groups of each micro-batch joined with stored vectors and ranked."""
    e = spark.read.parquet(f"{d}/events.parquet")
    users = vectors(e.select(F.col("user_id").alias("id")).distinct(), 1)
    items = vectors(spark.range(100), 2)

    def serve(batch, _):
        pairs = batch.select(F.concat_ws(":", F.date_trunc("hour", "ts").cast("string"), "k").alias("group_key"), "user_id").distinct()
        mean = pairs.join(pairs.groupBy("group_key").count(), "group_key").select("group_key", "user_id", (1 / F.col("count")).alias("weight"))
        return rk.topn(rp.weighted_sum(pairs, mean, users), items, 3)

    return ev.drain(_events(spark, d), "append", serve).drop("_batch").withColumn("score", F.round("score", 6) + F.lit(0.0))


@query("stream_join_copresence", LOG + "SELECT a.event_id AS event_a, b.event_id AS event_b, a.user_id AS user_a, b.user_id AS user_b, a.k FROM e a JOIN e b ON a.k = b.k AND a.user_id < b.user_id AND abs(a.us - b.us) <= 300000000")
def _(spark, d):
    """Ties of users who touch one item within five minutes, from a stream joined with itself."""
    return ev.drain(ev.copresence(_events(spark, d)), "append").drop("_batch")
