"""Splits, ranks, hits, reciprocal ranks, significance and cost."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def time_split(gv: DataFrame, train: float = 0.8, valid: float = 0.1, exact: bool = False) -> DataFrame:
    """Adds ``split``: the last records in time are the test, the last of the rest the validation.

    The default cuts at approximate time percentiles (one small aggregate and a filter). ``exact``
    counts records in (time, group, item) order through day totals, without a global sort; only days that
    a cut falls into are sorted. One number a day comes to the driver.
    """
    if not exact:
        us = F.unix_micros(F.col("ts").cast("timestamp"))
        a, b = gv.agg(F.percentile_approx(us, [train * (1 - valid), train], 100_000).alias("c")).first()["c"]
        return gv.withColumn("split", F.when(us > b, "test").when(us > a, "valid").otherwise("train"))
    day = gv.withColumn("_day", F.unix_date(F.to_date("ts")))
    totals = sorted(((x["_day"], x["count"]) for x in day.groupBy("_day").count().collect()), key=lambda x: (x[0] is not None, x[0]))
    cut = math.floor(train * sum(n for _, n in totals))
    first = cut - math.floor(valid * cut)
    whole, mixed, base = F.lit("train"), {}, 0
    starts = {"valid": None, "test": None}
    for at, n in totals:
        if any(base < c < base + n for c in (first, cut)):
            mixed[at] = base
        for name, c in (("valid", first), ("test", cut)):
            starts[name] = at if starts[name] is None and base >= c else starts[name]
        base += n
    for name in ("valid", "test"):
        if starts[name] is not None:
            whole = F.when(F.col("_day") >= starts[name], name).otherwise(whole)
    rest = day.filter(F.col("_day").isNotNull() & ~F.col("_day").isin(*mixed)).withColumn("split", whole).drop("_day")
    inner = Window.partitionBy("_day").orderBy("ts", "group_key", "item_id")
    for at, before in mixed.items():  # two days at most
        r = F.row_number().over(inner) + F.lit(before)
        part = day.filter(F.col("_day") == at).withColumn("_r", r)
        rest = rest.union(part.withColumn("split", F.when(F.col("_r") > cut, "test").when(F.col("_r") > first, "valid").otherwise("train")).drop("_day", "_r"))
    return rest


def truth_rank(truth: DataFrame, scores: DataFrame, seen: DataFrame | None = None, ties: str = "id") -> DataFrame:
    """``group_key, item_id, rnk, candidates``: one more than the candidates that score higher.

    Candidates are the items that the group never touched, and the truth. Counting is an aggregate:
    neither scores nor candidates are sorted. ``ties``: by ``id``, ``optimistic``, ``pessimistic`` or
    ``mean``.
    """
    own = truth.select("group_key", "item_id").join(scores, ["group_key", "item_id"]).select("group_key", F.col("item_id").alias("truth"), F.col("score").alias("own"))
    other = scores if seen is None else scores.join(seen.select("group_key", "item_id").distinct(), ["group_key", "item_id"], "left_anti")
    both = own.join(other, "group_key").filter("item_id <> truth")
    higher, equal = F.count_if(F.col("score") > F.col("own")), F.count_if(F.col("score") == F.col("own"))
    first = F.count_if((F.col("score") == F.col("own")) & (F.col("item_id") < F.col("truth")))
    extra = {"id": first, "optimistic": F.lit(0), "pessimistic": equal, "mean": equal / 2}[ties]
    counted = both.groupBy("group_key", "truth").agg((higher + extra).alias("above"), F.count("*").alias("others"))
    out = own.join(counted, ["group_key", "truth"], "left")
    return out.select("group_key", F.col("truth").alias("item_id"), (F.coalesce("above", F.lit(0)) + 1).alias("rnk"), (F.coalesce("others", F.lit(0)) + 1).alias("candidates"))


def hits(ranks: DataFrame, ns: tuple[int, ...] = (1, 5, 10, 15, 20)) -> DataFrame:
    one = ranks.agg(*[F.avg((F.col("rnk") <= n).cast("double")).alias(str(n)) for n in ns])
    return one.select(F.explode(F.array(*[F.struct(F.lit(n).alias("n"), F.col(str(n)).alias("hits")) for n in ns])).alias("x")).select("x.n", "x.hits")


def mrr(ranks: DataFrame) -> DataFrame:
    return ranks.agg(F.avg(1 / F.col("rnk")).alias("mrr"), F.count("*").alias("n_test"))


def paired_test(a: DataFrame, b: DataFrame) -> DataFrame:
    """Two rows: paired t on reciprocal ranks, and McNemar's test on hits at 10."""
    x = a.select("group_key", "item_id", F.col("rnk").alias("ra")).join(b.select("group_key", "item_id", F.col("rnk").alias("rb")), ["group_key", "item_id"])
    d = 1 / F.col("ra") - 1 / F.col("rb")
    won, lost = F.count_if((F.col("ra") <= 10) & (F.col("rb") > 10)), F.count_if((F.col("ra") > 10) & (F.col("rb") <= 10))
    t = x.agg(F.avg(d).alias("mean_diff"), (F.avg(d) / F.sqrt(F.var_samp(d) / F.count("*"))).alias("stat"), F.count("*").alias("n"), won.alias("won"), lost.alias("lost"))
    r = t.first()
    p = lambda z: math.erfc(abs(z) / math.sqrt(2)) if z is not None else None
    both = r["won"] + r["lost"]
    z = (r["won"] - r["lost"]) / math.sqrt(both) if both else 0.0
    rows = [("reciprocal_rank", r["mean_diff"], r["stat"], r["n"], p(r["stat"])), ("hits_10", (r["won"] - r["lost"]) / max(1, r["n"]), z, r["n"], p(z))]
    return a.sparkSession.createDataFrame(rows, "metric string, mean_diff double, stat double, n long, p_value double")


def time_folds(records: DataFrame, folds: int = 3) -> list[tuple[DataFrame, DataFrame]]:
    """Training and validation parts in time order: fold ``k`` trains on all that is before its part.

    Records are cut at even counts in (time, group, item) order, found through day totals.
    """
    day = records.withColumn("_day", F.date_trunc("day", "ts"))
    totals = day.groupBy("_day").count()
    before = Window.orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)
    base = totals.select("_day", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_base"))
    inner = Window.partitionBy("_day").orderBy("ts", "group_key", "item_id")
    n = records.count()
    r = day.withColumn("_r", F.row_number().over(inner) - 1).join(base, "_day")
    part = F.floor((F.col("_r") + F.col("_base")) * (folds + 1) / F.lit(max(1, n)))
    cut = r.withColumn("_part", part).drop("_day", "_r", "_base")
    return [(cut.filter(F.col("_part") < k).drop("_part"), cut.filter(F.col("_part") == k).drop("_part")) for k in range(1, folds + 1)]


def cost_model(d: int, negatives: int, views: int, edges: int, epochs: int = 1) -> dict[str, int]:
    """Multiply-adds of a step and of training: dimension x negatives x views, steps with the edges."""
    step = d * (1 + negatives) * max(1, views)
    return {"step": step, "steps": edges * epochs, "total": step * edges * epochs}


def plateau(curve: list[tuple[int, float]], eps: float = 0.01) -> int:
    """The smallest number of steps from which the measure stays within ``eps`` of its last value."""
    last, at = curve[-1][1], curve[-1][0]
    for n, v in reversed(curve):
        if abs(v - last) > eps * max(abs(last), 1e-12):
            break
        at = n
    return at
