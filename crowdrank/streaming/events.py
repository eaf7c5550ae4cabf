"""Incremental groups, popularity and serving over the event stream.

Event time is the table's naive time read as UTC and rows are written by micro-batch into the shared
folder; a restart with the same checkpoint goes on where it stopped.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowdrank.session import shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, files: int = 4) -> DataFrame:
    """Rows of a folder, ``files`` files a micro-batch, with the event time in UTC and the item."""
    rows = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)
    utc = F.to_utc_timestamp(F.col("ts").cast("timestamp"), F.current_timezone())
    return rows.withColumn("at", utc).withColumn("k", F.get_json_object("props", "$.k").cast("long"))


def drain(stream: DataFrame, mode: str, each: Callable[[DataFrame, str], DataFrame] | None = None, checkpoint: str | None = None) -> DataFrame:
    """Run until the available input is used up and return what was written.

    ``complete`` results replace each other; ``append`` and ``update`` rows are kept by batch.
    """
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        out = each(batch, path) if each else batch
        out.withColumn("_batch", F.lit(number)).write.mode("overwrite" if mode == "complete" else "append").parquet(path)

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint or f"{path}-log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(path)


def tumbling_groups(events: DataFrame, late: str = "1 hour", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Users that touch one item within a window."""
    w = F.window("at", width, slide) if slide else F.window("at", width)
    return events.withWatermark("at", late).groupBy(w.alias("w"), "k").agg(F.array_sort(F.collect_set("user_id")).alias("members")).select(F.unix_micros("w.start").alias("start_us"), "k", F.size("members").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.withWatermark("at", "1 hour").groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def copresence(events: DataFrame, within: str = "5 minutes", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: two users who touch one item within a span of time.

    Both sides carry a watermark and the join bounds the distance, so state is dropped as time goes on.
    """
    side = lambda n: events.withWatermark("at", late).select(F.col("user_id").alias(f"user_{n}"), F.col("k").alias(f"k_{n}"), F.col("at").alias(f"at_{n}"), F.col("event_id").alias(f"event_{n}"))
    span = F.expr(f"at_b >= at_a - INTERVAL {within} AND at_b <= at_a + INTERVAL {within}")
    both = side("a").join(side("b"), (F.col("k_a") == F.col("k_b")) & span & (F.col("user_a") < F.col("user_b")))
    return both.select("event_a", "event_b", "user_a", "user_b", F.col("k_a").alias("k"))


def popularity(events: DataFrame) -> DataFrame:
    return events.groupBy("k").agg(F.count("*").alias("n"))


def first_touches(events: DataFrame) -> DataFrame:
    """One row a user and item, whatever the batch it came in."""
    return events.dropDuplicates(["user_id", "k"]).select("user_id", "k")


def repeats_within(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "k")


def running_degree(events: DataFrame) -> DataFrame:
    """Distinct-free degree of each user, kept as state and emitted with every change."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(map(len, frames))
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, degree long", "degree long", "update", "NoTimeout")


def replay(spark: SparkSession, path: str, files: int = 6, late_every: int | None = None, late_by: int = 1) -> str:
    """The event table as files of equal spans of time; every ``late_every``-th row comes ``late_by`` files later."""
    e = spark.read.schema(SCHEMA).parquet(path)
    us = F.unix_micros(F.to_utc_timestamp(F.col("ts").cast("timestamp"), F.current_timezone()))
    lo, hi = e.agg(F.min(us), F.max(us)).first()
    number = F.floor((us - F.lit(lo)) * files / F.lit((hi or 0) - (lo or 0) + 1)).cast("int")
    if late_every:
        number = F.least(number + late_by * (F.col("event_id") % late_every == 0).cast("int"), F.lit(files - 1))
    out = f"{shared_dir(spark)}/replay-{uuid.uuid4().hex}"
    for i in range(files):
        e.withColumn("f", number).filter(F.col("f") == i).drop("f").coalesce(1).write.mode("append").parquet(out)
    return out
