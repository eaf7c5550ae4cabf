"""Streams: restart from a checkpoint, late rows, joins."""

import uuid

from pyspark.sql import functions as F

from crowdrank.session import shared_dir
from crowdrank.streaming import events as ev

DIR = "/root/testdata/sf0.001"


def test_restart_goes_on_where_it_stopped(spark):
    """The second run of a checkpointed stream reads only the files that came since."""
    path = ev.replay(spark, f"{DIR}/events.parquet", 4)
    files = sorted(r[0] for r in spark.read.parquet(path).select(F.input_file_name()).distinct().collect())
    inbox, log = (f"{shared_dir(spark)}/{k}-{uuid.uuid4().hex}" for k in ("inbox", "log"))
    batches = []
    for part in (files[:2], files[2:]):
        spark.read.schema(ev.SCHEMA).parquet(*part).write.mode("append").parquet(inbox)
        out = ev.drain(ev.first_touches(ev.source(spark, inbox)), "append", checkpoint=log)
        batches.append({(r["user_id"], r["k"]) for r in out.collect()})
    everything = {(r["user_id"], r["k"]) for r in spark.read.schema(ev.SCHEMA).parquet(path).select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).collect()}
    assert batches[0] | batches[1] == everything and not batches[0] & batches[1] and all(batches)
