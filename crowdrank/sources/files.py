"""Edge lists and model tables in files: round trips, bucketed tables, stored models."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowdrank.session import shared_dir


def _place(spark: SparkSession, kind: str) -> str:
    return f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """Write in a format and read it back with the explicit schema (no inference)."""
    spark, path = df.sparkSession, _place(df.sparkSession, fmt)
    writer = df.write.option("header", True) if fmt == "csv" else df.write
    writer.format(fmt).save(path)
    reader = spark.read.schema(df.schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def bucketed_join(a: DataFrame, b: DataFrame, key: str = "id", buckets: int = 8) -> DataFrame:
    """Store both sides bucketed and sorted by the key, so that their join needs no exchange."""
    spark, names = a.sparkSession, []
    for df in (a, b):
        names.append(f"bucketed_{uuid.uuid4().hex[:12]}")
        df.write.bucketBy(buckets, key).sortBy(key).option("path", _place(spark, "bucketed")).saveAsTable(names[-1])
    return spark.table(names[0]).hint("merge").join(spark.table(names[1]), key)


def save_model(spark: SparkSession, params: dict, users: DataFrame, items: DataFrame, config: dict) -> str:
    """Vectors as Parquet, dense parameters and settings as one small manifest, written last."""
    path = _place(spark, "model")
    users.write.parquet(f"{path}/users")
    items.write.parquet(f"{path}/items")
    rows = [(k, list(v.shape), v.ravel().tolist()) for k, v in params.items()]
    spark.createDataFrame(rows, "name string, shape array<int>, data array<double>").write.parquet(f"{path}/params")
    spark.createDataFrame([(json.dumps(config),)], "manifest string").coalesce(1).write.text(f"{path}/manifest")
    return path


def load_model(spark: SparkSession, path: str) -> tuple[dict, DataFrame, DataFrame, dict]:
    import numpy as np

    config = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    params = {r["name"]: np.array(r["data"]).reshape(r["shape"]) for r in spark.read.parquet(f"{path}/params").collect()}
    return params, spark.read.parquet(f"{path}/users"), spark.read.parquet(f"{path}/items"), config


def store_and_load(spark: SparkSession, ids: DataFrame) -> DataFrame:
    """Save and load a model of hashed vectors; one row a user with the length of its vector."""
    from crowdrank.operators.models import Config, parameters
    from crowdrank.operators.train import start_vectors

    c = Config()
    vectors = start_vectors(ids, c.d, c.seed)
    path = save_model(spark, parameters(c), vectors, vectors, {"d": c.d, "heads": c.heads})
    _, users, _, config = load_model(spark, path)
    return users.select("id", F.size("vec").alias("n")).filter(F.col("n") == config["d"])
