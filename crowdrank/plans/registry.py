"""All queries of the group-recommendation engine with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from crowdrank.operators.models import Config
from crowdrank.operators.rank import topn
from crowdrank.operators.train import fit, group_vectors
from crowdrank.plans import graph_queries, model_queries, stream_queries, surface_queries, training_queries
from crowdrank.sources.workloads import teams

QUERIES = graph_queries.QUERIES | model_queries.QUERIES | training_queries.QUERIES | surface_queries.QUERIES | stream_queries.QUERIES
SQL = graph_queries.SQL | model_queries.SQL | training_queries.SQL | surface_queries.SQL | stream_queries.SQL


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Train on suppliers and orders, and recommend ten items to every team."""
    w = teams(spark, sf_dir)
    m = fit(w.uv, w.uu, w.records, Config(rounds=1, local=2, d=8))
    return topn(group_vectors(m, w.records), m.items, 10, seen=w.gv)
