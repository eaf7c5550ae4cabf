"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read by the next.

Language ID drops texts without a recognisable language; line dedup deletes later repeated runs of
lines and later copies of single lines of ``SINGLE_WORDS`` words or more, and documents that lose all
their lines go; the n-gram Jaccard join keeps the smallest id of each group; decontamination drops
documents that hold benchmark passages by the contract's rule; packing cuts the rest into sequences.

Null texts have no language and go first. Rows without an id are told apart by their text; identical
rows of one id stay or go together. An empty table gives no rows, and extra columns stay up to packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowdrank.llm import decontamination, jaccard_join, language_id, line_dedup, packing
from crowdrank.llm.common import cut, table
from crowdrank.session import ship


def of_texts(docs: DataFrame, found: DataFrame, how: str) -> DataFrame:
    """Rows of ``docs`` that have, or have not, a row ``doc_id, th`` in ``found``."""
    found = found.select(F.col("doc_id").alias("__id"), F.col("th").alias("__th"))
    return docs.join(found, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.xxhash64("text") == F.col("__th")), how)


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return language_id.keep_known(docs, language_id.fit(docs.filter(~language_id.held_out())))


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    clash = {c: f"kept {c}" for c in ("n_lines", "n_removed") if c in docs.columns}
    out = line_dedup.dedup_lines(docs.withColumnsRenamed(clash), single_words=line_dedup.SINGLE_WORDS)
    out = out.filter("n_removed = 0 OR n_removed < n_lines")
    n_chars = F.when(F.col("n_removed") > 0, F.char_length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)
    return out.withColumn("n_chars", n_chars).select(*(F.col(f"`{clash.get(c, c)}`").alias(c) for c in docs.columns))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return of_texts(docs, jaccard_join.jaccard_classes(docs).filter("first"), "left_semi")


def without_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return of_texts(docs, decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark")).filter("contaminated"), "left_anti")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", known_language),
    ("line_dedup", without_repeated_lines),
    ("jaccard_join", one_of_each_group),
    ("decontamination", without_benchmarks),
    ("packing", packed),
]

#: A fitted model and a tokenizer stand in the way of SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = cut(docs)
    return docs
