"""Benchmark decontamination as a prefix-filtered set join of item windows [native].

Every window of an item is a set of words that a document must hold as a run. Words are ordered by
rarity in the corpus; a containment threshold of 1 makes the necessary prefix one word, the rarest
of the window, so only the places of those words are joined. Positional and length bounds then fix
the one run of the document that can match, and its words are compared exactly.

A word that is the rarest of many windows keeps them in slices of bounded size, each a row of its own.

Defined results: null or word-less texts have no words and no hits; null items and items without
words have no windows; an item without an id is listed as the empty string; items that repeat count
once an ``item_id``; a null document id is an id like others; rows repeated under one id are each
judged on their own text; empty tables give no rows or no hits; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import table

#: The characters between words, after A-Z have been lower-cased.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words_of(text: Column) -> Column:
    """The words of a text; a leading or trailing separator leaves an empty string, which goes."""
    return F.array_remove(F.split(F.coalesce(F.translate(text, UPPER, LOWER), F.lit("")), SEPARATORS), "")


def windows(items: DataFrame, width: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """Distinct windows ``win`` with the ids of all items that hold them."""
    w = items.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("item"), words_of(F.col(text_col)).alias("w")).filter("size(w) > 0")
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("w") - (width - 1)))
    return w.select("item", "w", F.explode(starts).alias("s")).select("item", F.slice("w", F.col("s"), width).alias("win")).groupBy("win").agg(F.collect_set("item").alias("items"))


def anchored(wins: DataFrame, docs: DataFrame, text_col: str, small: bool, slices: int) -> DataFrame:
    """Windows by their rarest word: ``tok, anchors array<struct<off, win, items>>``, a row a word and slice."""
    vocabulary = wins.select(F.explode("win").alias("tok")).distinct()
    hint = F.broadcast if small else (lambda x: x)
    seen = docs.select(F.explode(words_of(F.col(text_col))).alias("tok")).join(hint(vocabulary), "tok").groupBy("tok").count()
    order = wins.select("win", "items", F.posexplode("win").alias("off", "tok")).join(hint(seen), "tok", "left")
    rarest = order.groupBy("win", "items").agg(F.min(F.struct(F.coalesce("count", F.lit(0)).alias("n"), "tok", "off")).alias("r"))
    by = [F.col("r.tok").alias("tok"), F.pmod(F.xxhash64("win"), F.lit(slices)).alias("slice")]
    return rarest.groupBy(*by).agg(F.collect_list(F.struct(F.col("r.off").alias("off"), "win", "items")).alias("anchors")).drop("slice")


def find(docs: DataFrame, items: DataFrame, width: int = 13, id_col: str = "doc_id", text_col: str = "text", broadcast_words: int = 4_000_000) -> DataFrame:
    """Verified occurrences: ``doc_id, th (hash of the text), start (from 0), len, items``.

    The anchor table is broadcast only while all windows together have at most ``broadcast_words``
    words; beyond that, thin rows of word places are joined by shuffle and the text follows for the
    documents that have a candidate.
    """
    wins = windows(items, width)
    n_words = wins.agg(F.sum(F.size("win"))).first()[0] or 0
    small = n_words <= broadcast_words
    anchors = anchored(wins, docs, text_col, small, max(1, n_words // (64 * width)))
    text = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("th"), words_of(F.col(text_col)).alias("w"))
    if small:
        at = text.select("doc_id", "th", "w", F.posexplode("w").alias("pos", "tok")).join(F.broadcast(anchors), "tok")
        near = at.select("doc_id", "th", "w", "pos", F.explode("anchors").alias("a"))
    else:
        tokens = anchors.select("tok").distinct()
        thin = text.select("doc_id", "th", F.posexplode("w").alias("pos", "tok")).join(tokens, "tok")
        own = text.dropDuplicates(["doc_id", "th"]).select(F.col("doc_id").alias("d"), F.col("th").alias("h"), "w")
        near = thin.distinct().join(own, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("th").eqNullSafe(F.col("h")))
        near = near.join(anchors, "tok").select("doc_id", "th", "w", "pos", F.explode("anchors").alias("a"))
    start = F.col("pos") - F.col("a.off")
    fits = (start >= 0) & (start + F.size("a.win") <= F.size("w"))
    same = F.when(fits, F.slice("w", F.greatest(start, F.lit(0)) + 1, F.size("a.win")) == F.col("a.win")).otherwise(F.lit(False))
    return near.filter(same).select("doc_id", "th", start.alias("start"), F.size("a.win").alias("len"), F.col("a.items").alias("items"))


def decontaminate(docs: DataFrame, items: DataFrame, width: int = 13, id_col: str = "doc_id", text_col: str = "text", share: int = 20) -> DataFrame:
    """One row a document: ``doc_id, th (hash of the text), n_words, n_hit, spans, items, contaminated``."""
    hits = find(docs, items, width, id_col, text_col)
    spans = hits.groupBy("doc_id", "th").agg(F.array_sort(F.collect_set(F.struct("start", "len"))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    covered = F.size(F.array_distinct(F.flatten(F.transform("spans", lambda x: F.sequence(x["start"], x["start"] + x["len"] - 1)))))
    spans = spans.select(F.col("doc_id").alias("d"), F.col("th").alias("h"), "spans", "items", covered.cast("long").alias("n_hit"))
    sizes = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("th"), F.size(words_of(F.col(text_col))).cast("long").alias("n_words"))
    out = sizes.join(spans, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("h")), "left").withColumn("n_hit", F.coalesce("n_hit", F.lit(0).cast("long")))
    out = out.select("doc_id", "th", "n_words", "n_hit", "spans", "items")
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words")))


def op7_decontamination(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    items = table(spark, sf_dir, "benchmark").select("item_id", "text")
    out = decontaminate(docs, items)
    ids = F.coalesce("items", F.array().cast("array<string>"))
    return out.select("doc_id", "n_words", "n_hit", F.size(ids).cast("long").alias("n_items"), F.sha2(F.array_join(ids, ","), 256).alias("items_sha256"), "contaminated")


SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[s:s + least(13, len(w)) - 1], ' ') AS g FROM (SELECT *, unnest(range(1, greatest(1, len(w) - 12) + 1)) AS s FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM win),
grams AS (SELECT doc_id, n, s, array_to_string(w[s:s + n - 1], ' ') AS g FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes WHERE len(w) >= n)),
hit AS (SELECT doc_id, s, grams.n AS n, item_id FROM grams JOIN win USING (n, g)),
cover AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY doc_id),
it AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM hit GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN cover USING (doc_id) LEFT JOIN it USING (doc_id)
"""
