"""Substring dedup with one compressed FM-index a shard.

Windows of ``width`` words are routed to shards by their minimiser, the smallest hash of the
``gram``-word runs inside, so all occurrences of a window meet in one shard. Consecutive windows with
one minimiser are a segment. Minimisers that occur once cannot hold a repeat. Equal segments are one
text with a multiplicity; each shard indexes its distinct segments and streams them through backward
search, which gives the matching statistics at ``width`` and the weighted number of occurrences.
Minimisers with many distinct segments (a common passage amid different text) are routed on by whole
windows, counted before they are shuffled, so no minimiser fills a shard.

Defined results: null or blank text has no words; texts shorter than the window lose nothing; a
window that repeats only within its own document counts, also overlapping itself; repeated rows are
copies of each other, so both lose their words; rows of one id with different texts and rows without
an id are told apart by a hash of their text; an empty table gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import _BASE, _INVERSE, cut, gram_hashes, lean, lean_call, mix, word_hashes
from crowdrank.llm.fm_index import FMIndex

_POWER: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    if len(_POWER.get(base, ())) < n:
        step = np.full(1 << max(10, (n - 1).bit_length()), base, np.uint64)
        step[0] = 1
        _POWER[base] = np.multiply.accumulate(step)
    return _POWER[base][:n]


def run_hashes(words: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of runs of words, by prefix sums."""
    sums = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * _power(_BASE, len(words)), out=sums[1:])
    return mix((sums[ends] - sums[starts]) * _power(_INVERSE, len(words) + 1)[starts] + (ends - starts).astype(np.uint64))


def leftmost_minima(h: np.ndarray, w: int) -> np.ndarray:
    """For each window of ``w`` values the place of its smallest, the leftmost on ties."""
    at, span = np.arange(len(h)), 1
    while 2 * span <= w:
        a, b = at[: len(at) - span], at[span:]
        at, span = np.where(h[a] <= h[b], a, b), 2 * span
    if span < w:
        a, b = at[: len(h) - w + 1], at[w - span :]
        at = np.where(h[a] <= h[b], a, b)
    return at


def segments(words: np.ndarray, width: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """First window, number of windows, minimiser and content hash of each segment."""
    if len(words) < width:
        return (np.zeros(0, np.int64),) * 2 + (np.zeros(0, np.uint64),) * 2
    h = gram_hashes(words, gram)
    at = leftmost_minima(h, width - gram + 1)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    n = np.diff(np.append(first, len(at)))
    return first, n, h[at[first]], run_hashes(words, first, first + n + width - 1)


def _words(text) -> np.ndarray:
    return word_hashes(text.encode())[2] if text else np.zeros(0, np.uint64)


def cut_segments(text: DataFrame, width: int, gram: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                own = batch.slice(lo, 1024)
                parts = [segments(_words(t.as_py()), width, gram) for t in own.column(2)]
                of = pa.array(np.repeat(np.arange(own.num_rows), [len(p[0]) for p in parts]))
                start, n, m, seg = (np.concatenate([p[i] for p in parts]) for i in range(4))
                yield pa.RecordBatch.from_arrays([own.column(0).take(of), own.column(1).take(of), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int16)), pa.array(m.astype(np.uint64).view(np.int64)), pa.array(seg.astype(np.uint64).view(np.int64))], ["doc_id", "th", "start", "n", "m", "seg"])

    return text.mapInArrow(lean(run), "doc_id long, th long, start int, n short, m long, seg long")


def fetch(reps: DataFrame, text: DataFrame, width: int) -> DataFrame:
    """Words of the representatives: whole segments, or single windows where ``hot``."""
    places = reps.groupBy(F.col("doc_id").alias("d"), F.col("th").alias("h")).agg(F.collect_list(F.struct("start", "n", "m", "seg", "c", "hot")).alias("places"))

    def run(batches):
        names = ["m", "seg", "off", "route", "c", "n", "words"]
        for batch in batches:
            out = [[] for _ in names]
            for t, places in zip(batch.column(1), batch.column(2), strict=True):
                w = _words(t.as_py())
                for p in places.as_py():
                    s, n = p["start"], p["n"]
                    if p["hot"]:
                        first = np.arange(s, s + n)
                        routes = run_hashes(w[s : s + n + width - 1], first - s, first - s + width).view(np.int64)
                        rows = [(p["m"], p["seg"], i, int(routes[i]), p["c"], 1, w[s + i : s + i + width].tobytes()) for i in range(n)]
                    else:
                        rows = [(p["m"], p["seg"], -1, p["m"], p["c"], n, w[s : s + n + width - 1].tobytes())]
                    for row in rows:
                        for col, x in zip(out, row, strict=True):
                            col.append(x)
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names)

    met = text.join(places, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("h")))
    # a row repeated under one id brings its segments again; they count twice or more already
    return met.select("doc_id", "t", "places").mapInArrow(lean(run), "m long, seg long, off int, route long, c long, n int, words binary")


def search_shard(table: pa.Table, width: int) -> pa.Table:
    """Index the distinct texts of a shard, stream them, and report windows that occur twice or more."""
    table = table.combine_chunks()
    texts = [np.frombuffer(x, np.uint64) for x in table["words"].to_pylist()]
    index = FMIndex(texts, table["c"].to_numpy(), width)
    hits = [np.flatnonzero(x >= 2).astype(np.int32) for x in index.statistics(texts)]
    keep = np.flatnonzero([len(h) > 0 for h in hits])
    out = table.take(pa.array(keep)).select(["m", "seg", "route"])
    return out.append_column("offs", pa.array([hits[i] for i in keep], pa.list_(pa.int32())))


def repeated(docs: DataFrame, width: int = 35, gram: int = 12, hot_segments: int = 64, shard_texts: int = 4000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Places of windows that also start elsewhere: ``doc_id, th, start, offs`` (offsets from ``start``)."""
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("th"), F.col(text_col).alias("t"))
    segs = cut(cut_segments(text, width, gram))
    twice = cut(segs.groupBy("m").count().filter("count > 1").select("m"), thin=True)
    live = cut(segs.join(twice, "m", "left_semi"))
    reps = live.groupBy("m", "seg").agg(F.count("*").alias("c"), F.min(F.struct("doc_id", "th", "start", "n")).alias("p"))
    reps = cut(reps.select("m", "seg", "c", "p.doc_id", "p.th", "p.start", "p.n"))
    many = cut(reps.groupBy("m").count().filter(F.col("count") > hot_segments).select("m"), thin=True)
    marked = reps.join(many.withColumn("hot", F.lit(True)), "m", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    fetched = cut(fetch(marked, text, width))
    whole, single = fetched.filter("off < 0"), fetched.filter("off >= 0")
    # windows of hot minimisers: count first, keep one text for each that occurs twice
    counted = single.groupBy("route").agg(F.sum("c").alias("c"), F.min("words").alias("words")).filter("c > 1")
    texts = whole.select("m", "seg", "route", "c", "words").union(counted.select(F.lit(0).cast("long"), F.lit(0).cast("long"), "route", "c", "words"))
    shards = max(1, -(-fetched.count() // shard_texts))
    shard = F.pmod(F.xxhash64("route", F.lit(2)), F.lit(shards))
    found = cut(texts.withColumn("shard", shard).groupBy("shard").applyInArrow(lean_call(lambda t: search_shard(t.drop(["shard"]), width)), "m long, seg long, route long, offs array<int>"))
    mine = found.filter("NOT (m = 0 AND seg = 0)").select("m", "seg", "offs")
    by_window = found.filter("m = 0 AND seg = 0").select("route")
    spread = single.select("m", "seg", "off", "route").join(by_window, "route", "left_semi").groupBy("m", "seg").agg(F.collect_list("off").alias("offs"))
    hits = cut(mine.union(spread))
    return live.join(hits, ["m", "seg"]).select("doc_id", "th", "start", "offs")


def remove_repeats(docs: DataFrame, width: int = 35, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = True, **how) -> DataFrame:
    """One row a document: ``doc_id, n_words, n_removed, kept_sha256`` and, if asked for, ``kept`` text."""
    spots = repeated(docs, width, id_col=id_col, text_col=text_col, **how).groupBy(F.col("doc_id").alias("d"), F.col("th").alias("h")).agg(F.collect_list(F.struct("start", "offs")).alias("spots"))
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("th"), F.col(text_col).alias("t"))

    def run(batches):
        names = ["doc_id", "n_words", "n_removed", "kept_sha256", "kept"]
        for batch in batches:
            rows = []
            for doc, t, spots in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                words = (t.as_py() or "").encode().split()
                n = len(words)
                if spots:
                    edge = np.zeros(n + 1, np.int64)
                    s = np.concatenate([np.array(x["offs"]) + x["start"] for x in spots])
                    np.add.at(edge, s, 1)
                    np.add.at(edge, s + width, -1)
                    words = [w for w, d in zip(words, np.cumsum(edge)[:n].tolist(), strict=True) if not d]
                kept = b" ".join(words)
                rows.append((doc, n, n - len(words), hashlib.sha256(kept).hexdigest(), kept.decode() if keep_text else None))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    met = text.join(spots, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("h")), "left")
    out = met.select("doc_id", "t", "spots").mapInArrow(lean(run), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string")
    return out if keep_text else out.drop("kept")


def op10_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), keep_text=False)


SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
win AS (SELECT doc_id, s, md5(array_to_string(w[s:s + 34], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS s FROM d WHERE len(w) >= 35)),
r AS (SELECT doc_id, s FROM (SELECT doc_id, s, count(*) OVER (PARTITION BY g) AS c FROM win) WHERE c > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(s, s + 35)) AS p FROM r),
kept AS (SELECT doc_id, string_agg(w[p], ' ' ORDER BY p) AS t FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM d) x WHERE NOT EXISTS (SELECT 1 FROM gone g WHERE g.doc_id = x.doc_id AND g.p = x.p) GROUP BY doc_id),
n AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id) LEFT JOIN n USING (doc_id)
"""
