"""Stupid-backoff language-model scores, computed as joins of n-gram counts.

Documents are dealt to blocks. Order by order, every block explodes its n-grams, keeps each once with
its count, and sends them to the count table of that order, which is partitioned by n-gram hash; each
table partition adds up the counts of all blocks and answers every block with the counts of its
n-grams over the whole corpus. An n-gram can be seen ``min_count`` times only if both n-grams of one
word less that it holds are, so higher orders ask for no others; this drops no n-gram that counts. A
document's score is the sum over its words of the log of ``count(n-gram) / count(context)`` at the
longest order that the corpus holds at least ``min_count`` times, times ``alpha`` for each order given
up; the last resort is the word's share of the corpus. The corpus holds the scored document itself, so
with the default of 2 an n-gram of higher order counts as seen if it occurs anywhere else too.

Rows of the exchange hold sorted arrays, so an n-gram costs bytes, not rows, and a frequent one
counts once a block; a block sends no row to a partition for which it has no n-gram, so there are
never more rows than n-grams. Defined results: null or blank text has no words, score 0 and no mean;
a null id is scored like any other; repeated rows are scored alike and count each time; extra columns
are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import gram_hashes, lean_call, table, word_hashes

ASKED = "block int, k int, slice int, grams binary, counts binary"
ANSWERED = "block int, k int, slice int, counts binary"


class Block:
    """The words of some texts, and the counts of their n-grams as far as they are known."""

    def __init__(self, texts: list[str | None], min_count: int) -> None:
        words = [word_hashes(t.encode())[2] if t else np.zeros(0, np.uint64) for t in texts]
        self.sizes = np.array([len(w) for w in words], np.int64)
        self.flat = np.concatenate(words) if words else np.zeros(0, np.uint64)
        n = len(self.flat)
        # how many words of the same text stand before each
        self.depth = (np.arange(n) - np.repeat(np.cumsum(self.sizes) - self.sizes, self.sizes)).astype(np.int32)
        self.least = max(1, min_count)
        #: corpus counts of the n-gram that ends at each word, by order; 0 where none was asked for
        self.known: list[np.ndarray] = []

    def ends(self) -> np.ndarray:
        """Last words of the n-grams of the next order that may be seen often enough."""
        k = len(self.known)
        ends = np.flatnonzero(self.depth >= k)
        if k:
            ends = ends[self.known[-1][ends] >= self.least]
            ends = ends[self.known[-1][ends - 1] >= self.least]
        return ends

    def hashes(self, ends: np.ndarray) -> np.ndarray:
        k = len(self.known) + 1
        h = gram_hashes(self.flat, k)[ends - (k - 1)] if len(ends) else np.zeros(0, np.uint64)
        # the order is part of the key
        return h ^ np.uint64((k * 0x9E3779B97F4A7C15) % 2**64)

    def learn(self, rows: list[tuple[int, bytes]]) -> None:
        """Take the answers of the next order: counts by slice, aligned with the sorted n-grams."""
        ends = self.ends()
        counts = np.zeros(len(self.flat), np.int64)
        if len(ends):
            _, place = np.unique(self.hashes(ends), return_inverse=True)
            counts[ends] = np.concatenate([_counts(data) for _, data in sorted(rows)])[place]
        self.known.append(counts)

    def scores(self, total: int, alpha: float) -> np.ndarray:
        """Sum of log scores of each text."""
        best = np.log(np.maximum(self.known[0], 1) / max(1, total))
        for k in range(1, len(self.known)):
            context = np.concatenate(([0], self.known[k - 1][:-1]))
            possible = self.depth >= k
            seen = possible & (self.known[k] >= self.least)
            lower = np.where(possible, best + np.log(alpha), best)
            best = np.where(seen, np.log(np.where(seen, self.known[k], 1) / np.where(seen, context, 1)), lower)
        edges = np.concatenate(([0], np.cumsum(self.sizes)))
        return np.array([best[a:b].sum() for a, b in zip(edges, edges[1:], strict=False)])


def _planes(x: np.ndarray) -> bytes:
    """Low bytes first by plane, so that the high planes pack away."""
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes()


def _from_planes(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(8, -1).T).view("<i8").ravel()


def _narrow(sorted_hashes: np.ndarray) -> bytes:
    return _planes(np.diff(sorted_hashes, prepend=np.uint64(0)))


def _wide(data: bytes) -> np.ndarray:
    return np.cumsum(_from_planes(data).view(np.uint64), dtype=np.uint64)


def _packed(counts: np.ndarray) -> bytes:
    return zstandard.compress(_planes(counts), 1)


def _counts(data: bytes) -> np.ndarray:
    return _from_planes(zstandard.decompress(data))


def question(block: Block, number: int, slices: int) -> pa.Table:
    """The n-grams of the next order, each once with its count, by slice of the hash space."""
    grams, counts = np.unique(block.hashes(block.ends()), return_counts=True)
    bounds = np.array([(i << 64) // slices for i in range(1, slices)], np.uint64)
    cuts = np.concatenate(([0], np.searchsorted(grams, bounds), [len(grams)]))
    own = np.flatnonzero(np.diff(cuts))
    spans = [(int(cuts[i]), int(cuts[i + 1])) for i in own]
    n = len(own)
    cols = [pa.array([number] * n, pa.int32()), pa.array([len(block.known) + 1] * n, pa.int32()), pa.array(own.astype(np.int32))]
    cols += [pa.array([f(x[a:b]) for a, b in spans], pa.binary()) for f, x in ((_narrow, grams), (_packed, counts))]
    return pa.table(cols, ["block", "k", "slice", "grams", "counts"])


def tally(table: pa.Table) -> pa.Table:
    """One partition of a count table: add up all blocks, then answer each."""
    table = table.combine_chunks()
    asked = [_wide(x.as_py()) for x in table["grams"]]
    own = np.concatenate([_counts(x.as_py()) for x in table["counts"]])
    cuts = np.cumsum([0, *map(len, asked)])
    flat = np.concatenate(asked)
    del asked
    order = np.argsort(flat, kind="stable")
    flat = flat[order]
    group = np.cumsum(np.concatenate(([0], flat[1:] != flat[:-1])))
    sums = np.bincount(group, own[order].astype(np.float64)).astype(np.int64)
    back = np.empty(len(flat), np.int64)
    back[order] = sums[group]
    answers = pa.array([_packed(back[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)], pa.binary())
    return table.select(["block", "k", "slice"]).append_column("counts", answers)


def score(docs: DataFrame, order: int = 3, alpha: float = 0.4, min_count: int = 2, block_bytes: int = 12_000_000, slice_bytes: int = 6_000_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_words, log_score, mean_log`` for each document, counts taken over all documents."""
    words = F.size(F.array_remove(F.split(F.coalesce(F.col(text_col), F.lit("")), "[\\x20\\x09-\\x0D]+"), ""))
    size = docs.select(F.sum(F.octet_length(text_col)).alias("b"), F.sum(words).alias("n")).first()
    n_bytes, total = size["b"] or 0, size["n"] or 0
    blocks, slices = max(1, n_bytes // block_bytes), max(4, n_bytes // slice_bytes)
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t"))
    text = text.withColumn("block", F.pmod(F.xxhash64("doc_id", "t"), F.lit(blocks)).cast("int")).repartition("block")

    def read(a: pa.Table, answers: pa.Table | None) -> Block:
        block = Block(a["t"].to_pylist(), min_count)
        rows: dict[int, list[tuple[int, bytes]]] = {}
        if answers is not None:
            for k, at, data in zip(answers["k"].to_pylist(), answers["slice"].to_pylist(), answers["counts"].to_pylist(), strict=True):
                rows.setdefault(k, []).append((at, data))
        return block, rows

    @lean_call
    def ask_first(a: pa.Table) -> pa.Table:
        return question(read(a, None)[0], a["block"][0].as_py(), slices)

    def asking(k: int):
        @lean_call
        def ask(a: pa.Table, b: pa.Table) -> pa.Table:
            block, rows = read(a, b)
            for lower in range(1, k):
                block.learn(rows.get(lower, []))
            return question(block, a["block"][0].as_py(), slices)

        return ask

    @lean_call
    def add(a: pa.Table, b: pa.Table) -> pa.Table:
        block, rows = read(a, b)
        for k in range(1, order + 1):
            block.learn(rows.get(k, []))
        sums, n = block.scores(total, alpha), block.sizes
        mean = [s / k if k else None for s, k in zip(sums.tolist(), n.tolist(), strict=True)]
        return pa.table([a["doc_id"], pa.array(n, pa.int64()), pa.array(sums, pa.float64()), pa.array(mean, pa.float64())], ["doc_id", "n_words", "log_score", "mean_log"])

    answers = None
    for k in range(1, order + 1):
        if k == 1:
            asked = text.groupBy("block").applyInArrow(ask_first, ASKED)
        else:
            asked = text.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(asking(k), ASKED)
        answered = asked.groupBy("slice").applyInArrow(tally, ANSWERED)
        answers = answered if answers is None else answers.union(answered)
    return text.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(add, "doc_id long, n_words long, log_score double, mean_log double")


def op6_lm_scoring(spark, sf_dir: str) -> DataFrame:
    """Trigrams, then bigrams, then words."""
    out = score(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_words", F.round("log_score", 4).alias("log_score"))


SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
t AS (SELECT doc_id, p, w[p] AS c, CASE WHEN p > 1 THEN w[p - 1] END AS b, CASE WHEN p > 2 THEN w[p - 2] END AS a FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM d)),
u AS (SELECT c, count(*) AS c1 FROM t GROUP BY c),
g AS (SELECT b, c, count(*) AS c2 FROM t WHERE b IS NOT NULL GROUP BY b, c),
h AS (SELECT a, b, c, count(*) AS c3 FROM t WHERE a IS NOT NULL GROUP BY a, b, c),
n AS (SELECT count(*) AS n FROM t),
s2 AS (SELECT t.doc_id, t.a, t.b, t.c, CASE WHEN t.b IS NULL THEN ln(u.c1 / n.n) WHEN g.c2 >= 2 THEN ln(g.c2 / ub.c1) ELSE ln(0.4) + ln(u.c1 / n.n) END AS l
  FROM t CROSS JOIN n JOIN u ON u.c = t.c LEFT JOIN g ON g.b = t.b AND g.c = t.c LEFT JOIN u ub ON ub.c = t.b),
s3 AS (SELECT s2.doc_id, CASE WHEN s2.a IS NULL THEN s2.l WHEN h.c3 >= 2 THEN ln(h.c3 / gab.c2) ELSE ln(0.4) + s2.l END AS l
  FROM s2 LEFT JOIN h ON h.a = s2.a AND h.b = s2.b AND h.c = s2.c LEFT JOIN g gab ON gab.b = s2.a AND gab.c = s2.b),
x AS (SELECT doc_id, sum(l) AS l FROM s3 GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, round(coalesce(l, 0), 4) AS log_score FROM d LEFT JOIN x USING (doc_id)
"""
