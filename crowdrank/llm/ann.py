"""Approximate nearest neighbours by additive quantisation.

A vector is the sum of one entry of each full-dimensional codebook. Codebooks are fitted stage by
stage on residuals of a bounded sample; every row is encoded by beam search over them and stores its
own norm and that of its reconstruction. Queries score codes through lookup tables of query-entry
products: an inner product is scaled by the ratio of the norms, as a reconstruction is too short, and
a distance takes the norm of the reconstruction. The best rows of a block are reranked exactly, in
double precision, on the original vectors: the list starts at ``rerank`` rows and doubles until a
doubling changes none of the best ``k``, so groups of near copies, which codes cannot tell apart, are
reranked as a whole. A block has many times more rows than the list.

Defined results: null vectors, zero vectors, those with a null or non-finite component, those of
another length than the most frequent and rows without an id take no part; ties go to the smaller id;
fewer candidates than ``k`` are all returned; a query never finds rows of its own id; equal vectors
and other repeated ids are rows of their own; an empty table gives no rows. Columns other than id and
vector are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.llm.common import lean, lean_call, table


def kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = (x @ centres.T - 0.5 * (centres**2).sum(1)).argmax(1)
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        n = np.bincount(near, minlength=len(centres))
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
    return centres


def fit_codebooks(sample: np.ndarray, stages: int = 8, entries: int = 256, seed: int = 7) -> np.ndarray:
    """``(stages, entries, d)``: each stage is fitted to what the earlier ones leave."""
    rng, rest, books = np.random.default_rng(seed), sample.astype(np.float32), []
    for _ in range(stages):
        c = kmeans(rest, entries, rng)
        c = np.vstack([c, np.zeros((entries - len(c), sample.shape[1]), np.float32)])
        books.append(c)
        rest = rest - c[(rest @ c.T - 0.5 * (c**2).sum(1)).argmax(1)]
    return np.stack(books)


def encode(x: np.ndarray, books: np.ndarray, beam: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """Codes ``(n, stages)`` of the best of ``beam`` partial sums a stage, and ``(n, 2)`` norms: own, reconstruction."""
    n, (stages, entries, d) = len(x), books.shape
    rest, codes = x.astype(np.float32)[:, None, :], np.zeros((n, 1, 0), np.uint8)
    for c in books:
        h = rest.shape[1]
        loss = (rest**2).sum(2)[:, :, None] - 2 * (rest.reshape(n * h, d) @ c.T).reshape(n, h, entries) + (c**2).sum(1)
        flat, keep = loss.reshape(n, h * entries), min(beam, h * entries)
        best = np.argpartition(flat, keep - 1, axis=1)[:, :keep]
        row = np.arange(n)[:, None]
        rest = rest[row, best // entries] - c[best % entries]
        codes = np.concatenate([codes[row, best // entries], (best % entries).astype(np.uint8)[:, :, None]], axis=2)
    top = (rest**2).sum(2).argmin(1)
    row = np.arange(n)
    return codes[row, top], np.stack([np.sqrt((v**2).sum(1)) for v in (x, x - rest[row, top])], 1)


def lookup_scores(tables: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """``tables``: (stages, entries, queries). Sums of table entries, ``(rows, queries)``."""
    out = tables[0][codes[:, 0]].copy()
    for m in range(1, codes.shape[1]):
        out += tables[m][codes[:, m]]
    return out


def best_of_block(q: np.ndarray, q_ids: np.ndarray, books: np.ndarray, codes: np.ndarray, norms: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, rerank: int, measure: str):
    """Exact best ``k`` of a block for each query, after lookup-table scoring: index, ids, scores."""
    for a in range(0, len(q), 256):
        part = q[a : a + 256]
        approx = lookup_scores(np.ascontiguousarray((books @ part.T.astype(np.float32))), codes)
        own_norm, short = norms[:, :1], np.maximum(norms[:, 1:], 1e-30)
        approx = 2 * approx - short**2 if measure == "l2" else approx * (own_norm / short)
        approx = np.ascontiguousarray(approx.T)
        for i, row in enumerate(approx):
            own, size, last = q_ids[a + i], min(rerank, len(ids)), None
            while True:
                # all rows at least as good as the last of the list, so ties are never cut
                pick = np.flatnonzero(row >= np.partition(row, len(row) - size)[len(row) - size])
                pick = pick[ids[pick] != own]
                exact = (x[pick] * part[i]).sum(1) if measure == "ip" else -((x[pick] - part[i]) ** 2).sum(1)
                order = np.lexsort((ids[pick], -exact))[:k]
                found = (ids[pick][order], exact[order])
                if size >= len(ids) or last is not None and np.array_equal(last, found[0]):
                    break
                last, size = found[0], min(2 * size, len(ids))
            yield a + i, found[0], found[1]


def usable(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    v = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v")).filter("vec_id IS NOT NULL AND v IS NOT NULL AND size(v) > 0")
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return v.filter(~bad & F.exists("v", lambda x: x != 0))


def matrix(column: pa.Array, d: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def search(base: DataFrame, is_query: Column, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", measure: str = "ip", stages: int = 8, entries: int = 256, beam: int = 4, rerank: int = 256, sample_rows: int = 16_384, block_rows: int = 8_192, query_rows: int = 2_048) -> DataFrame:
    """The ``k`` nearest of each row for which ``is_query`` (over ``vec_id``) holds, against all rows.

    Codebooks are fitted on at most about ``sample_rows`` rows, picked by a hash of their id. Rows
    and queries meet block by block; a task holds one block of each.
    """
    spark, rows = base.sparkSession, usable(base, id_col, vec_col)
    schema = "query_id long, rank int, vec_id long, score double"
    sizes = rows.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n"), F.sum(is_query.cast("int")).alias("q")).collect()
    if not sizes:
        return spark.createDataFrame([], schema)
    d, n, nq = max(sizes, key=lambda r: (r["n"], r["d"]))
    rows = rows.filter(F.size("v") == d)
    below = min(int(sample_rows / n * 2**63), 2**63 - 1)
    picked = rows.filter(F.shiftrightunsigned(F.xxhash64("vec_id", F.lit(11)), 1) <= F.lit(below)).select("v").toArrow()
    sample = matrix(picked.column(0).combine_chunks(), d) if picked.num_rows else np.zeros((1, d))
    books = fit_codebooks(sample, stages, entries)
    shared = spark.sparkContext.broadcast(books)
    blocks, q_blocks = -(-n // block_rows), max(1, -(-nq // query_rows))

    def code(batches):
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(1), d)
                done = [encode(x[i : i + 1024], shared.value, beam) for i in range(0, len(x), 1024)]
                codes, norms = (np.concatenate(z) for z in zip(*done, strict=True))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(list(norms.astype(np.float32)), pa.list_(pa.float32()))], ["vec_id", "v", "codes", "norms"])

    coded = rows.mapInArrow(lean(code), "vec_id long, v array<double>, codes binary, norms array<float>")
    every = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    left = coded.select("*", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("blk"), every(q_blocks).alias("qb"))
    queries = rows.filter(is_query).select("vec_id", "v", F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(q_blocks)).cast("int").alias("qb"), every(blocks).alias("blk"))

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        out = [[], [], []]
        if a.num_rows and b.num_rows:
            a = a.combine_chunks()
            ids, x = a["vec_id"].to_numpy(), matrix(a["v"].combine_chunks(), d)
            codes = np.frombuffer(b"".join(a["codes"].to_pylist()), np.uint8).reshape(len(ids), -1)
            q_ids, q = b["vec_id"].to_numpy(), matrix(b["v"].combine_chunks(), d)
            for i, near, score in best_of_block(q, q_ids, shared.value, codes, matrix(a["norms"].combine_chunks(), 2), x, ids, k, rerank, measure):
                for col, part in zip(out, (np.full(len(near), q_ids[i]), near, score), strict=True):
                    col.append(part)
        cols = [np.concatenate(c) if c else np.zeros(0) for c in out]
        return pa.table({"query_id": pa.array(cols[0], pa.int64()), "vec_id": pa.array(cols[1], pa.int64()), "score": pa.array(cols[2], pa.float64())})

    near = left.groupBy("blk", "qb").cogroup(queries.groupBy("blk", "qb")).applyInArrow(lean_call(meet), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op1_additive_quantisation(spark, sf_dir: str) -> DataFrame:
    return search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
