"""Packing by shortest pack first over the length histogram.

Documents are tokenized and cut into full-length pieces and one rest. The histogram of piece
lengths (at most ``capacity`` entries) goes to the driver, which places lengths longest first, each
into the packs with the smallest sum, and keeps counts of packing patterns instead of packs. A piece
finds its pattern by its rank among the pieces of its length; ranks come from counts by partition
and length, so no length gathers in one task.

Defined results: null or empty text is a document of its end id alone; repeated rows and rows without
an id are packed one by one; lengths that tie take ranks in the order in which they are read; an empty
table gives no rows. Columns other than the id and the text are ignored.
"""

from __future__ import annotations

import heapq
import zlib
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.llm.common import cut
from crowdrank.llm.tokens import default_path, encoder

PIECES = "doc_id long, start long, length int, ids_crc32 long, doc_tokens long, part int, local long, ids binary"


def pieces(docs: DataFrame, path: str, end_id: int, capacity: int, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Pieces with their partition and their rank among its pieces of the same length."""

    def run(batches):
        from pyspark import TaskContext

        enc, part, seen = encoder(path, spaced=False, keep=600_000), TaskContext.get().partitionId(), Counter()
        end = end_id.to_bytes(4, "little")
        for b in batches:
            out = []
            for doc, ids in zip(b.column(0).to_pylist(), enc.encode_all(b.column(1).to_pylist()), strict=True):
                ids += end
                n = len(ids) // 4
                for s in range(0, n, capacity):
                    piece = ids[4 * s : 4 * (s + capacity)]
                    k = len(piece) // 4
                    out.append((doc, s, k, zlib.crc32(piece), n, part, seen[k], piece if keep_ids else None))
                    seen[k] += 1
            cols = list(zip(*out, strict=True)) or [[]] * 8
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "local", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col)).mapInArrow(run, PIECES)


def shortest_pack_first(histogram: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths of one pack, longest first) with the number of packs of each."""
    open_packs: list[tuple[int, tuple[int, ...], int]] = []
    done: list[tuple[tuple[int, ...], int]] = []
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            if not open_packs or open_packs[0][0] + length > capacity:
                total, pattern, n = 0, (), left
            else:
                total, pattern, n = heapq.heappop(open_packs)
                if n > left:
                    heapq.heappush(open_packs, (total, pattern, n - left))
                    n = left
            left -= n
            grown = (total + length, (*pattern, length), n)
            done.append(grown[1:]) if grown[0] == capacity else heapq.heappush(open_packs, grown)
    merged = Counter()
    for pattern, n in [*done, *(p[1:] for p in open_packs)]:
        merged[pattern] += n
    return sorted(merged.items(), reverse=True)


def slots(patterns: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int, list[int]]]:
    """For each length the ranges of ranks: ``length, lo, hi, first sequence, pieces a pack, offsets``."""
    out, base, used = [], 0, Counter()
    for pattern, n in patterns:
        at, offsets = 0, {}
        for x in pattern:
            offsets.setdefault(x, []).append(at)
            at += x
        for x, where in offsets.items():
            out.append((x, used[x], used[x] + n * len(where), base, len(where), where))
            used[x] += n * len(where)
        base += n
    return out


def pack(cut_pieces: DataFrame, capacity: int) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to the rows of ``pieces``, which must be stored."""
    spark = cut_pieces.sparkSession
    counts = cut_pieces.groupBy("part", "length").count()
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("part", "length", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("count").alias("n")).collect()}
    table = spark.createDataFrame(slots(shortest_pack_first(histogram, capacity)), "length int, lo long, hi long, first long, each long, offsets array<int>")
    ranked = cut_pieces.join(base, ["part", "length"]).withColumn("rank", F.col("base") + F.col("local"))
    # at most a few patterns for each of ``capacity`` lengths: a size that the data does not raise
    placed = ranked.join(F.broadcast(table), "length").filter("rank >= lo AND rank < hi")
    k = F.col("rank") - F.col("lo")
    return placed.withColumn("sequence_id", F.col("first") + F.floor(k / F.col("each")).cast("long")).withColumn("offset", F.element_at("offsets", (F.pmod(k, F.col("each")) + 1).cast("int")).cast("long")).drop("lo", "hi", "first", "each", "offsets", "rank", "base", "local", "part")


def pack_documents(docs: DataFrame, capacity: int = 2048, end_id: int = 1, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Tokenize, cut and pack. With ``keep_ids`` the ids of each piece stay in the column ``ids``."""
    out = pack(cut(pieces(docs, path or default_path("word_bpe_49k.json"), end_id, capacity, id_col, text_col, keep_ids)), capacity)
    return out if keep_ids else out.drop("ids")


def op4_packing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return pack_documents(docs).select("doc_id", "start", F.col("length").cast("long").alias("length"), "ids_crc32", "doc_tokens", "sequence_id", "offset")
