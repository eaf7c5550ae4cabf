"""Token ids written as Re-Pair shards in ascending id order, and read back.

Documents are range-partitioned and sorted by id. Each task encodes its texts and cuts them into
shards of about ``shard_ids`` ids, whole documents each; a shard is one row of the output table
(``part, shard, ids_before, n_ids, blob``), so any store that Spark reaches can hold it. Reading
decodes document by document.

Defined results: null and empty texts are the end id alone; documents without an id come first;
repeated ids stay as rows of their own, in any order among themselves; an empty table gives no rows.
Extra columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.llm.common import lean, shared_dir, table
from crowdrank.llm.repair import Shard, compress, write_shard
from crowdrank.llm.tokens import default_path, encoder

SHARDS = "part int, shard int, ids_before long, n_ids long, blob binary"


class ShardBuilder:
    """Collects documents as piece numbers; ``flush`` gives their shard."""

    def __init__(self, enc, end_id: int, vocabulary: int) -> None:
        self.enc, self.end, self.vocabulary = enc, end_id, vocabulary
        self.docs, self.parts, self.words = [], [], 0

    def add(self, docs: list[int], texts: list[str | None]) -> None:
        numbers, edges = self.enc.pieces(texts)
        # -1 stands for the end of a document
        self.parts.append(np.insert(numbers.astype(np.int64), edges[1:], -1))
        self.docs += docs
        self.words += len(numbers) + len(docs)

    def flush(self) -> tuple[bytes, int]:
        seq = np.concatenate(self.parts) + 1
        used = np.zeros(self.enc.count + 1, bool)
        used[seq], used[0] = True, True
        flat, before = self.enc.expand(np.flatnonzero(used[1:]))
        sizes = np.concatenate(([1], np.diff(before)))
        flat = np.concatenate((np.array([self.end], flat.dtype), flat))
        seq = (np.cumsum(used) - 1)[seq]
        ends = np.flatnonzero(seq == 0)
        counts = np.diff(np.concatenate(([0], np.cumsum(sizes[seq])[ends])))
        rules, symbols, last = compress((flat, sizes), seq, 0, self.vocabulary)
        blob, total = write_shard(self.docs, counts, rules, symbols, last, self.vocabulary), int(counts.sum())
        self.docs, self.parts, self.words = [], [], 0
        if self.enc.full():
            self.enc.forget()
        return blob, total


def write_ids(docs: DataFrame, path: str, vocabulary_path: str, end_id: int = 0, vocabulary: int = 50_257, shard_words: int = 1_000_000, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Write the shard table to ``path``."""

    def run(batches):
        from pyspark import TaskContext

        part, shard, before = TaskContext.get().partitionId(), 0, 0
        build = ShardBuilder(encoder(vocabulary_path, spaced=True), end_id, vocabulary)

        def row():
            nonlocal shard, before
            blob, n = build.flush()
            out = pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([shard], pa.int32()), pa.array([before], pa.int64()), pa.array([n], pa.int64()), pa.array([blob], pa.binary())], ["part", "shard", "ids_before", "n_ids", "blob"])
            shard, before = shard + 1, before + n
            return out

        for b in batches:
            for i in range(0, b.num_rows, 128):
                own = b.slice(i, 128)
                build.add(own.column(0).to_pylist(), own.column(1).to_pylist())
                if build.words >= shard_words:
                    yield row()
        if build.docs:
            yield row()

    ordered = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col)).repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    ordered.mapInArrow(lean(run), SHARDS).write.option("compression", "zstd").parquet(path)


def read_ids(spark, path: str, keep_ids: bool = False) -> DataFrame:
    """One row a document from the shards: ``doc_id, start, n_tokens, ids_crc32`` and, if asked for, ``ids``."""
    shards = spark.read.schema(SHARDS).parquet(path)
    # one row a partition of the writer, a number that the data does not raise
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = shards.groupBy("part").agg(F.sum("n_ids").alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))

    def run(batches):
        for b in batches:
            for part, at, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                s = Shard(blob.as_py())
                s.expand_all()
                for lo in range(0, len(s.docs), 4096):
                    rows = [s.ids(i) for i in range(lo, min(lo + 4096, len(s.docs)))]
                    n = np.array([len(x) // 4 for x in rows])
                    starts = at + np.concatenate(([0], np.cumsum(n)[:-1]))
                    at += int(n.sum())
                    cols = [pa.array(s.docs[lo : lo + len(rows)], pa.int64()), pa.array([part] * len(rows), pa.int32()), pa.array(starts, pa.int64()), pa.array(n, pa.int64()), pa.array([zlib.crc32(x) for x in rows], pa.int64()), pa.array(rows if keep_ids else [None] * len(rows), pa.binary())]
                    yield pa.RecordBatch.from_arrays(cols, ["doc_id", "part", "start", "n_tokens", "ids_crc32", "ids"])

    docs = shards.select("part", "ids_before", "blob").mapInArrow(lean(run), "doc_id long, part int, start long, n_tokens long, ids_crc32 long, ids binary")
    out = docs.join(F.broadcast(base), "part").select("doc_id", (F.col("base") + F.col("start")).alias("start"), "n_tokens", "ids_crc32", "ids")
    return out if keep_ids else out.drop("ids")


def op8_token_output(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    path = f"{shared_dir(spark)}/ids-{uuid.uuid4().hex}"
    write_ids(docs, path, default_path("byte_bpe_50k.json"))
    return read_ids(spark, path)
