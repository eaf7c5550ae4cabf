"""Helpers that several operators of this subpackage share."""

from __future__ import annotations

import contextlib
import ctypes
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from crowdrank.session import shared_dir


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame, thin: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends, lost executors lose nothing.

    ``thin``: narrow rows (labels, edges) are written by an eighth as many tasks as there are shuffle
    partitions, or twice the cores if that is more, so small tables do not become thousands of files.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}"
    if thin:
        most = int(spark.conf.get("spark.sql.shuffle.partitions", "200")) // 8
        df = df.coalesce(max(8, 2 * spark.sparkContext.defaultParallelism, most))
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def lean(run):
    """A function over Arrow batches that gives freed memory back to the system when it ends.

    Python workers are used again by later stages; without this each keeps its peak.
    """

    def wrapped(*args):
        try:
            yield from run(*args)
        finally:
            release()

    return wrapped


def lean_call(f):
    """The same for a function of one group or of two (Spark counts the arguments)."""

    def one(a):
        try:
            return f(a)
        finally:
            release()

    def two(a, b):
        try:
            return f(a, b)
        finally:
            release()

    return one if f.__code__.co_argcount == 1 else two


def release() -> None:
    """Drop what the allocators of this process hold but do not use."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


#: The white space of the word contract, 0x20 and 0x09 to 0x0D.
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: One random 64-bit value a byte, and an odd base with its powers' inverses modulo 2**64.
_BYTE = np.random.default_rng(20240607).integers(1, 2**63, 256, dtype=np.uint64)
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 2**64)


def mix(h: np.ndarray) -> np.ndarray:
    """Finalise 64-bit hashes (xor-shift and multiply), so that their low and high bits are usable."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


_POWERS = {"base": np.ones(1, np.uint64), "inverse": np.ones(1, np.uint64)}


def _powers(kind: str, n: int) -> np.ndarray:
    if len(_POWERS[kind]) < n:
        m = 1 << (n - 1).bit_length()
        step = np.full(m, _BASE if kind == "base" else _INVERSE, np.uint64)
        step[0] = 1
        _POWERS[kind] = np.multiply.accumulate(step)
    return _POWERS[kind][:n]


def byte_sums(a: np.ndarray) -> np.ndarray:
    """Prefix sums from which ``run_hash`` takes the hash of any run of bytes."""
    sums = np.zeros(len(a) + 1, np.uint64)
    np.cumsum(_BYTE[a] * _powers("base", len(a)), out=sums[1:])
    return sums


def run_hash(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return mix((sums[ends] - sums[starts]) * _powers("inverse", len(sums))[starts] + (ends - starts).astype(np.uint64))


def word_hashes(data: bytes, also_space: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and 64-bit hashes of the maximal runs of non-space bytes, without a Python loop.

    A word's hash is a polynomial of its bytes, taken from prefix sums and shifted back by the
    inverse power of its start, so equal words have equal hashes wherever they stand.
    """
    a = np.frombuffer(data, np.uint8)
    inside = np.zeros(len(a) + 2, bool)
    inside[1:-1] = ~also_space[a]
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    starts, ends = edge[::2], edge[1::2]
    return starts, ends, run_hash(byte_sums(a), starts, ends)


def gram_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """64-bit hashes of all runs of ``k`` word hashes (``len(words) - k + 1`` of them)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for i in range(k):
        h = h * np.uint64(0x2545F4914F6CDD1D) + words[i : i + n]
    return mix(h)
