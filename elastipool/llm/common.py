"""Shared pieces of the training-data operators."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.session import discard, materialise, plan_bytes, ship

#: Rows and bytes of an Arrow batch handed to Python: texts may be long, so batches are kept small.
ARROW_ROWS, ARROW_BYTES = "2000", "8388608"

def prepare(spark: SparkSession) -> None:
    """Ship the package and bound Arrow batches (both are runtime settings)."""
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BYTES)


def lean(run):
    """A map over Arrow batches that gives freed memory back at its end: workers are used again for other tasks, and what one leaves in its heap adds to the next."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim()

    return wrapped


def trim() -> None:
    """Return free heap pages to the system, where its C library can."""
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        return


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def bucket_count(df: DataFrame, per_bucket: int = 1 << 20, least: int = 64, most: int = 1 << 18) -> int:
    """A power of two that follows the input's size, so that no bucket grows with the corpus."""
    n = least
    size = plan_bytes(df)
    while n < most and n * per_bucket < size:
        n *= 2
    return n


def byte_views(col: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Offsets (n + 1), all bytes, and null mask of a string column, without decoding."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not pa.types.is_large_string(col.type) and not pa.types.is_string(col.type):
        col = col.cast(pa.string())
    wide = pa.types.is_large_string(col.type)
    bufs = col.buffers()
    off = np.frombuffer(bufs[1], np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    data = np.frombuffer(bufs[2], np.uint8) if bufs[2] is not None and bufs[2].size else np.zeros(0, np.uint8)
    null = np.asarray(col.is_null())
    return off, data, null


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash: every output bit depends on every input bit."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


class WordHashes(dict):
    """word (bytes) -> 64-bit hash, remembered up to a bounded number of words."""

    MOST = 100_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.MOST:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def word_hashes(text: bytes, known: WordHashes) -> np.ndarray:
    """Hashes of the words ``[^\\x20\\x09-\\x0D]+`` of a text whose A-Z are lower-cased; bytes.split() cuts at just these."""
    words = text.lower().split()
    return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def shingle_runs(words: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of ``width`` words in text order; of the whole sequence if it is shorter; none without words."""
    n = len(words)
    if n == 0:
        return np.zeros(0, np.uint64)
    k = min(width, n)
    acc = np.full(n - k + 1, k, np.uint64)
    for i in range(k):
        acc = mix(acc * _ODD[i % 5] + words[i : n - k + 1 + i])
    return acc


def shingles(words: np.ndarray, width: int) -> np.ndarray:
    """The distinct ones of :func:`shingle_runs`, sorted."""
    return np.unique(shingle_runs(words, width))


def pairs_of(batch: pa.RecordBatch, text: str) -> list[bytes | None]:
    """Each text as UTF-8 bytes, None for null."""
    off, data, null = byte_views(batch.column(batch.schema.get_field_index(text)))
    return [None if null[i] else data[off[i] : off[i + 1]].tobytes() for i in range(batch.num_rows)]


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Smallest reachable node of each node of ``edges(a, b)`` longs, as (node, root); alternates large-star and small-star
    rounds, each written to the shared folder, until the edges stay as they are. Nothing is gathered on the driver."""

    def star(e: DataFrame, large: bool) -> DataFrame:
        both = e.union(e.select("b", "a")) if large else e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        j = both.join(low, "a")
        if large:
            out = j.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        else:
            out = j.select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        return out.where("a <> b").distinct()

    e = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "cc")
    seen = None
    for _ in range(most_rounds):
        nxt = materialise(star(star(e, True), False), "cc")
        now = nxt.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        discard(e)
        e = nxt
        if (now.n, now.h) == seen:
            break
        seen = (now.n, now.h)
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("a").alias("node"), F.col("b").alias("root"))


__all__ = [
    "ARROW_BYTES", "ARROW_ROWS", "WordHashes", "bucket_count", "byte_views", "components", "discard", "lean", "materialise", "mix",
    "pairs_of", "plan_bytes", "prepare", "shingle_runs", "shingles", "table", "word_hashes",
]
