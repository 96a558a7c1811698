"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

A document is contaminated by an item when it holds at least ``num / den`` of the item's distinct word shingles. Items are indexed by
partitions of size: an item of n shingles is sketched by its n - need + l smallest shingle hashes (its bottom min-hashes), where need is the least
number of shared shingles and l grows with the size partition. A document that contains the item misses at most n - need shingles, so it holds
at least l of the sketch, wherever the passage lies and however long the document is: the search has no false negatives, unlike banded
signatures, whose chance of a match falls with the document's length. Candidates are then verified on all shingles of the item.

Items are indexed in blocks of at most ``BLOCK`` shingles, each sent to all tasks for one pass over the documents: the benchmark's size, never the
corpus', decides the number of passes. Documents are read map-only.

Null or empty texts hold and are nothing: no pair. An item of fewer than five words is one shingle of all its words; documents are looked through for runs
of that many words too, as long as such items exist.
Repeated rows give repeated pairs; null ids are passed on. Other columns are not read. Empty tables give an empty result.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.llm import common
from elastipool.llm.common import WordHashes, lean, prepare, shingle_runs, shingles, table

BLOCK = 1 << 22
#: Size partitions: least number of shingles, and sketch values a document must hold.
PARTITIONS = ((1, 1), (8, 2), (16, 3), (32, 4), (128, 8), (1024, 32))
PAIRS = "doc_id long, item_id long, n_item long, shared long"
_BITS = 22


class Index:
    """Sketches and whole shingle sets of a block of items."""

    def __init__(self, items: list[tuple[int, np.ndarray]], num: int, den: int, widths: tuple[int, ...] = (5,)):
        self.widths = widths
        self.ids = [i for i, _ in items]
        self.size = np.array([len(s) for _, s in items], np.int64)
        self.need = (self.size * num + den - 1) // den
        self.least = np.array([max(least for low, least in PARTITIONS if low <= n) for n in self.size], np.int64)
        self.least = np.minimum(self.least, self.need)
        owner = np.repeat(np.arange(len(items)), self.size)
        every = np.concatenate([s for _, s in items]) if items else np.zeros(0, np.uint64)
        o = np.lexsort((owner, every))
        self.key, self.owner = every[o], owner[o]
        rank = np.concatenate([np.arange(n) for n in self.size]) if items else np.zeros(0, np.int64)
        self.in_sketch = (rank < (self.size - self.need + self.least)[owner])[o] if items else np.zeros(0, bool)
        self.seen = np.zeros(1 << _BITS, bool)
        self.seen[(self.key[self.in_sketch] >> np.uint64(64 - _BITS)).astype(np.int64)] = True

    def _owners(self, hashes: np.ndarray, sketch: bool) -> np.ndarray:
        a, z = np.searchsorted(self.key, hashes, "left"), np.searchsorted(self.key, hashes, "right")
        n = z - a
        at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(a, n)
        return self.owner[at[self.in_sketch[at]]] if sketch else self.owner[at]

    def matches(self, words: np.ndarray) -> list[tuple[int, int, int]]:
        """(item id, item size, shared shingles) of the items contained in a document of these word hashes."""
        runs = [shingle_runs(words, k) for k in self.widths if k <= len(words) or k == max(self.widths)]
        s = runs[0] if len(runs) == 1 else np.unique(np.concatenate(runs))
        near = s[self.seen[(s >> np.uint64(64 - _BITS)).astype(np.int64)]]
        if not len(near):
            return []
        hit = np.bincount(self._owners(np.unique(near), True), minlength=len(self.ids))
        maybe = hit >= self.least
        if not maybe.any():
            return []
        shared = np.bincount(self._owners(np.unique(s), False), minlength=len(self.ids))
        return [(self.ids[k], int(self.size[k]), int(shared[k])) for k in np.flatnonzero(maybe & (shared >= self.need))]


def item_sets(items: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    def run(batches):
        known = WordHashes()
        for b in batches:
            words = [common.word_hashes(t, known) if t else np.zeros(0, np.uint64) for t in common.pairs_of(b, "text")]
            got = [shingles(w, width) for w in words]
            cols = [b.column(0), pa.array([len(g) for g in got], pa.int64()), pa.array([g.tobytes() for g in got], pa.binary()), pa.array([min(width, len(w)) for w in words], pa.int32())]
            yield pa.RecordBatch.from_arrays(cols, names=["item_id", "n", "items", "width"])

    return items.select(items[id_col].cast("long").alias("item_id"), items[text_col].cast("string").alias("text")).mapInArrow(lean(run), "item_id long, n long, items binary, width int")


def indexes(items: DataFrame, width: int, num: int, den: int, item_col: str, item_text: str) -> list:
    """Broadcast indexes of the items, each of BLOCK shingles or so."""
    spark = items.sparkSession
    prepare(spark)
    sets = item_sets(items, item_col, item_text, width).where("n > 0")
    total = sets.agg(F.sum("n")).first()[0] or 0
    blocks = max(1, -(-2 * total // BLOCK))

    def one(k: int):
        t = (sets if blocks == 1 else sets.where(F.pmod(F.xxhash64("items"), F.lit(blocks)) == k)).toArrow()
        return spark.sparkContext.broadcast(Index([(i, np.frombuffer(x, np.uint64)) for i, x in zip(t.column(0).to_pylist(), t.column(2).to_pylist())], num, den, tuple(sorted({width, *t.column(3).to_pylist()}))))

    return [one(k) for k in range(blocks)]


def contaminated(docs: DataFrame, items: DataFrame, width: int = 5, num: int = 75, den: int = 100, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """All pairs (doc_id, item_id, n_item, shared) with den * shared >= num * n_item."""
    prepare(docs.sparkSession)
    src = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))

    def one(index) -> DataFrame:
        def run(batches):
            known = WordHashes()
            for b in batches:
                rows = []
                for d, t in zip(b.column(0).to_pylist(), common.pairs_of(b, "text")):
                    if t:
                        rows += [(d, *m) for m in index.value.matches(common.word_hashes(t, known))]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows)], names=["doc_id", "item_id", "n_item", "shared"])

        return src.mapInArrow(lean(run), PAIRS)

    return reduce(DataFrame.unionAll, [one(x) for x in indexes(items, width, num, den, item_col, item_text)])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def without_contaminated(docs: DataFrame, items: DataFrame, width: int = 5, num: int = 75, den: int = 100, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """``docs`` without rows that contain an item; map-only, all columns kept, one pass for each block of items."""
    for index in indexes(items, width, num, den, item_col, item_text):
        docs = _filtered(docs, index, text_col)
    return docs


def _filtered(docs: DataFrame, index, text_col: str) -> DataFrame:
    at = docs.columns.index(text_col)

    def run(batches):
        known = WordHashes()
        for b in batches:
            texts = b.column(at).to_pylist()
            keep = [not (t and index.value.matches(common.word_hashes(t.encode(), known))) for t in texts]
            yield b.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
