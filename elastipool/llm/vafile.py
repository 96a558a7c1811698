"""Exact top-k search by inner product with vector-approximation files.

Each component x becomes floor(SCALE * x). Vectors are packed into blocks; beside the exact integers a block keeps one cell number per component,
of 256 equal cells between the block's least and greatest value of that component. A query block scans only the cells of a data block: the cell centre
gives an approximate score, and half a cell times the query's absolute value bounds its error. Exact vectors are then read in order of their
best possible score until the k-th exact score found so far is at least the next bound; the k-th score is carried from block to block
of a task. So the result is exact whatever the cells are, and the whole data take part.

Queries are a stated set and meet the data block by block; both sides are packed tables in the shared folder. Their blocks are dealt into a grid of at most
``QGROUP`` query blocks by ``DGROUP`` data blocks a cell, so neither side gathers in one task, however many vectors share a length. Per pair of blocks at most k rows
a query leave, and the final ranking keeps k a query.

Vectors that are null, empty, or hold a null or non-finite component, and rows without an id, take no part. Vectors meet vectors of their own length
only. Rows that share the query's id are its own; a query id given more than once is answered once, for its greatest vector. Scores beyond 64 bits wrap.
Other columns are not read. Equal scores go to the smaller id; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.llm.common import materialise, prepare, table

SCALE, K, EVERY, ROWS, QUERIES = 1024, 10, 100, 1024, 128
QGROUP, DGROUP = 256, 512
BLOCK = "dim int, ids binary, exact binary, cells binary, low binary, step binary"
QBLOCK = "dim int, ids binary, exact binary"


def packed(vectors: DataFrame, rows: int, cells: bool) -> DataFrame:
    """Blocks of at most ``rows`` (id, v array<long>) of equal length."""

    def run(batches):
        held: dict[int, list] = {}

        def block(dim):
            ids, v = (np.concatenate(x) for x in zip(*held.pop(dim)))
            out = {"dim": [dim], "ids": [ids.tobytes()], "exact": [v.tobytes()]}
            if cells:
                low, high = v.min(0).astype(np.float64), v.max(0).astype(np.float64)
                step = np.maximum((high - low) / 255.0, 1e-9)
                out |= {"cells": [np.clip(np.rint((v - low) / step), 0, 255).astype(np.uint8).tobytes()], "low": [low.tobytes()], "step": [step.tobytes()]}
            return pa.RecordBatch.from_pydict({k: pa.array(x, pa.int32() if k == "dim" else pa.binary()) for k, x in out.items()})

        for b in batches:
            ids = np.asarray(b.column(0))
            lists = b.column(1)
            off, flat = np.asarray(lists.offsets), np.asarray(lists.values)
            dims = np.diff(off)
            for dim in np.unique(dims).tolist():
                at = np.flatnonzero(dims == dim)
                for k in range(0, len(at), rows):
                    part = at[k : k + rows]
                    held.setdefault(dim, []).append((ids[part], flat[off[part][:, None] + np.arange(dim)]))
                    if sum(len(x[0]) for x in held[dim]) >= rows:
                        yield block(dim)
        for dim in list(held):
            yield block(dim)

    return vectors.mapInArrow(run, BLOCK if cells else QBLOCK)


def search(vectors: DataFrame, is_query, k: int = K, scale: int = SCALE, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows of highest integer inner product for each row where ``is_query`` holds."""
    prepare(vectors.sparkSession)
    v = F.transform(vectors[vec_col], lambda x: x.cast("double"))
    fine = ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    base = vectors.where(vectors[id_col].isNotNull() & (F.size(vec_col) > 0) & F.coalesce(fine, F.lit(False)))
    ints = F.transform(v, lambda x: F.floor(x * scale).cast("long"))
    data = materialise(packed(base.select(vectors[id_col].cast("long").alias("id"), ints.alias("v")), ROWS, True), "va-data", "snappy")
    chosen = base.where(is_query).select(vectors[id_col].cast("long").alias("id"), ints.alias("v")).groupBy("id").agg(F.max("v").alias("v"))
    asked = materialise(packed(chosen, QUERIES, False), "va-queries")
    q_groups, d_groups = (max(1, -(-t.count() // size)) for t, size in ((asked, QGROUP), (data, DGROUP)))
    group = lambda n: F.pmod(F.xxhash64("ids"), F.lit(n)).cast("int")
    copies = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = asked.select("dim", F.col("ids").alias("q_ids"), F.col("exact").alias("q"), group(q_groups).alias("qg"), copies(d_groups).alias("dg"))
    both = left.join(data.withColumn("dg", group(d_groups)).withColumn("qg", copies(q_groups)), ["dim", "qg", "dg"])
    # one row for each pair of blocks; a data block is scanned by as many tasks as there are query blocks
    got = both.select("dim", "q_ids", "q", "ids", "exact", "cells", "low", "step").mapInArrow(_scan(k), "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return got.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _scan(k: int):
    def run(batches):
        floor: dict[int, np.ndarray] = {}  # k best scores of each query in this task
        for b in batches:
            for i in range(b.num_rows):
                dim = b.column(0)[i].as_py()
                q_ids, ids = (np.frombuffer(b.column(c)[i].as_buffer(), np.int64) for c in (1, 3))
                q, exact = (np.frombuffer(b.column(c)[i].as_buffer(), np.int64).reshape(-1, dim) for c in (2, 4))
                cells = np.frombuffer(b.column(5)[i].as_buffer(), np.uint8).reshape(-1, dim)
                low, step = (np.frombuffer(b.column(c)[i].as_buffer(), np.float64) for c in (6, 7))
                qf = q.astype(np.float64)
                about = cells.astype(np.float64) @ (qf * step).T + (qf @ low)
                slack = np.abs(qf) @ (step * 0.500001) + 1.0 + np.abs(about).max(0, initial=0) * 1e-9
                out = []
                for j, query in enumerate(q_ids.tolist()):
                    best = floor.get(query, np.zeros(0, np.int64))
                    upper = about[:, j] + slack[j]
                    order = np.flatnonzero(upper >= best[-1]) if len(best) >= k else np.arange(len(ids))
                    order = order[ids[order] != query]
                    if len(order) > 4 * k:
                        # no row below the k-th lower bound can be among the k best
                        kth = np.partition(upper[order], len(order) - k)[len(order) - k] - 2 * slack[j]
                        order = order[upper[order] >= kth]
                    order = order[np.argsort(-upper[order], kind="stable")]
                    rows, scores, at = [], [], 0
                    while at < len(order):
                        if len(best) >= k and upper[order[at]] < best[-1]:
                            break
                        part = order[at : at + 4 * k]
                        s = exact[part] @ q[j]
                        best = np.sort(np.concatenate([best, s]))[::-1][:k]
                        rows.append(part)
                        scores.append(s)
                        at += len(part)
                    floor[query] = best
                    if rows:
                        r, s = np.concatenate(rows), np.concatenate(scores)
                        o = np.lexsort((ids[r], -s))[:k]
                        out.append((np.full(len(o), query), ids[r[o]], s[o]))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out)], names=["query_id", "vec_id", "score"])

    return run


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return search(t, F.col("vec_id") % EVERY == 0)


ORACLE_SQL = """
WITH v AS (
  SELECT vec_id, [CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT) FOR x IN embedding] AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(CAST(x AS DOUBLE))]) = 0
), c AS (
  SELECT q.vec_id AS query_id, d.vec_id AS vec_id, CAST(list_sum([q.e[i] * d.e[i] FOR i IN range(1, len(q.e) + 1)]) AS BIGINT) AS score
  FROM v q JOIN v d ON q.vec_id % 100 = 0 AND d.vec_id <> q.vec_id AND len(q.e) = len(d.e)
), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM c)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
