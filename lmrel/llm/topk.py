"""Exact top-k inner products by a three-phase uniform threshold.

A score is the sum of m partial scores, one per group of dimensions.  Phase 1: every task lists,
for each query and group, its candidates of highest partial score and gives the exact scores of the
best of them.  The k-th best gathered is a lower bound t of the true k-th score, so a candidate of
the answer has a partial score of t / m or more in some group.  Phase 2 sends this cutoff to all
tasks and collects the entries that reach it; phase 3 resolves their other groups exactly and keeps
the scores of t or more.  Queries go in blocks of bounded bytes against all rows, each block in its
own pass: nothing that is broadcast grows with the table.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import lean, reliable, table

#: Dimension groups, bytes of a broadcast block of queries, scores of a matrix held at once.
GROUPS, BLOCK_BYTES, AT_ONCE = 4, 32 << 20, 1 << 20
SCALE = 256


def usable(vector: Column) -> Column:
    """Neither null nor with a null, NaN or infinite component, nor empty."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & ~F.coalesce(bad, F.lit(False))


def quantised(column: pa.Array, width: int) -> np.ndarray:
    """floor(256 x) of the vectors as a matrix of ``width`` columns; shorter vectors are filled with 0."""
    sizes = np.asarray(column.value_lengths())
    flat = np.floor(SCALE * np.asarray(column.flatten().cast(pa.float64())))
    out = np.zeros((len(sizes), width))
    out[np.arange(width) < sizes[:, None]] = flat
    return out


def _groups(width: int) -> list[slice]:
    step = max(1, math.ceil(width / GROUPS))
    return [slice(i, i + step) for i in range(0, width, step)]


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of integers, exact: in doubles while they stay below 2**53."""
    top = (np.abs(a).max(initial=0) or 1) * (np.abs(b).max(initial=0) or 1) * max(1, a.shape[1])
    return a @ b.T if top < 2**53 else (a.astype(np.int64) @ b.astype(np.int64).T)


def _batches(it: Iterator[pa.RecordBatch], queries: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for batch in it:
        ids, vectors = batch.column(0).to_numpy(zero_copy_only=False), quantised(batch.column(1), queries.shape[1])
        yield from ((ids[i : i + 8192], vectors[i : i + 8192]) for i in range(0, len(ids), 8192))


class _Best:
    """The k best (score, smaller id first) of each query so far."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.rows: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.held = 0
        self.bound = 4 * n * k + 4096

    def add(self, query: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        if len(query):
            self.rows.append((query, ids, scores.astype(np.int64)))
            self.held += len(query)
            if self.held > self.bound:
                self.rows = [self.best()]
                self.held = len(self.rows[0][0])

    def best(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if not self.rows:
            return (np.zeros(0, np.int64),) * 3
        query, ids, scores = (np.concatenate(x) for x in zip(*self.rows))
        order = np.lexsort((ids, -scores, query))
        query, ids, scores = query[order], ids[order], scores[order]
        first = np.searchsorted(query, query, side="left")
        keep = np.arange(len(query)) - first < self.k
        return query[keep], ids[keep], scores[keep]


def _out(query_ids: np.ndarray, best: _Best) -> pa.RecordBatch:
    query, ids, scores = best.best()
    return pa.RecordBatch.from_arrays([pa.array(query_ids[query], pa.int64()), pa.array(ids, pa.int64()), pa.array(scores, pa.int64())], ["query_id", "vec_id", "score"])


def _pass(rows: DataFrame, query_ids: np.ndarray, queries: np.ndarray, k: int) -> DataFrame:
    spark = rows.sparkSession
    sent = spark.sparkContext.broadcast((query_ids, queries))
    schema = "query_id long, vec_id long, score long"

    def first(it):
        ids_q, q = sent.value
        best, step = _Best(len(ids_q), k), max(1, AT_ONCE // 8192)
        for ids, c in _batches(it, q):
            for i in range(0, len(q), step):
                own = ids_q[i : i + step, None] == ids
                seen = []
                for g in _groups(q.shape[1]):
                    part = _product(q[i : i + step, g], c[:, g]).astype(np.float64)
                    part[own] = -np.inf
                    top = min(k, len(ids))
                    seen.append(np.argpartition(-part, top - 1, axis=1)[:, :top])
                at = np.sort(np.concatenate(seen, axis=1), axis=1)
                new = np.ones(at.shape, dtype=bool)
                new[:, 1:] = at[:, 1:] != at[:, :-1]
                row, col = np.nonzero(new)
                col = at[row, col]
                fine = ~own[row, col]
                row, col = row[fine], col[fine]
                a, b = q[i + row], c[col]
                top = (np.abs(a).max(initial=0) or 1) * (np.abs(b).max(initial=0) or 1) * a.shape[1]
                score = np.einsum("ij,ij->i", a, b) if top < 2**53 else np.einsum("ij,ij->i", a.astype(np.int64), b.astype(np.int64))
                best.add(row + i, ids[col], score)
        yield _out(ids_q, best)

    ranked = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    gathered = rows.mapInArrow(lean(first), schema).withColumn("at", F.row_number().over(ranked)).where(F.col("at") == k)
    floor = {r.query_id: r.score for r in gathered.select("query_id", "score").collect()}
    least = np.array([floor.get(int(i), -(1 << 62)) for i in query_ids], dtype=np.float64)
    cutoff = spark.sparkContext.broadcast(least)

    def second(it):
        ids_q, q = sent.value
        t = cutoff.value
        best, step = _Best(len(ids_q), k), max(1, AT_ONCE // 8192)
        for ids, c in _batches(it, q):
            for i in range(0, len(q), step):
                groups = _groups(q.shape[1])
                parts = [_product(q[i : i + step, g], c[:, g]) for g in groups]
                reach = np.zeros(parts[0].shape, dtype=bool)
                for part in parts:
                    reach |= part * len(groups) >= t[i : i + step, None]
                reach &= ids_q[i : i + step, None] != ids
                row, col = np.nonzero(reach)
                score = sum(part[row, col].astype(np.int64) for part in parts)
                fine = score >= t[i + row]
                best.add(row[fine] + i, ids[col[fine]], score[fine])
        yield _out(ids_q, best)

    return rows.mapInArrow(lean(second), schema).withColumn("rank", F.row_number().over(ranked)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score of the k highest integer inner products of every query.

    Both inputs have vec_id and embedding.  Vectors null, empty or with a null or non-finite
    component take no part; shorter vectors count as filled with zeros; ties go to the smaller
    vec_id; rows of the query's own vec_id are no candidates; a vec_id with several query rows asks
    once, by the least vector; candidates that are repeated are repeated in the answer.
    """
    spark = vectors.sparkSession
    rows = vectors.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    asked = queries.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    asked = asked.groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    n, width = asked.agg(F.count(F.lit(1)), F.max(F.size("embedding"))).first()
    blocks = max(1, math.ceil((n or 0) * (width or 1) * 8 / BLOCK_BYTES))
    width = max(width or 1, rows.agg(F.max(F.size("embedding"))).first()[0] or 1)
    out = None
    for b in range(blocks if n else 0):
        part = asked if blocks == 1 else asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        block = sorted(part.collect(), key=lambda r: r.vec_id)
        if not block:
            continue
        arrays = pa.array([r.embedding for r in block], pa.list_(pa.float64()))
        done = _pass(rows, np.array([r.vec_id for r in block], dtype=np.int64), quantised(arrays, width), k)
        done = done if blocks == 1 else reliable(done)
        out = done if out is None else out.unionByName(done)
    return out if out is not None else spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")


def op3_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five best rows for every row whose vec_id is divisible by 50, against all rows."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return exact_top_k(rows, rows.where("vec_id % 50 = 0"))


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS q
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT a.vec_id AS query_id, b.vec_id AS vec_id, CAST(list_inner_product(a.q, b.q) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
