"""Exact nearest neighbours of a stated query set: block matrix join on int8 tiles with error bounds.

Queries and candidates are dealt into a grid; a cell holds a bounded block of each, so cost is the product
of two stated sets in blocks and memory does not grow with either. Within a cell, vectors are quantised to int8 with
one scale each; products of int8 tiles are exact integers, and the norms of what quantisation left over bound
the error of every distance from both sides. Pairs whose lower bound exceeds the k-th smallest upper bound
are dropped; survivors are computed again on the original vectors in double precision and go into the heap of
their query. Heaps of the cells are merged by an aggregation that keeps k at every step.

Recall is 1 by construction: bounds only drop pairs that cannot be among the k nearest.

Defined cases: vectors that are null, empty, all zero, or hold null or non-finite components take no
part; vectors of different length are never compared; a query is not its own neighbour (by id);
equal distances go to the smaller id; rows that repeat an id are one vector or, if they differ, several of one
query or candidate: between two ids the smallest distance counts, so a query gets each neighbour once; fewer candidates
than k give them all; an empty table gives an empty result; other columns are left out, whatever their names.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mediarel.llm import common

#: Rows of a cell of the grid, for queries and for candidates.
QUERY_BLOCK = 8192
CANDIDATE_BLOCK = 16384
#: Sides of a tile within a cell.
TILE_QUERIES = 512
TILE_CANDIDATES = 2048


def usable(vector: Column) -> Column:
    """Not null, finite in every component, not all zero."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))
    return vector.isNotNull() & F.coalesce(F.forall(vector, finite) & F.exists(vector, lambda x: x != 0), F.lit(False))


def quantise(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 rows, their scales, and the norms of what is left over (rounded up)."""
    peak = np.abs(vectors).max(axis=1)
    scale = np.where(peak > 0, peak / 127.0, 1.0)
    codes = np.rint(vectors / scale[:, None]).astype(np.int8)
    rest = np.linalg.norm(vectors - codes * scale[:, None], axis=1) * (1 + 1e-9) + 1e-12 * peak
    return codes, scale, rest


def euclidean(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances of paired rows in double precision, components added in order."""
    total = np.zeros(len(a))
    for k in range(a.shape[1]):
        step = a[:, k] - b[:, k]
        total += step * step
    return np.sqrt(total)


class _Block:
    """Vectors of one side of a cell with their codes."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        self.ids, self.vectors = ids, vectors
        self.codes, self.scale, self.rest = quantise(vectors)
        # Products of int8 codes up to this length are whole numbers below 2**24, so float32 holds them exactly.
        self.kind = np.float32 if vectors.shape[1] * 127 * 127 < 1 << 24 else np.float64
        self.wide = self.codes.astype(self.kind)
        squares = (self.wide.astype(np.float64) ** 2).sum(axis=1)
        self.norm = squares * self.scale**2
        self.repeats = len(np.unique(ids)) < len(ids)


def search_cell(queries: _Block, candidates: _Block, k: int) -> list[list[tuple[float, int]]]:
    """For each query its k best (distance, id) among the candidates, in order."""
    best: list[list[tuple[float, int]]] = []
    for q0 in range(0, len(queries.ids), TILE_QUERIES):
        q = slice(q0, q0 + TILE_QUERIES)
        heaps: list[list[tuple[float, int]]] = [[] for _ in queries.ids[q]]
        worst = np.full(len(heaps), np.inf)
        for c0 in range(0, len(candidates.ids), TILE_CANDIDATES):
            c = slice(c0, c0 + TILE_CANDIDATES)
            dots = (queries.wide[q] @ candidates.wide[c].T).astype(np.float64) * queries.scale[q, None] * candidates.scale[None, c]
            squared = np.maximum(queries.norm[q, None] + candidates.norm[None, c] - 2 * dots, 0.0)
            # Rounding of the three terms above, in squared distance.
            slack = 1e-12 * (queries.norm[q, None] + candidates.norm[None, c])
            error = queries.rest[q, None] + candidates.rest[None, c]
            upper = np.sqrt(squared + slack) + error
            lower = np.sqrt(np.maximum(squared - slack, 0.0)) - error
            own = queries.ids[q, None] == candidates.ids[None, c]
            upper[own] = np.inf
            n = upper.shape[1]
            # Where ids repeat, the k smallest bounds may be of fewer ids; the heaps hold each id once.
            limit = np.partition(upper, k - 1, axis=1)[:, k - 1] if n > k and not candidates.repeats else np.full(len(heaps), np.inf)
            rows, cols = np.nonzero((lower <= np.minimum(limit, worst)[:, None]) & ~own)
            for s in range(0, len(rows), 1 << 17):
                r, o = rows[s : s + (1 << 17)], cols[s : s + (1 << 17)]
                exact = euclidean(queries.vectors[q][r], candidates.vectors[c][o])
                ids = candidates.ids[c][o]
                order = np.lexsort((ids, exact, r))
                r, exact, ids = r[order], exact[order], ids[order]
                if candidates.repeats:
                    first = np.sort(np.unique(np.stack((r, ids)), axis=1, return_index=True)[1])
                    r, exact, ids = r[first], exact[first], ids[first]
                # Of each query's survivors only the first k can enter its heap.
                rank = np.arange(len(r)) - np.searchsorted(r, r)
                for i in np.nonzero(rank < k)[0]:
                    heap, item = heaps[r[i]], (-exact[i], -int(ids[i]))
                    held = next((j for j, x in enumerate(heap) if x[1] == item[1]), None) if candidates.repeats else None
                    if held is not None:
                        if item > heap[held]:
                            heap[held] = item
                            heapq.heapify(heap)
                    elif len(heap) < k:
                        heapq.heappush(heap, item)
                    elif item > heap[0]:
                        heapq.heapreplace(heap, item)
                    worst[r[i]] = -heap[0][0] if len(heap) == k else np.inf
        best += [sorted((-d, -i) for d, i in heap) for heap in heaps]
    return best


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, query_block: int = QUERY_BLOCK, candidate_block: int = CANDIDATE_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score for ``queries`` against ``vectors`` (both vec_id, embedding)."""
    clean = lambda df: df.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & usable(F.col("embedding"))).distinct().withColumn("dim", F.size("embedding"))
    asked, offered = clean(queries), clean(vectors)
    n_queries, n_candidates = asked.count(), offered.count()
    rows, columns = max(1, -(-n_queries // query_block)), max(1, -(-n_candidates // candidate_block))
    # Queries go to every column of the grid and candidates to every row of it.
    spread = lambda df, own, n, other, m: df.withColumn(own, F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(n)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    left = spread(asked, "row", rows, "column", columns).groupBy("dim", "row", "column")
    right = spread(offered, "column", columns, "row", rows).groupBy("dim", "row", "column")

    def cell(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        block = lambda x: _Block(x["vec_id"].to_numpy(dtype=np.int64), np.stack(x["embedding"].to_numpy()))
        queries_, candidates = block(a), block(b)
        found = search_cell(queries_, candidates, k)
        pairs = [(int(q), i, d) for q, best in zip(queries_.ids, found, strict=True) for d, i in best]
        return pd.DataFrame(pairs, columns=["query_id", "vec_id", "score"])

    heaps = left.cogroup(right).applyInPandas(cell, "query_id long, vec_id long, score double")
    # At most k rows a query vector and column of the grid reach this; one shuffle serves both steps.
    nearer = heaps.repartition("query_id").groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))
    ranked = nearer.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op7_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = common.table(spark, sf_dir, "embeddings")
    return nearest(vectors, vectors.where(F.col("vec_id") % 100 == 0))


OP7_SQL = """
WITH v AS (
  SELECT DISTINCT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
d AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, min(sqrt(list_reduce(list_transform(list_zip(q.e, c.e), lambda z: (z[1] - z[2]) * (z[1] - z[2])), lambda a, b: a + b))) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e)
  WHERE q.vec_id % 100 = 0 GROUP BY q.vec_id, c.vec_id),
r AS (SELECT query_id, vec_id, score, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS INTEGER) AS rank FROM d)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
