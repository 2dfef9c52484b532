"""Nearest neighbours of a stated query set by a block matrix join with int8 tiles.

Queries travel in blocks of bounded size; every block is one pass over all
candidates, and is released before the next one is gathered. A task multiplies
the int8 codes of a block and of a tile of candidates (as float32 over at most
1,024 components at a time, where sums of such products are exact integers), which
gives each cosine with a proven error bound from the two quantisation residuals.
Pairs whose upper bound reaches the best lower bounds so far are recomputed in
double precision on the original vectors and merged into one heap a query; the
heaps of all tasks are merged by rank.

Equal vectors of a tile are multiplied once and keep their smallest ids, so a
very common vector adds no more pairs than a rare one. The result is exact:
recall against brute force is 1.

Defined results: vectors that are null, empty, zero, of overflowing norm, or
hold null or non-finite components take no part, as do null ids; vectors are
compared with those of their own length only; repeated rows of one id are one
candidate, at its best score, and a repeated query id searches with its smallest
vector; ties go to the smaller vec_id; fewer than k candidates give fewer rows;
an empty table gives none; extra columns are ignored.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.llm.runtime import cut, one_blas_thread

#: Queries of one block: 4,096 of 64 doubles are 2 MB to broadcast.
QUERY_BLOCK = 4096
TILE_ROWS = 2048
#: Components whose code products sum exactly in single precision: 1,024 times 127 squared is under 2^24.
EXACT = 1024
SLACK = 1e-9


def sound(embedding: Column) -> Column:
    """Whether a vector can take part."""
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf")))
    as_doubles = embedding.cast("array<double>")
    norm = F.aggregate(as_doubles, F.lit(0.0), lambda a, x: a + x * x)
    return embedding.isNotNull() & ~F.exists(as_doubles, bad) & (norm > 0) & (norm < F.lit(float("inf")))


def running_dot(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row dots in double precision, summed from the first component on."""
    out = np.zeros(len(a))
    for k in range(a.shape[1]):
        out += a[:, k] * b[:, k]
    return out


class Codes:
    """Unit vectors as int8 codes with scales and residual norms."""

    def __init__(self, vectors: np.ndarray):
        self.vectors = vectors
        self.norms = np.sqrt(running_dot(vectors, vectors))
        unit = vectors / self.norms[:, None]
        self.scale = np.abs(unit).max(axis=1) / 127
        self.codes = np.rint(unit / self.scale[:, None]).astype(np.int8)
        self.residual = np.linalg.norm(unit - self.scale[:, None] * self.codes, axis=1)


def tile_bounds(queries: Codes, tile: Codes) -> tuple[np.ndarray, np.ndarray]:
    """Approximate cosines of all pairs and how far each may be off."""
    product = np.zeros((len(queries.codes), len(tile.codes)))
    for k in range(0, queries.codes.shape[1], EXACT):
        part = slice(k, k + EXACT)
        product += queries.codes[:, part].astype(np.float32) @ tile.codes[:, part].astype(np.float32).T
    near = product * queries.scale[:, None] * tile.scale[None, :]
    off = tile.residual[None, :] + queries.residual[:, None] * (1 + tile.residual[None, :]) + SLACK
    return near, off


def distinct_vectors(vectors: np.ndarray, ids: np.ndarray, keep: int) -> tuple[np.ndarray, list[list[int]]]:
    """Equal rows once, with their ``keep`` smallest distinct ids."""
    raw = np.ascontiguousarray(vectors + 0.0).view(np.dtype((np.void, vectors.shape[1] * 8))).ravel()
    _, first, group = np.unique(raw, return_index=True, return_inverse=True)
    order = np.lexsort((ids, group))
    names: list[list[int]] = [[] for _ in first]
    for g, i in zip(group[order].tolist(), ids[order].tolist(), strict=True):
        if len(names[g]) < keep and (not names[g] or names[g][-1] != i):
            names[g].append(i)
    return vectors[first], names


class Search:
    """Heaps of one query block over the candidates of one task."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int):
        self.ids, self.codes, self.k = ids, Codes(vectors), k
        self.heaps: list[list[tuple[float, int]]] = [[] for _ in ids]
        self.floor = np.full(len(ids), -np.inf)

    def add(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        vectors, names = distinct_vectors(vectors, ids, self.k + 1)
        tile = Codes(vectors)
        near, off = tile_bounds(self.codes, tile)
        floor = self.floor
        first = np.array([n[0] for n in names])
        order = np.argsort(first, kind="stable")
        starts = np.flatnonzero(np.r_[True, np.diff(first[order]) > 0])
        if len(starts) > self.k:  # k + 1 different ids reach this bound, and one of them may be the query itself
            by_id = near - off if len(starts) == len(first) else np.maximum.reduceat((near - off)[:, order], starts, axis=1)
            at = len(starts) - self.k - 1
            floor = np.maximum(floor, np.partition(by_id, at, axis=1)[:, at])
        row, col = np.nonzero(near + off >= floor[:, None])
        score = running_dot(self.codes.vectors[row], vectors[col]) / (self.codes.norms[row] * tile.norms[col])
        for q, c, s in zip(row.tolist(), col.tolist(), score.tolist(), strict=True):
            if s >= self.floor[q]:
                for name in names[c]:
                    if name != self.ids[q]:
                        self._push(q, s, name)

    def _push(self, q: int, score: float, name: int) -> None:
        heap, item = self.heaps[q], (score, -name)
        for at, (held, other) in enumerate(heap):
            if other == -name:
                if held < score:
                    heap[at] = item
                    heapq.heapify(heap)
                break
        else:
            if len(heap) < self.k:
                heapq.heappush(heap, item)
            elif item > heap[0]:
                heapq.heapreplace(heap, item)
        if len(heap) == self.k:
            self.floor[q] = heap[0][0]

    def rows(self) -> Iterator[tuple[int, int, float]]:
        for q, heap in zip(self.ids.tolist(), self.heaps, strict=True):
            for score, name in heap:
                yield q, -name, score


def _arrays(ids: pa.Array, vectors: pa.Array) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Ids and matrix of each vector length."""
    names = np.asarray(ids)
    sizes = np.asarray(vectors.value_lengths())
    flat = np.asarray(vectors.flatten())
    ends = np.cumsum(sizes)
    out = {}
    for size in np.unique(sizes).tolist():
        at = np.flatnonzero(sizes == size)
        out[size] = names[at], flat[(ends[at] - size)[:, None] + np.arange(size)]
    return out


def nearest(vectors: DataFrame, is_query: Column, k: int = 5, query_block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest by cosine of each query among all other rows."""
    spark = vectors.sparkSession
    rows = vectors.where(F.col("vec_id").isNotNull() & sound(F.col("embedding"))).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    queries = rows.where(is_query).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    total = rows.where(is_query).select("vec_id").distinct().count()
    blocks = max(1, -(-total // query_block))

    def one_pass(block: int) -> DataFrame:
        mine = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == block).toArrow()
        held = _arrays(mine.column("vec_id").combine_chunks(), mine.column("embedding").combine_chunks()) if mine.num_rows else {}
        shared = spark.sparkContext.broadcast(held)  # about query_block vectors, whatever the table's size

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            one_blas_thread()
            searches = {size: Search(ids, m, k) for size, (ids, m) in shared.value.items()}
            for batch in batches:
                for start in range(0, batch.num_rows, TILE_ROWS):
                    part = batch.slice(start, TILE_ROWS)
                    for size, (ids, m) in _arrays(part.column("vec_id"), part.column("embedding")).items():
                        if size in searches:
                            searches[size].add(ids, m)
            found = [r for s in searches.values() for r in s.rows()]
            if found:
                q, v, s = zip(*found, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(v, pa.int64()), pa.array(s, pa.float64())], ["query_id", "vec_id", "score"])

        found = cut(rows.mapInArrow(run, "query_id long, vec_id long, score double"))  # k rows a query and task
        shared.destroy()
        return found

    found = reduce(DataFrame.unionAll, [one_pass(b) for b in range(blocks)])
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def oracle_sql(every: int = 50, k: int = 5) -> str:
    return f"""
WITH v AS (
  SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[]) > 0),
p AS (
  SELECT q.vec_id AS query_id, c.vec_id,
         list_inner_product(q.e, c.e) / (sqrt(list_inner_product(q.e, q.e)) * sqrt(list_inner_product(c.e, c.e))) AS score
  FROM v q JOIN v c ON q.vec_id % {every} = 0 AND c.vec_id <> q.vec_id AND len(q.e) = len(c.e)),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= {k}"""
