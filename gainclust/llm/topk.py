"""Exact top-k by integer inner product: matrix products of query blocks with tiles of rows, partial selection per
tile, merged per partition, then by salted groups, then per query.

Every component becomes floor(scale * x). Queries and rows meet in tiles (tiles.py). Products run in float64 while
exact, else in int64, else in Python integers; a score beyond 64 bits is defined as the end of their range, so such
scores tie.

Cases: null vectors, null or non-finite components and null ids take no part; vectors are compared with those of the
same length only; a query never meets rows with its own id; repeated rows are candidates each; a query id that
repeats uses its smallest vector; ties go to the smaller id; empty table - no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.llm.common import finite_vector
from gainclust.llm.tiles import Matrices, searched

BLOCK, SHARD, TILE, PART = 16_384, 65_536, 8192, 128
OUT = "query_id long, vec_id long, score long"
LOW, HIGH = -(2**63), 2**63 - 1


def _ints(m: np.ndarray, scale: int) -> np.ndarray:
    return np.floor(m * float(scale))


def products(q: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer inner products of whole-number float64 matrices, as int64."""
    top = (np.abs(q).max(initial=0.0)) * (np.abs(b).max(initial=0.0)) * max(q.shape[1], 1)
    if top < 2.0**53:
        return (q @ b.T).astype(np.int64)
    if top < 2.0**62:
        return q.astype(np.int64) @ b.astype(np.int64).T
    big = np.frompyfunc(int, 1, 1)
    return np.clip(big(q) @ big(b).T, LOW, HIGH).astype(np.int64)


def select(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k best by (score down, id up)."""
    if len(scores) > k:
        floor = np.partition(scores, len(scores) - k)[len(scores) - k]
        keep = np.flatnonzero(scores > floor)
        tied = np.flatnonzero(scores == floor)
        need = k - len(keep)
        if len(tied) > need:
            tied = tied[np.argpartition(ids[tied], need - 1)[:need]]
        keep = np.concatenate([keep, tied])
    else:
        keep = np.arange(len(scores))
    return keep[np.lexsort((ids[keep], ~scores[keep]))]


class Best:
    """The k best rows of each query so far."""

    def __init__(self, query_ids: np.ndarray, k: int):
        self.query_ids, self.k = query_ids, k
        self.found: list[tuple[np.ndarray, np.ndarray]] = [(np.empty(0, np.int64), np.empty(0, np.int64))] * len(query_ids)

    def add(self, rows: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        for j, i in enumerate(rows):
            s = scores[j]
            old_ids, old = self.found[i]
            # rows under the k-th score so far cannot enter
            near = np.flatnonzero(s >= old[-1]) if len(old) == self.k else np.arange(len(s))
            near = near[ids[near] != self.query_ids[i]]
            if len(near):
                all_ids, all_s = np.concatenate([old_ids, ids[near]]), np.concatenate([old, s[near]])
                best = select(all_ids, all_s, self.k)
                self.found[i] = all_ids[best], all_s[best]

    def batch(self) -> pa.RecordBatch:
        n = [len(x) for x, _ in self.found]
        cat = lambda j: np.concatenate([f[j] for f in self.found]) if self.found else np.empty(0, np.int64)
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(self.query_ids, n)), pa.array(cat(0)), pa.array(cat(1))], names=["query_id", "vec_id", "score"])


def top_by_query(parts: DataFrame, k: int, best_first: list, spread: int = 64) -> DataFrame:
    """Merge partial lists in two rounds: by (query, salt), then by query."""
    salted = parts.withColumn("salt", F.pmod(F.xxhash64("vec_id"), F.lit(spread)))
    first = Window.partitionBy("query_id", "salt").orderBy(*best_first)
    last = Window.partitionBy("query_id").orderBy(*best_first)
    near = salted.withColumn("rank", F.row_number().over(first)).where(F.col("rank") <= k)
    return near.withColumn("rank", F.row_number().over(last)).where(F.col("rank") <= k).drop("salt")


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vec_col: str = "embedding", block: int = BLOCK) -> DataFrame:
    """Rows (query_id, rank, vec_id, score) of each query's k best rows of vectors."""
    slim = lambda df: df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("vec")).where(F.col("id").isNotNull() & finite_vector(F.col("vec")))

    def search(query_ids: np.ndarray, by_length: Matrices, chunks: Iterator) -> Iterator[pa.RecordBatch]:
        wanted = [(rows, _ints(m, scale)) for rows, m in by_length]
        best = Best(query_ids, k)
        for own, matrices in chunks:
            for rows, m in matrices:
                for q_rows, q in wanted:
                    if q.shape[1] != m.shape[1]:
                        continue
                    for t in range(0, len(rows), TILE):
                        tile, tile_ids = _ints(m[t : t + TILE], scale), own[rows[t : t + TILE]]
                        for p in range(0, len(q_rows), PART):
                            best.add(q_rows[p : p + PART], tile_ids, products(q[p : p + PART], tile))
        yield best.batch()

    parts = searched(slim(vectors), slim(queries), search, OUT, block, SHARD)
    return top_by_query(parts, k, [F.desc("score"), F.asc("vec_id")]).select("query_id", "rank", "vec_id", "score")
