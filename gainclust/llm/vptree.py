"""Approximate nearest neighbours by cosine: a vantage-point tree per shard of rows, searched for blocks of queries.

Rows are scaled to unit length, where Euclidean distance orders like cosine and obeys the triangle inequality. A node
holds a vantage point and the median distance ``mu`` to the rest; the far side is skipped when the gap between the
query's distance and ``mu`` exceeds ``factor`` times the distance of the k-th best so far. factor 1 is the exact
search; smaller factors skip more. Reported scores are cosines of the original vectors in double precision.

Within a shard equal vectors are held once, with their k + 1 smallest ids (a query meets at most itself among them).
Where a point that was dropped is as near as the last one kept, up to rounding (parallel vectors, say), all points of
the shard at that distance or nearer are looked at, so that the score and then the smaller id decide.
Cases: null, zero, non-finite vectors and null ids take no part; only vectors of equal length meet; a query
never meets rows with its own id; a query id that repeats uses its smallest vector; ties go to the smaller id; empty
table - no rows; other columns are not read. Shards are bounded by ``shard_rows``; every row is indexed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import finite_vector
from gainclust.llm.tiles import Matrices, searched
from gainclust.llm.topk import top_by_query

BLOCK, SHARD_ROWS, LEAF = 16_384, 65_536, 128
OUT = "query_id long, vec_id long, score double"
#: Over double rounding: of distances, so that factor 1 stays exact, and of their squares, for ties.
SLACK, TIE = 1e-7, 1e-12


class Tree:
    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.points, self.leaf = points, leaf
        self.root = self._build(np.arange(len(points)))

    def _build(self, rows: np.ndarray):
        if len(rows) <= self.leaf:
            return rows
        # the vantage point is the row farthest from the group's first row: no random state
        first = self.points[rows[0]]
        vp = rows[int(np.argmax(((self.points[rows] - first) ** 2).sum(1)))]
        rest = rows[rows != vp]
        d = np.sqrt(((self.points[rest] - self.points[vp]) ** 2).sum(1))
        mu = float(np.median(d))
        inner = d <= mu
        if inner.all():
            inner = d < mu
            if not inner.any():
                return rows  # all at one distance: nothing to split by
        return vp, mu, self._build(rest[inner]), self._build(rest[~inner])

    def search(self, queries: np.ndarray, offer, radius, factor: float) -> None:
        """Calls offer(query rows, point rows, distances); radius(query rows) is the k-th distance so far."""

        def visit(node, qs: np.ndarray) -> None:
            if not len(qs) or (isinstance(node, np.ndarray) and not len(node)):
                return
            if isinstance(node, np.ndarray):
                gap = 2.0 - 2.0 * (queries[qs] @ self.points[node].T)
                offer(qs, node, np.sqrt(np.maximum(gap, 0.0)))
                return
            vp, mu, inner, outer = node
            d = np.sqrt(((queries[qs] - self.points[vp]) ** 2).sum(1))
            offer(qs, np.array([vp]), d[:, None])
            near_in = d <= mu
            visit(inner, qs[near_in])
            visit(outer, qs[~near_in])
            still = np.abs(d - mu) <= factor * radius(qs) + SLACK
            visit(outer, qs[near_in & still])
            visit(inner, qs[~near_in & still])

        visit(self.root, np.arange(len(queries)))


class Nearest:
    """k least distances per query among unique points, with slots for the query's own point."""

    def __init__(self, n: int, k: int):
        self.k = k + 1  # the query's own vector may be one of the points
        self.d = np.full((n, self.k), np.inf)
        self.p = np.full((n, self.k), -1, np.int64)
        self.dropped = np.full(n, np.inf)  # the nearest point not kept

    def offer(self, qs: np.ndarray, points: np.ndarray, d: np.ndarray) -> None:
        hit = (d < self.d[qs, -1][:, None]).any(1)
        self.dropped[qs[~hit]] = np.minimum(self.dropped[qs[~hit]], d[~hit].min(1))
        if not hit.any():
            return
        qs, d = qs[hit], d[hit]
        all_d = np.concatenate([self.d[qs], d], 1)
        all_p = np.concatenate([self.p[qs], np.broadcast_to(points, d.shape)], 1)
        order = np.argsort(all_d, 1, kind="stable")
        self.dropped[qs] = np.minimum(self.dropped[qs], np.take_along_axis(all_d, order[:, self.k : self.k + 1], 1)[:, 0])
        order = order[:, : self.k]
        self.d[qs], self.p[qs] = np.take_along_axis(all_d, order, 1), np.take_along_axis(all_p, order, 1)

    def radius(self, qs: np.ndarray) -> np.ndarray:
        return self.d[qs, -1]

    def tied(self) -> np.ndarray:
        """Queries that dropped a point as near as their last one."""
        return np.isfinite(self.dropped) & (self.dropped**2 <= self.d[:, -1] ** 2 + TIE)


def search_shard(ids: np.ndarray, m: np.ndarray, query_ids: np.ndarray, q: np.ndarray, k: int, factor: float, leaf: int = LEAF) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query row, id, cosine) of the nearest rows found in one shard."""
    order = np.argsort(ids, kind="stable")
    ids, m = ids[order], m[order]
    unique, inverse, count = np.unique(m, axis=0, return_inverse=True, return_counts=True)
    by_point = np.argsort(inverse.ravel(), kind="stable")  # ids stay in order within a point
    starts = np.concatenate([[0], np.cumsum(count)])
    norms = np.sqrt((unique**2).sum(1))
    q_norms = np.sqrt((q**2).sum(1))
    unit_q = q / q_norms[:, None]
    best = Nearest(len(q), k)
    unit_p = unique / norms[:, None]
    Tree(unit_p, leaf).search(unit_q, best.offer, best.radius, factor)
    tied = best.tied()
    out: list[tuple] = []
    for i in range(len(q)):
        points = best.p[i][best.p[i] >= 0]
        if not len(points):
            continue
        if tied[i]:
            points = np.flatnonzero(2.0 - 2.0 * (unit_p @ unit_q[i]) <= best.d[i, -1] ** 2 + 2 * TIE)
        cosine = (unique[points] * q[i]).sum(1) / (norms[points] * q_norms[i])
        few = np.argsort(-cosine, kind="stable")
        if tied[i]:
            # of equal scores the points of smallest ids go on
            few = np.lexsort((ids[by_point[starts[points]]], -cosine))[: k + 1]
        for p, c in zip(points[few], cosine[few]):
            own = ids[by_point[starts[p] : min(starts[p + 1], starts[p] + k + 1)]]
            own = own[own != query_ids[i]]
            out += [(i, int(v), float(c)) for v in own]
    if not out:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    a, b, c = zip(*out)
    return np.array(a), np.array(b, np.int64), np.array(c)


def ann(vectors: DataFrame, queries: DataFrame, k: int = 5, factor: float = 0.2, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, block: int = BLOCK) -> DataFrame:
    """Rows (query_id, rank, vec_id, score) of the k nearest rows found for each query."""
    v = F.col("vec")
    slim = lambda df: df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("vec")).where(F.col("id").isNotNull() & finite_vector(v) & F.exists(v, lambda x: x != 0))

    def search(query_ids: np.ndarray, by_length: Matrices, chunks: Iterator) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}

        def shard(d: int) -> Iterator[pa.RecordBatch]:
            own, m = np.concatenate([x for x, _ in held[d]]), np.concatenate([x for _, x in held[d]])
            held[d] = []
            for rows, q in by_length:
                if q.shape[1] == d:
                    at, found, score = search_shard(own, m, query_ids[rows], q, k, factor)
                    yield pa.RecordBatch.from_arrays([pa.array(query_ids[rows][at]), pa.array(found), pa.array(score)], names=["query_id", "vec_id", "score"])

        for own, matrices in chunks:
            for rows, m in matrices:
                d = m.shape[1]
                held.setdefault(d, []).append((own[rows], m))
                if sum(len(x) for x, _ in held[d]) >= shard_rows:
                    yield from shard(d)
        for d in held:
            if held[d]:
                yield from shard(d)
        yield pa.RecordBatch.from_arrays([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.float64())], names=["query_id", "vec_id", "score"])

    parts = searched(slim(vectors), slim(queries), search, OUT, block, shard_rows)
    return top_by_query(parts, k, [F.desc("score"), F.asc("vec_id")]).select("query_id", "rank", "vec_id", "score")
