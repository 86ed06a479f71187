"""Seeds by squared distance in a few rounds instead of one pass per seed, for hundreds of clusters and more."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.functions.vectors import portable_hash
from gainclust.operators import kernels
from gainclust.operators.state import MAX_STATE_BYTES
from gainclust.sources.storage import stored


def _matrix(column) -> np.ndarray:
    flat = np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64)
    return flat.reshape(len(column), -1)


def _closer(rows: DataFrame, new: np.ndarray, first: int) -> DataFrame:
    """Rows (id, vec, d2, near) after the candidates ``new``, numbered from ``first``, are added."""
    shared = rows.sparkSession.sparkContext.broadcast(new)  # checked by the caller

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        half = (c * c).sum(1)
        for b in batches:
            if not b.num_rows:
                continue
            x = _matrix(b.column(1))
            at = np.argmin(half - 2 * (x @ c.T), axis=1)
            d2 = ((x - c[at]) ** 2).sum(1)
            old, near = b.column(2).to_numpy(zero_copy_only=False), b.column(3).to_numpy(zero_copy_only=False)
            better = d2 < old
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.where(better, d2, old)), pa.array(np.where(better, at + first, near).astype(np.int32))], names=["id", "vec", "d2", "near"])

    return rows.mapInArrow(run, "id long, vec array<double>, d2 double, near int")


def seed_dsq_oversampled(rows: DataFrame, k: int, rounds: int = 5, factor: float = 2.0, seed: int = 42) -> np.ndarray:
    """k seed vectors of (id, vec). Each round draws every row on its own with probability factor * k * d2 / sum(d2),
    so about factor * k candidates join at once; the candidates, weighted by the rows nearest to them, are then
    reduced to k by weighted seeding on the driver, which holds about rounds * factor * k vectors.

    Fewer candidates than k (repeated rows): all of them are returned.
    """
    h = portable_hash(F.col("id"), f"seed{seed}")
    every = [np.array(rows.orderBy(h, "id").select("vec").first().vec, np.float64)[None, :]]
    held = rows.select("id", F.transform("vec", lambda x: x.cast("double")).alias("vec"), F.lit(float("inf")).alias("d2"), F.lit(0).alias("near"))
    held = stored(_closer(held, every[0], 0), "seeds")
    for r in range(rounds):
        cost = held.agg(F.sum("d2")).first()[0] or 0.0
        if cost <= 0:
            break
        u = portable_hash(F.col("id"), f"over{seed}-{r}") / F.lit(float(1 << 28))
        drawn = held.where(u * F.lit(cost) < F.lit(factor * k) * F.col("d2")).select("id", "vec")
        width = sum(map(len, every))
        limit = MAX_STATE_BYTES // (8 * every[0].shape[1]) - width
        got = drawn.orderBy("id").limit(limit + 1).collect()
        if len(got) > limit:
            raise ValueError(f"over {limit} candidates do not fit a broadcast; lower rounds or factor")
        if not got:
            continue
        new = np.array([x.vec for x in got], np.float64)
        held = stored(_closer(held, new, width), "seeds")
        every.append(new)
    pool = np.concatenate(every)
    weight = np.zeros(len(pool))
    for x in held.groupBy("near").agg(F.count(F.lit(1)).alias("n")).collect():  # one row per candidate
        weight[x.near] = x.n
    return weighted_seeds(pool, weight, k, np.random.default_rng(seed))


def weighted_seeds(x: np.ndarray, weight: np.ndarray, k: int, rng: np.random.Generator, epochs: int = 10) -> np.ndarray:
    """k of the weighted rows by squared distance, then a few weighted mean steps."""
    x, weight = x[weight > 0], weight[weight > 0]
    if len(x) <= k:
        return x
    rows = [int(rng.choice(len(x), p=weight / weight.sum()))]
    d2 = ((x - x[rows[0]]) ** 2).sum(1)
    while len(rows) < k and (d2 * weight).sum() > 0:
        p = d2 * weight
        rows.append(int(rng.choice(len(x), p=p / p.sum())))
        d2 = np.minimum(d2, ((x - x[rows[-1]]) ** 2).sum(1))
    c = x[rows]
    for _ in range(epochs):
        at = kernels.nearest(x, c)
        total = np.bincount(at, weight, len(c))
        s = np.zeros_like(c)
        np.add.at(s, at, x * weight[:, None])
        c = np.where(total[:, None] > 0, s / np.maximum(total, 1e-300)[:, None], c)
    return c
