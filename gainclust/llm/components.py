"""Connected components of links between long ids.

Up to ONE_TASK links (checked, some megabytes) are joined by union-find in one task; more by least-label hooking and
pointer jumping over the cluster. Both give every node the least id that it can reach.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import discard, stored

ONE_TASK = 1_000_000


def components(links: DataFrame) -> DataFrame:
    """From links (a, b): rows (node, root), root the least id reachable; stored."""
    edges = stored(links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
    few = edges.count() <= ONE_TASK
    out = stored(edges.repartition(1).mapInArrow(_forest, "node long, root long"), "labels") if few else _hooked(edges)
    discard(edges)
    return out


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    up: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while (above := up.setdefault(root, root)) != root:
            root = above
        while up[x] != root:
            up[x], x = root, up[x]
        return root

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            a, b = find(a), find(b)
            up[max(a, b)] = min(a, b)
    yield pa.RecordBatch.from_arrays([pa.array(list(up), pa.int64()), pa.array([find(x) for x in list(up)], pa.int64())], names=["node", "root"])


def _hooked(first: DataFrame) -> DataFrame:
    """Every round writes its labels. Links are carried over to the roots found and those within one root dropped, so
    the work shrinks; the loop ends when no link is left. Aggregates combine before the shuffle, so a node with many
    links is no hot key."""
    edges, labels = first, stored(first.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("root", F.col("node")), "labels")
    while not edges.isEmpty():
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("p"))
        # two jumps towards the least neighbour of the least neighbour
        for _ in range(2):
            up = least.select(F.col("a").alias("p"), F.col("p").alias("pp"))
            least = least.join(up, "p").select("a", F.col("pp").alias("p"))
        least = stored(least, "hooks")
        before = [labels, least, *([edges] if edges is not first else [])]
        labels = stored(labels.join(least.withColumnRenamed("a", "root"), "root", "left").select("node", F.coalesce("p", "root").alias("root")), "labels")
        ends = edges.join(least, "a").select(F.col("p").alias("pa"), "b").join(least.withColumnRenamed("a", "b"), "b").select("pa", F.col("p").alias("pb"))
        edges = stored(ends.where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), "links")
        discard(*before)
    if edges is not first:
        discard(edges)
    return labels
