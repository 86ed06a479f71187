"""Measures of accuracy and cost, and pooled vectors."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Components whose products fit the driver (512 MB).
MAX_PCA = 8192


def entropy(assignments: DataFrame, classes: DataFrame) -> DataFrame:
    """Per cluster (cluster, cnt, entropy in 0..1) against (id, cls); rows without a class are left out."""
    both = assignments.join(classes.where("cls IS NOT NULL"), "id")
    n_classes = classes.where("cls IS NOT NULL").agg(F.count_distinct("cls").alias("c"))
    per = both.groupBy("cluster", "cls").agg(F.count(F.lit(1)).alias("n"))
    p = F.col("n") / F.sum("n").over(Window.partitionBy("cluster"))
    per = per.withColumn("h", -p * F.log(p)).groupBy("cluster").agg(F.sum("n").alias("cnt"), F.sum("h").alias("h"))
    return per.crossJoin(F.broadcast(n_classes)).select("cluster", "cnt", F.when(F.col("c") > 1, F.abs(F.col("h")) / F.log("c")).otherwise(0.0).alias("entropy"))


def total_entropy(per_cluster: DataFrame) -> DataFrame:
    return per_cluster.agg((F.sum(F.col("cnt") * F.col("entropy")) / F.sum("cnt")).alias("entropy"))


def epochs_to(history: DataFrame, target: float) -> DataFrame:
    return history.where(F.col("distortion") <= target).groupBy("method").agg(F.min("epoch").alias("epochs"))


def run_summary(runs: DataFrame, value: str = "distortion") -> DataFrame:
    p = F.percentile(value, F.array(*[F.lit(x) for x in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    out = runs.groupBy("method").agg(p.alias("p"), F.count(F.lit(1)).alias("runs"))
    return out.select("method", "runs", *[F.element_at("p", i + 1).alias(c) for i, c in enumerate(("least", "q1", "median", "q3", "most"))])


def nominal_comparisons(n: int | Column, k: int, s: int) -> float | Column:
    """n (s - 1) log_s k, for even splits; n may be a column."""
    return n * (s - 1) * math.log(k) / math.log(s)


def visited(nodes: DataFrame) -> DataFrame:
    return nodes.where("NOT is_leaf").agg(F.sum("cnt").alias("visited"))


def growth(runs: DataFrame, x: str, y: str) -> DataFrame:
    """Slope of log y on log x per method."""
    return runs.groupBy("method").agg(F.regr_slope(F.log(F.col(y)), F.log(F.col(x))).alias("slope"))


def speedup(runs: DataFrame, baseline: str, value: str = "seconds") -> DataFrame:
    base = runs.where(F.col("method") == baseline).agg(F.avg(value).alias("b"))
    return runs.groupBy("method").agg(F.avg(value).alias("a")).crossJoin(F.broadcast(base)).select("method", (F.col("b") / F.col("a")).alias("ratio"))


def result_cube(runs: DataFrame, dims: list[str], value: str) -> DataFrame:
    """Mean, least and most of a measure for every combination of the dimensions and for all totals (null there)."""
    return runs.cube(*dims).agg(F.grouping_id().cast("int").alias("level"), F.avg(value).alias("mean"), F.min(value).alias("least"), F.max(value).alias("most"), F.count(F.lit(1)).alias("runs"))


def result_table(runs: DataFrame, row: str, column: str, value: str, columns: list) -> DataFrame:
    """Methods by parameter, as the tables of an experiment are printed."""
    return runs.groupBy(row).pivot(column, columns).agg(F.avg(value))


def best_so_far(history: DataFrame, value: str = "distortion") -> DataFrame:
    """Per epoch of a method: the gain over the epoch before, and the least value up to there."""
    w = Window.partitionBy("method").orderBy("epoch")
    return history.select("method", "epoch", value, (F.lag(value).over(w) - F.col(value)).alias("gained"), F.min(value).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("best"))


def pair_agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Adjusted Rand index of two clusterings from their contingency counts."""
    t = a.select("id", F.col("cluster").alias("a")).join(b.select("id", F.col("cluster").alias("b")), "id").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    two = lambda c: c * (c - 1) / F.lit(2.0)
    side = lambda c: t.groupBy(c).agg(F.sum("n").alias("n")).agg(F.sum(two(F.col("n"))).alias(f"s{c}"))
    whole = t.agg(F.sum(two(F.col("n"))).alias("s"), two(F.sum("n")).alias("all"))
    out = whole.crossJoin(side("a")).crossJoin(side("b")).withColumn("e", F.col("sa") * F.col("sb") / F.col("all"))
    return out.select(((F.col("s") - F.col("e")) / ((F.col("sa") + F.col("sb")) / 2 - F.col("e"))).alias("rand"))


def vlad_pool(descriptors: DataFrame, words: np.ndarray, by: str = "l_orderkey") -> DataFrame:
    """Sum of residuals to the nearest word, per entity, as (id, vec): words x d components, by joins and sums only."""
    spark = descriptors.sparkSession
    k, d = words.shape
    w = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(words)], "word int, c array<double>")  # a small vocabulary
    gap = F.aggregate(F.zip_with("vec", "c", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    near = descriptors.select("id", "vec", F.col(by).alias("entity")).crossJoin(F.broadcast(w))
    near = near.groupBy("id").agg(F.min(F.struct(gap.alias("e"), "word", "c", "vec", "entity")).alias("m"))
    res = near.select("m.entity", "m.word", F.posexplode(F.zip_with("m.vec", "m.c", lambda x, y: x - y)).alias("pos", "r"))
    slots = res.groupBy("entity", (F.col("word") * d + F.col("pos")).alias("slot")).agg(F.sum("r").alias("r"))
    m = slots.groupBy("entity").agg(F.map_from_entries(F.collect_list(F.struct("slot", "r"))).alias("m"))
    return m.select(F.col("entity").alias("id"), F.transform(F.sequence(F.lit(0), F.lit(k * d - 1)), lambda j: F.coalesce(F.try_element_at("m", j), F.lit(0.0))).alias("vec"))


def gram(rows: DataFrame) -> DataFrame:
    """(i, mean, g): the mean of component i and the mean products with all components. A partition gives its d sums of
    d products; these are added by i."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, m = 0, None, None
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column(0).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(b.num_rows, -1)
            n, s, m = n + len(x), x.sum(0) if s is None else s + x.sum(0), x.T @ x if m is None else m + x.T @ x
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(s), dtype=np.int32)), pa.array(np.full(len(s), n)), pa.array(s), pa.array(list(m), pa.list_(pa.float64()))], names=["i", "n", "s", "g"])

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            for i, n, s, g in zip(*(c.to_pylist() for c in b.columns[:3]), b.column(3)):
                g = g.values.to_numpy()
                held[i] = [held[i][0] + n, held[i][1] + s, held[i][2] + g] if i in held else [n, s, g]
        r = list(held.values())
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([x[1] / x[0] for x in r], pa.float64()), pa.array([x[2] / x[0] for x in r], pa.list_(pa.float64()))], names=["i", "mean", "g"])

    width = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = rows.select(F.transform("vec", lambda x: x.cast("double")).alias("vec")).mapInArrow(partial, "i int, n long, s double, g array<double>")
    return parts.repartition(width, "i").mapInArrow(total, "i int, mean double, g array<double>")


def pca_fit(rows: DataFrame, d: int, keep: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and leading axes from the mean products (d x d to the driver; d is refused above MAX_PCA)."""
    if d > MAX_PCA:
        raise ValueError(f"{d} components; {MAX_PCA} at most fit the driver")
    got = gram(rows).orderBy("i").toArrow()
    mean = got["mean"].to_numpy()
    products = np.array(got["g"].to_pylist())
    values, axes = np.linalg.eigh(products - np.outer(mean, mean))
    axes = axes[:, np.argsort(-values)[:keep]]
    return mean, axes * np.sign(axes[np.abs(axes).argmax(0), np.arange(keep)])


def pca_apply(rows: DataFrame, mean: np.ndarray, axes: np.ndarray) -> DataFrame:
    arr = lambda v: F.array(*[F.lit(float(x)) for x in v])
    centred = F.zip_with("vec", arr(mean), lambda x, y: x - y)
    one = lambda a: F.aggregate(F.zip_with("c", arr(a), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return rows.select("id", centred.alias("c")).select("id", F.array(*[one(axes[:, j]) for j in range(axes.shape[1])]).alias("vec"))
