"""Spark's own clusterers behind the interface of this engine, as an outside check."""

from __future__ import annotations

from pyspark.ml.clustering import BisectingKMeans, KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.operators.kway import ClusterResult


def mllib_kmeans(rows: DataFrame, k: int, bisecting: bool = False, max_iter: int = 20, seed: int = 42) -> ClusterResult:
    data = rows.select("id", array_to_vector(F.transform("vec", lambda x: x.cast("double"))).alias("features"))
    model = (BisectingKMeans if bisecting else KMeans)(k=k, maxIter=max_iter, seed=seed).fit(data)
    return ClusterResult(model.transform(data).select("id", F.col("prediction").alias("cluster")), k)
