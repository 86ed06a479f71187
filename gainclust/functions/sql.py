"""The vector arithmetic and the kernels for users of SQL: functions, an aggregate and table functions.

``register(spark)`` makes them known to a session. The scalar functions are SQL expressions, so they stay in the JVM.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

_VEC = "ARRAY<DOUBLE>"
_DOT = "aggregate(zip_with({}, {}, (x, y) -> x * y), 0D, (s, x) -> s + x)"
_GAIN = f"""CASE WHEN n_u <= 1 THEN CASE WHEN n_v = 0 THEN 0D ELSE ({_DOT.format('vec', 'd_v')} * 2 + {_DOT.format('vec', 'vec')} - {_DOT.format('d_v', 'd_v')} / n_v) / (n_v + 1) - {_DOT.format('vec', 'vec')} END
    ELSE CASE WHEN n_v = 0 THEN {_DOT.format('vec', 'vec')} ELSE (2 * {_DOT.format('vec', 'd_v')} + {_DOT.format('vec', 'vec')} - {_DOT.format('d_v', 'd_v')} / n_v) / (n_v + 1) END
        - (2 * {_DOT.format('vec', 'd_u')} - {_DOT.format('vec', 'vec')} - {_DOT.format('d_u', 'd_u')} / n_u) / (n_u - 1) END"""

SCALARS = {
    "vec_dot": (f"a {_VEC}, b {_VEC}", "DOUBLE", _DOT.format("a", "b")),
    "vec_norm2": (f"a {_VEC}", "DOUBLE", _DOT.format("a", "a")),
    "vec_l2sq": (f"a {_VEC}, b {_VEC}", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"),
    #: change of the score when a row leaves u (sum d_u, n_u rows, itself included) for v
    "move_gain": (f"vec {_VEC}, d_u {_VEC}, n_u BIGINT, d_v {_VEC}, n_v BIGINT", "DOUBLE", _GAIN),
}


def vec_sum(vectors: pd.Series) -> list:
    """Sum of the vectors of a group; null for no vector. A group meets in one task: for groups of a known size.

    The engine's own sums (state.cluster_state) combine before the shuffle instead.
    """
    some = [v for v in vectors if v is not None]
    return np.sum(np.stack(some), axis=0).tolist() if some else None


class ExplodeSubvectors:
    """(sub, vec) for each of m equal parts of a vector; none for a null vector."""

    def eval(self, vec: list, m: int) -> Iterator:
        if vec is None:
            return
        if len(vec) % m:
            raise ValueError(f"{len(vec)} components in {m} parts")
        width = len(vec) // m
        for i in range(m):
            yield i, [float(x) for x in vec[i * width : (i + 1) * width]]


class TopCandidates:
    """(place, cluster, dist2) of the k0 centroids nearest to a vector, ties to the lower cluster."""

    def eval(self, vec: list, centroids: list, k0: int) -> Iterator:
        if vec is None or not centroids:
            return
        gap = np.asarray(centroids, float) - np.asarray(vec, float)
        d2 = (gap * gap).sum(1)
        for place, c in enumerate(np.argsort(d2, kind="stable")[:k0]):
            yield place + 1, int(c), float(d2[c])


class GainCluster:
    """Clusters each partition of TABLE(...) PARTITION BY ... by itself: (id, cluster), the table having id and vec.

    A partition is one task's work, so one of more than ``kway.LOCAL_ROWS`` rows is refused.
    """

    def __init__(self):
        self.ids, self.rows, self.k = [], [], 1

    @staticmethod
    def analyze(table: AnalyzeArgument, k: AnalyzeArgument) -> AnalyzeResult:
        if not table.isTable or {"id", "vec"} - set(table.dataType.names):
            raise ValueError("gain_cluster takes a table with columns id and vec")
        return AnalyzeResult(StructType().add("id", LongType()).add("cluster", IntegerType()))

    def eval(self, row, k: int) -> None:
        from gainclust.operators.kway import LOCAL_ROWS

        if len(self.ids) >= LOCAL_ROWS:
            raise ValueError(f"over {LOCAL_ROWS} rows in a partition; use kway.gain_kway")
        self.ids.append(row["id"])
        self.rows.append(row["vec"])
        self.k = k

    def terminate(self) -> Iterator:
        from gainclust.operators import kernels

        if self.ids:
            order = np.argsort(self.ids, kind="stable")
            x = np.asarray(self.rows, float)[order]
            labels = kernels.gain_kway(x, min(self.k, len(x))).labels
            for i, c in zip(order, labels):
                yield self.ids[i], int(c)


def register(spark: SparkSession) -> None:
    for name, (args, kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udf.register("vec_sum", F.pandas_udf(vec_sum, ArrayType(DoubleType()), F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("explode_subvectors", F.udtf(ExplodeSubvectors, returnType="sub int, vec array<double>"))
    spark.udtf.register("top_candidates", F.udtf(TopCandidates, returnType="place int, cluster int, dist2 double"))
    spark.udtf.register("gain_cluster", F.udtf(GainCluster))
