"""Product quantization and nearest-neighbour search."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.functions.vectors import dot, norm2
from gainclust.operators import kernels
from gainclust.operators.kway import _matrix

#: Queries per broadcast block.
QUERY_BLOCK = 1024


def split_subvectors(rows: DataFrame, m: int, d: int) -> DataFrame:
    """(id, sub, vec) with m equal parts."""
    if d % m:
        raise ValueError(f"{m} does not divide {d}")
    w = d // m
    return rows.select("id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda j: F.struct(j.alias("sub"), F.slice("vec", j * w + 1, w).alias("vec")))).alias("p")).select("id", "p.sub", "p.vec")


def train_pq(rows: DataFrame, m: int, d: int, codewords: int = 256, method: str = "gain_random_label", seed: int = 42, sample_rows: int = 100_000) -> DataFrame:
    """(sub, code, vec): m codebooks, one task each, by any method. Trains on rows of least hash, sample_rows at most."""
    rows = rows.orderBy(F.xxhash64("id"), "id").limit(sample_rows)

    def train(pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf["vec"].to_numpy()).astype(np.float64)
        k = min(codewords, len(x))
        run = kernels.METHODS[method](x, k, seed)
        c = run.centroids(x)[np.bincount(run.labels, minlength=run.k) > 0]
        return pd.DataFrame({"sub": int(pdf["sub"].iloc[0]), "code": np.arange(len(c)), "vec": list(c)})

    return split_subvectors(rows, m, d).groupBy("sub").applyInPandas(train, "sub int, code int, vec array<double>")


def pq_encode(rows: DataFrame, codebooks: DataFrame, m: int, d: int) -> DataFrame:
    """(id, codes): nearest word of each part, ties to the lower code. Codebooks (m x words) are broadcast."""
    books = _books(codebooks, m)
    shared, w = rows.sparkSession.sparkContext.broadcast(books), d // m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = _matrix(b.column(1))
                codes = np.stack([kernels.nearest(x[:, j * w : (j + 1) * w], shared.value[j]) for j in range(m)], 1).astype(np.int16)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(codes), pa.list_(pa.int16()))], names=["id", "codes"])

    return rows.select("id", "vec").mapInArrow(run, "id long, codes array<smallint>")


def _books(codebooks: DataFrame, m: int) -> list[np.ndarray]:
    got = codebooks.orderBy("sub", "code").collect()  # m x 256 rows
    return [np.array([r.vec for r in got if r.sub == j], np.float64) for j in range(m)]


def encode_relational(rows: DataFrame, codebooks: DataFrame, m: int, d: int) -> DataFrame:
    """(id, sub, code, err2) by joins only."""
    parts = split_subvectors(rows, m, d)
    words = codebooks.select("sub", "code", F.col("vec").alias("word"))
    gap = F.aggregate(F.zip_with("vec", "word", lambda x, y: (x - y) * (x - y)), F.lit(0).cast("long"), lambda s, x: s + x)
    near = parts.join(F.broadcast(words), "sub").groupBy("id", "sub").agg(F.min(F.struct(gap.alias("e"), "code")).alias("m"))
    return near.select("id", "sub", F.col("m.code").alias("code"), F.col("m.e").alias("err2"))


def pq_decode(codes: DataFrame, codebooks: DataFrame, m: int) -> DataFrame:
    words = codebooks.groupBy("sub").agg(F.transform(F.array_sort(F.collect_list(F.struct("code", "vec"))), lambda p: p["vec"]).alias("words"))
    books = words.agg(F.transform(F.array_sort(F.collect_list(F.struct("sub", "words"))), lambda p: p["words"]).alias("books"))
    return codes.crossJoin(F.broadcast(books)).select("id", F.flatten(F.zip_with("books", "codes", lambda w, c: F.element_at(w, c.cast("int") + 1))).alias("vec"))


def pq_error(rows: DataFrame, decoded: DataFrame) -> DataFrame:
    gap = F.aggregate(F.zip_with(F.col("a.vec"), F.col("b.vec"), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    return rows.alias("a").join(decoded.alias("b"), "id").agg(F.avg(gap).alias("mean_error"))


def _search(queries: DataFrame, base: DataFrame, r: int, scorer) -> DataFrame:
    """Blocks of queries broadcast against rows where they lie; partition-wise best r, then best r overall."""
    spark, parts = base.sparkSession, None
    n = queries.count()
    for block in range(-(-n // QUERY_BLOCK) or 1):
        got = queries.where(F.pmod(F.xxhash64("id"), F.lit(max(-(-n // QUERY_BLOCK), 1))) == block).orderBy("id").toArrow()
        shared = spark.sparkContext.broadcast((got["id"].to_numpy(), _matrix(got["vec"].combine_chunks())))

        def run(batches, shared=shared):
            ids, q = shared.value
            best_d, best_i = np.full((len(q), r), np.inf), np.full((len(q), r), -1, np.int64)
            for b in batches:
                if b.num_rows and len(q):
                    dist = np.concatenate([best_d, scorer(q, b)], 1)
                    who = np.concatenate([best_i, np.broadcast_to(b.column(0).to_numpy(), (len(q), b.num_rows))], 1)
                    order = np.lexsort((who, dist), axis=1)[:, :r]
                    best_d, best_i = np.take_along_axis(dist, order, 1), np.take_along_axis(who, order, 1)
            ok = best_i.ravel() >= 0
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, r)[ok]), pa.array(best_i.ravel()[ok]), pa.array(best_d.ravel()[ok])], names=["query_id", "id", "dist2"])

        found = base.mapInArrow(run, "query_id long, id long, dist2 double")
        parts = found if parts is None else parts.unionByName(found)
    w = Window.partitionBy("query_id").orderBy("dist2", "id")
    return parts.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= r)


def exact_knn(queries: DataFrame, base: DataFrame, r: int = 100) -> DataFrame:
    def scorer(q, b):
        x = _matrix(b.column(1))
        return np.maximum((q * q).sum(1)[:, None] - 2 * q @ x.T + (x * x).sum(1), 0)

    return _search(queries.select("id", "vec"), base.select("id", "vec"), r, scorer)


def adc_search(queries: DataFrame, codes: DataFrame, codebooks: DataFrame, m: int, r: int = 100, symmetric: bool = False) -> DataFrame:
    """Distances from table look-ups: queries exact, base coded (asymmetric), or both coded (symmetric)."""
    books = _books(codebooks, m)

    def scorer(q, b):
        w, code, out = books[0].shape[1], _matrix(b.column(1)).astype(np.int64), 0.0
        for j in range(m):
            part = q[:, j * w : (j + 1) * w]
            if symmetric:
                part = books[j][kernels.nearest(part, books[j])]
            lut = ((part[:, None, :] - books[j][None]) ** 2).sum(2)
            out = out + lut[:, code[:, j]]
        return out

    return _search(queries.select("id", "vec"), codes.select("id", "codes"), r, scorer)


def recall_at(results: DataFrame, truth: DataFrame, ranks: list[int]) -> DataFrame:
    """Share of queries whose nearest neighbour is among the first R, for each R."""
    first = truth.where("rank = 1").select("query_id", F.col("id").alias("true_id"))
    hit = first.join(results, (first["query_id"] == results["query_id"]) & (first["true_id"] == results["id"]), "left").select(first["query_id"], "rank")
    r = results.sparkSession.createDataFrame([(x,) for x in ranks], "r int")
    return hit.crossJoin(F.broadcast(r)).groupBy("r").agg(F.avg(F.when(F.col("rank") <= F.col("r"), 1.0).otherwise(0.0)).alias("recall")).select(F.col("r").alias("rank"), "recall")


def exact_knn_relational(queries: DataFrame, base: DataFrame, r: int) -> DataFrame:
    """Fixed-point reference form: bounded queries broadcast, ranked by a window."""
    q = queries.select(F.col("id").alias("query_id"), F.col("vec").alias("q"))
    d2 = norm2(F.col("q"), "long") - 2 * dot(F.col("q"), F.col("vec"), "long") + norm2(F.col("vec"), "long")
    w = Window.partitionBy("query_id").orderBy("dist2", "id")
    return base.select("id", "vec").crossJoin(F.broadcast(q)).select("query_id", "id", d2.alias("dist2")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= r)
