"""A set of queries against all rows, in tiles of bounded size.

Queries that fit a broadcast (MAX_BYTES, checked) are sent to the rows, which stay where they are read. More queries
are dealt into tiles, rows into tiles of ``shard`` rows, and each pair of tiles meets in one task: a row is copied
once for every query tile, a query once for every row tile, and nothing is read twice or held on the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import list_matrix

MAX_BYTES = 64 << 20
Matrices = list[tuple[np.ndarray, np.ndarray]]  # (row numbers, matrix) for each vector length


def searched(rows: DataFrame, queries: DataFrame, search: Callable[[np.ndarray, Matrices, Iterator[tuple[np.ndarray, Matrices]]], Iterator[pa.RecordBatch]], schema: str, block: int, shard: int) -> DataFrame:
    """search(query ids, query matrices, row chunks) for every tile of rows (id, vec) and every tile of queries.

    Queries with equal ids count once, with the smallest vector.
    """
    spark = rows.sparkSession
    queries = queries.groupBy("id").agg(F.min("vec").alias("vec"))
    n, width = queries.agg(F.count(F.lit(1)), F.coalesce(F.max(F.size("vec")), F.lit(0))).first()
    if n <= block and n * width * 8 <= MAX_BYTES:
        got = queries.orderBy("id").toArrow()
        shared = spark.sparkContext.broadcast((np.asarray(got["id"].to_numpy(), np.int64), list_matrix(got["vec"]) if got.num_rows else []))

        def here(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield from search(*shared.value, ((b.column("id").to_numpy(zero_copy_only=False), list_matrix(b.column("vec"))) for b in batches if b.num_rows))

        return rows.mapInArrow(here, schema)

    tile = max(1, min(block, MAX_BYTES // (8 * max(width, 1))))
    q_tiles, r_tiles = -(-n // tile), -(-rows.count() // shard) or 1
    number = lambda tiles: F.pmod(F.xxhash64("id"), F.lit(tiles)).cast("int")
    every = lambda tiles: F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    left = queries.select("id", "vec", number(q_tiles).alias("q"), every(r_tiles).alias("r"))
    right = rows.select("id", "vec", number(r_tiles).alias("r"), every(q_tiles).alias("q"))

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64() if "double" in schema else pa.int64())})
        ids = [np.asarray(t["id"].to_numpy(), np.int64) for t in (a, b)]
        return pa.Table.from_batches(list(search(ids[0], list_matrix(a["vec"]), iter([(ids[1], list_matrix(b["vec"]))]))))

    return left.groupBy("q", "r").cogroup(right.groupBy("q", "r")).applyInArrow(meet, schema)
