"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space that separates words, as a class body for regular expressions (fixed by the contracts).
WORD = "[^\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables, read by Spark only (any file system Spark knows)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; only where driver and executors are one process may a temporary one be set."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="gainclust-")
        spark.sparkContext.setCheckpointDir(found)
        found = spark.sparkContext.getCheckpointDir() or found
    return found.rstrip("/")


#: Once a table is written, nothing reads the shuffle files it came from.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage, survives lost executors and frees shuffle files."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/gainclust/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables made by stored() that no later plan reads."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df._stored_path)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def finite_vector(col: Column) -> Column:
    """True for a vector that is not null and holds only finite numbers."""
    ok = F.forall(col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return col.isNotNull() & F.coalesce(ok, F.lit(False))


def list_matrix(column) -> list[tuple]:
    """Rows of an Arrow list column without nulls as (row numbers, float64 matrix), one pair per length found."""
    import numpy as np

    column = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    offsets = np.asarray(column.offsets)
    flat = np.asarray(column.values.to_numpy(zero_copy_only=False), dtype=np.float64)
    lengths = np.diff(offsets)
    out = []
    for d in np.unique(lengths):
        rows = np.flatnonzero(lengths == d)
        take = offsets[:-1][rows][:, None] + np.arange(d)[None, :]
        out.append((rows, flat[take.astype(np.int64)]))
    return out


def trimmed(kernel: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """An Arrow kernel that gives freed memory back when its task ends: workers are reused and idle beside the JVM."""

    def run(batches: Iterator) -> Iterator:
        yield from kernel(batches)
        import pyarrow

        gc.collect()
        pyarrow.default_memory_pool().release_unused()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except (OSError, AttributeError):
            return  # not glibc: nothing to trim

    return run


_HELD: dict = {}


def held_in_worker(key, make: Callable):
    """An object that one worker process keeps from task to task; only the last one asked for is kept."""
    if key not in _HELD:
        _HELD.clear()
        gc.collect()
        _HELD[key] = make()
    return _HELD[key]
