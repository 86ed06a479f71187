"""Contiguous shards of near equal bytes from global prefix sums of partition totals. DataFrame functions only.

Size of a row: UTF-8 bytes of the text (null: none) plus a fixed header. Rows are laid out in order of (checksum, size,
id), so equal texts lie together; rows equal in all three are interchangeable. Row with global byte offset ``o`` goes to
shard ``o * n div total``, so cuts lie at equal targets. A group of one checksum and size of at most WHOLE of a shard's
bytes goes where its first row goes and so stays whole; only larger groups are cut, as one may exceed a shard. Shards
differ by less than the largest row and twice WHOLE of a shard.

Cases: empty table - no rows; null id - kept, first among equal texts; empty or null text - header only; repeated rows -
each kept with a slot of its own; other columns are never read; fewer rows than shards - some shards stay empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.llm.common import shuffle_width, stored


WHOLE = 0.01


def shard_by_bytes(docs: DataFrame, n_shards: int = 24, id_col: str = "doc_id", text_col: str = "text", header: int = 8) -> DataFrame:
    """Rows (id, size, text_crc32, shard, slot); slot counts from 0 without gaps within each shard."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    slim = docs.select(F.col(id_col).alias("id"), (F.octet_length(text) + F.lit(header)).cast("long").alias("size"), F.crc32(F.encode(text, "utf-8")).cast("long").alias("text_crc32"))
    slim = stored(slim, "sizes")
    order = ["text_crc32", "size", "id"]
    # the partition number is written with the rows, so no later retry can see another layout
    placed = stored(slim.repartitionByRange(shuffle_width(spark), *order).withColumn("part", F.spark_partition_id()), "placed")

    # one row per partition, hence small whatever the input
    upto = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    totals = placed.groupBy("part").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n"))
    offsets = totals.select("part", F.coalesce(F.sum("b").over(upto), F.lit(0)).alias("b0"), F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("n0"))
    total = totals.agg(F.sum("b").alias("total"))
    offsets = stored(offsets.crossJoin(F.broadcast(total)), "offsets")

    inside = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    run = placed.join(F.broadcast(offsets), "part").select(
        "id", "size", "text_crc32",
        (F.col("b0") + F.sum("size").over(inside) - F.col("size")).alias("start"),
        (F.col("n0") + F.row_number().over(inside) - 1).alias("row"),
        "total",
    )
    run = stored(run, "offsets-of-rows")
    # groups of several rows that are small enough to stay whole; the rest go by their own offsets
    groups = run.groupBy("text_crc32", "size").agg(F.min("start").alias("first"), F.count(F.lit(1)).alias("rows"), F.first("total").alias("all"))
    groups = groups.where((F.col("rows") > 1) & (F.col("rows") * F.col("size") <= F.lit(WHOLE / n_shards) * F.col("all"))).select("text_crc32", "size", "first")
    run = run.join(groups, ["text_crc32", "size"], "left").withColumn("start", F.coalesce("first", "start"))
    run = run.withColumn("shard", F.least(F.lit(n_shards - 1).cast("long"), F.expr(f"start * {n_shards} div total")).cast("int"))
    run = stored(run.select("id", "size", "text_crc32", "shard", "row"), "sharded")
    first = run.groupBy("shard").agg(F.min("row").alias("row0"))  # n_shards rows at most
    return run.join(F.broadcast(first), "shard").select("id", "size", "text_crc32", "shard", (F.col("row") - F.col("row0")).alias("slot"))
