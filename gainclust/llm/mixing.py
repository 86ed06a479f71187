"""Mixing sources to target weights by hash thresholds found from histograms, without sorting rows.

Each source gets a target by weight, at most ``cap`` times its own size; what a capped source cannot take is
shared again among the others by weight (water level). A source whose target is ``r`` whole copies and a rest
takes every row ``r`` times, and once more those rows whose hash lies under the source's threshold. The threshold is
refined level by level: a histogram of words by (source, next 12 hash bits) names the boundary bucket,
and only rows in that bucket are counted again. The last unit (rows of one hash) is taken if at least half of it fits.

Cases: null text - size 0, taken 0; null source - a source of its own, last in order; null id - hashed as the word
``null``; repeated rows - each counted, all taken or left alike; empty table - no rows; other columns are not read
by the plan; reruns agree, as nothing depends on the layout.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gainclust.llm.common import WORD, stored

LEVELS, BITS = 4, 12


def row_hash(id_col: Column, salt: int) -> Column:
    """48 bits of md5, the same in every SQL engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.coalesce(id_col.cast("string"), F.lit("null")), F.lit(str(salt))).cast("binary")), 1, LEVELS * BITS // 4), 16, 10).cast("long")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """From rows (skey, size): one row per source (skey, source_size, target, copies, budget)."""
    src = sizes.groupBy("skey").agg(F.sum("size").alias("source_size"))
    everything = Window.partitionBy()
    nth = F.row_number().over(Window.orderBy("skey"))  # one row per source
    src = src.withColumn("w", F.element_at(F.array(*[F.lit(x) for x in weights]), (F.pmod(nth - 1, F.lit(len(weights))) + 1).cast("int")))
    src = src.withColumn("limit", F.col("source_size") * cap).withColumn("ratio", F.col("limit").cast("double") / F.col("w"))
    before = Window.orderBy("ratio", "skey").rowsBetween(Window.unboundedPreceding, -1)
    src = src.withColumn("total", F.sum("source_size").over(everything)).withColumn("w_all", F.sum("w").over(everything))
    src = src.withColumn("c0", F.coalesce(F.sum("limit").over(before), F.lit(0))).withColumn("w0", F.coalesce(F.sum("w").over(before), F.lit(0)))
    capped = (F.col("total") - F.col("c0")).cast("double") / (F.col("w_all") - F.col("w0")) >= F.col("ratio")
    src = src.withColumn("capped", capped)
    src = src.withColumn("cc", F.coalesce(F.sum(F.when(F.col("capped"), F.col("limit"))).over(everything), F.lit(0)))
    src = src.withColumn("cw", F.coalesce(F.sum(F.when(F.col("capped"), F.col("w"))).over(everything), F.lit(0)))
    level = (F.col("total") - F.col("cc")).cast("double") / F.nullif(F.col("w_all") - F.col("cw"), F.lit(0))
    src = src.withColumn("target", F.when(F.col("capped"), F.col("limit").cast("double")).otherwise(level * F.col("w")))
    copies = F.when(F.col("source_size") == 0, 0).otherwise(F.floor(F.col("target") / F.nullif(F.col("source_size"), F.lit(0)).cast("double"))).cast("long")
    src = src.withColumn("copies", copies)
    return src.select("skey", "source_size", "target", "copies", (F.col("target") - F.col("copies") * F.col("source_size")).alias("budget"))


def _boundary(rows: DataFrame, targets: DataFrame) -> DataFrame:
    """Per source the hash of the unit at the boundary, and whether that unit is taken."""
    state = targets.select("skey", "budget", F.lit(0).cast("long").alias("prefix"))
    slim = rows.select("skey", "size", "h").where("size > 0")
    for level in range(LEVELS):
        shift = BITS * (LEVELS - 1 - level)
        mine = slim.join(state, "skey")
        if level:
            mine = mine.where(F.shiftright("h", shift + BITS) == F.col("prefix"))
        hist = mine.groupBy("skey", "budget", F.shiftright("h", shift).alias("prefix")).agg(F.sum("size").alias("g"))
        upto = Window.partitionBy("skey").orderBy("prefix").rowsBetween(Window.unboundedPreceding, -1)
        hist = hist.withColumn("before", F.coalesce(F.sum("g").over(upto), F.lit(0)))
        # the one bucket in which the running sum passes the budget; none if everything fits
        hist = hist.where((F.col("before") <= F.col("budget")) & (F.col("before") + F.col("g") > F.col("budget")))
        if level == LEVELS - 1:
            return hist.select("skey", F.col("prefix").alias("cut"), (F.col("before") + F.col("g") / F.lit(2.0) <= F.col("budget")).alias("cut_taken"))
        state = hist.select("skey", (F.col("budget") - F.col("before")).alias("budget"), "prefix")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = (1, 2, 3), cap: int = 3, salt: int = 42, keep: list[str] | None = None) -> DataFrame:
    """Rows (id, size, source_size, target, taken, copies_taken) and the columns in keep, one per input row."""
    skey = F.when(F.col(source_col).isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col(source_col)))
    kept = keep or []
    base = docs.select(F.col(id_col).alias("id"), word_count(F.col(text_col)).alias("size"), skey.alias("skey"), row_hash(F.col(id_col), salt).alias("h"), *[F.col(c).alias(f"kept_{c}") for c in kept])
    slim = stored(base.select("id", "size", "skey", "h"), "mix-sizes")
    targets = stored(source_targets(slim, weights, cap), "mix-targets")
    cuts = stored(targets.join(_boundary(slim, targets), "skey", "left"), "mix-cuts")  # one row per source
    once = F.when(F.col("budget") <= 0, False).when(F.col("cut").isNull(), True).when(F.col("h") == F.col("cut"), F.col("cut_taken")).otherwise(F.col("h") < F.col("cut"))
    out = (base if kept else slim).join(cuts, "skey")
    times = F.when(F.col("size") > 0, F.col("copies") + F.when(once, 1).otherwise(0)).otherwise(F.lit(0)).cast("long")
    out = out.withColumn("copies_taken", times)
    return out.select("id", "size", "source_size", "target", (F.col("size") * F.col("copies_taken")).alias("taken"), "copies_taken", *[F.col(f"kept_{c}").alias(c) for c in kept])
