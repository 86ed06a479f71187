"""Vectors (id, vec) from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gainclust.functions.vectors import portable_hash, unit
from gainclust.sources.storage import load_table


def emb64(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")


def emb64_scaled(spark: SparkSession, d: str) -> DataFrame:
    return emb64(spark, d).withColumn("vec", F.transform("vec", lambda x: x.cast("double") * (1 + F.col("id") % 5)))


def line4(spark: SparkSession, d: str) -> DataFrame:
    t = load_table(spark, d, "lineitem")
    nth = F.row_number().over(Window.partitionBy("l_orderkey", "l_linenumber").orderBy("l_partkey", "l_suppkey", "l_extendedprice")) - 1
    vec = F.array(F.col("l_quantity"), F.col("l_extendedprice") / 1000, F.col("l_discount") * 100, F.col("l_tax") * 100)
    return t.select((F.col("l_orderkey") * 8 + F.col("l_linenumber") + (nth.cast("long") * F.lit(1 << 40))).alias("id"), vec.alias("vec"), "l_orderkey", "l_returnflag")


def part2(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.array(F.col("p_size").cast("double"), F.col("p_retailprice") / 100).alias("vec"), (F.col("p_size") % 8).alias("label"))


def acct1(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "supplier").select(F.col("s_suppkey").alias("id"), F.array(F.col("s_acctbal") / 1000).alias("vec"), (F.col("s_nationkey") % 3).alias("label"))


def user7(spark: SparkSession, d: str) -> DataFrame:
    kinds = ["click", "purchase", "error", "signup", "view"]
    counts = [F.sum(F.when(F.col("event_type") == x, 1.0).otherwise(0.0)).alias(x) for x in kinds]
    g = load_table(spark, d, "events").groupBy(F.col("user_id").alias("id")).agg(*counts, F.avg("value").alias("mean"), F.max("value").alias("top"))
    return g.select("id", F.array(*kinds, "mean", "top").alias("vec"))


def cust4(spark: SparkSession, d: str) -> DataFrame:
    p = F.col("o_totalprice")
    g = load_table(spark, d, "orders").groupBy(F.col("o_custkey").alias("id")).agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum(p).alias("s"), F.avg(p).alias("m"), F.max(p).alias("t"))
    return g.select("id", F.array("n", "s", "m", "t").alias("vec"))


def grown(df: DataFrame, times: int) -> DataFrame:
    """Each row `times` times, moved by a deterministic jitter below 1 %."""
    more = df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    jitter = 1 + (portable_hash(F.concat_ws("-", "id", "copy"), "grow") % 1000) / F.lit(100_000.0)
    return more.select((F.col("id") * times + F.col("copy")).alias("id"), F.transform("vec", lambda x: x.cast("double") * jitter).alias("vec"))


def terms(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, term): runs of letters, lower case, each time they occur."""
    return docs.select(F.col(id_col).alias("id"), F.explode(F.regexp_extract_all(F.lower(text_col), F.lit("\\p{L}+"), F.lit(0))).alias("term"))


def term_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, term, tf) of terms."""
    return terms(docs, id_col, text_col).groupBy("id", "term").agg(F.count(F.lit(1)).alias("tf"))


def idf(counts: DataFrame, n_docs: int) -> DataFrame:
    return counts.groupBy("term").agg(F.count(F.lit(1)).alias("df")).withColumn("idf", F.log(F.lit(float(n_docs)) / F.col("df")))


def without_tags(html: Column) -> Column:
    """Markup replaced by spaces; null stays null."""
    return F.regexp_replace(html, "<[^>]*>", " ")


def tfidf(docs: DataFrame, vocab: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Long form (id, slot, term, weight), unit length per document; documents without a known term have no row.

    Rows of one id (the turns of a conversation) make one document.
    """
    counts = term_counts(docs, id_col, text_col)
    top = idf(counts, docs.select(id_col).distinct().count()).orderBy(F.desc("df"), "term").limit(vocab)  # bounded by vocab
    top = top.withColumn("slot", F.row_number().over(Window.orderBy(F.desc("df"), "term")) - 1)
    known = terms(docs, id_col, text_col).join(F.broadcast(top), "term")  # the others are not sent
    raw = known.groupBy("id", "slot", "term", "idf").agg(F.count(F.lit(1)).alias("tf")).withColumn("w", F.col("tf") * F.col("idf"))
    norm = F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy("id").orderBy("slot").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    return raw.select("id", "slot", "term", F.when(norm > 0, F.col("w") / norm).otherwise(0.0).alias("weight"))


def doc_tfidf(docs: DataFrame, vocab: int = 512, **cols) -> DataFrame:
    """Dense (id, vec) of tfidf; every document has a row, all zero if it knows no term."""
    id_col = cols.get("id_col", "doc_id")
    entries = tfidf(docs, vocab, **cols).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("slot", "weight"))).alias("m"))
    slots = F.sequence(F.lit(0), F.lit(vocab - 1))
    return docs.select(F.col(id_col).alias("id")).join(entries, "id", "left").select("id", F.transform(slots, lambda j: F.coalesce(F.try_element_at("m", j), F.lit(0.0))).alias("vec"))


def doc_terms(docs: DataFrame, vocab: int = 512, **cols) -> DataFrame:
    """The same as (id, slots, weights) without the zeros."""
    id_col = cols.get("id_col", "doc_id")
    entries = tfidf(docs, vocab, **cols).groupBy("id").agg(F.array_sort(F.collect_list(F.struct("slot", "weight"))).alias("m"))
    found = docs.select(F.col(id_col).alias("id")).join(entries, "id", "left")
    return found.select("id", *(F.coalesce(f"m.{x}", F.array().cast(kind)).alias(y) for x, y, kind in (("slot", "slots", "array<int>"), ("weight", "weights", "array<double>"))))


def doc_hashed(docs: DataFrame, width: int = 256, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Dense hashed term counts, unit length: no vocabulary pass, any scale."""
    counts = term_counts(docs, id_col, text_col).withColumn("slot", (portable_hash(F.col("term"), "slot") % width).cast("int"))
    by = counts.groupBy("id", "slot").agg(F.sum("tf").alias("w")).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("slot", F.col("w").cast("double")))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda j: F.coalesce(F.try_element_at("m", j), F.lit(0.0)))
    return by.select("id", unit(dense).alias("vec"))
