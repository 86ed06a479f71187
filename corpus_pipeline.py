"""Cleaning a corpus in five stages; each reads the documents that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainclust.llm import bpe, langid, mixing, near_text, suffix_dedup
from gainclust.llm.common import stored
from gainclust.llm.queries import vocabulary

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter and those whose entropy is over the calibrated bound."""
    model = langid.train(docs)
    out = langid.identify(docs, model, keep=[F.col(c).alias(f"in_{c}") for c in COLUMNS])
    return out.where("NOT rejected").select(*[F.col(f"in_{c}").alias(c) for c in COLUMNS])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group of texts linked by a similarity of 0.8 or more of their five-word shingles: that of
    least id (null last), of those the first.

    Rows are told apart by a stored key of their own, so null and repeated ids never merge rows.
    """
    rows = stored(docs.select(F.monotonically_increasing_id().alias("row"), *COLUMNS), "rows")
    groups = near_text.near_duplicates(rows, 5, 0.8, id_col="row").select(F.col("id").alias("row"), "component")
    first = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "row"))["row"]
    kept = groups.join(rows.select("row", "doc_id"), "row").groupBy("component").agg(first.alias("row")).select("row")
    return rows.join(kept, "row", "left_semi").select(*COLUMNS)


#: A passage is over 50 words; of natural words with their spaces 200 bytes hold fewer, so no such passage is shorter.
PASSAGE_BYTES, PASSAGE_WORDS = 200, 51


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts out the passages of over 50 words that occur more than once; a document with nothing left goes.

    Repeats are found as byte strings of PASSAGE_BYTES; what repeats without a gap goes if it holds PASSAGE_WORDS words.
    Null and empty texts go; repeated and null ids keep their rows; an empty table gives no rows.
    """
    keep = [F.col(c).alias(f"in_{c}") for c in ("lang", "source")]
    out = suffix_dedup.remove_repeats(docs, PASSAGE_BYTES, keep=keep, returns=("text",), min_words=PASSAGE_WORDS)
    return out.where("length(text) > 0").select(F.col("id").alias("doc_id"), "text", F.col("in_lang").alias("lang"), F.col("in_source").alias("source"), F.length("text").cast("long").alias("n_chars"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as the mix takes it."""
    out = mixing.mix(docs, keep=["text", "lang", "n_chars", "source"]).where("copies_taken > 0")
    return out.withColumn("nth", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies_taken")))).select(F.col("id").alias("doc_id"), "text", "lang", "source", "n_chars")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, with the digests of ids and of the decoded bytes."""
    return bpe.encode_decode(docs, *vocabulary(), returns=("n_tokens", "ids", "decoded_sha256"), cache_words=100_000).withColumnRenamed("id", "doc_id")


STAGES = [("language ID", language), ("SimHash near-dedup", near_duplicates), ("suffix-array dedup", repeats), ("mixing", mix), ("BPE encoding", encode)]

#: Language models, suffix sorting and BPE are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
