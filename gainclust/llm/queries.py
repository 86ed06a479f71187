"""The registered queries of this subpackage and, where SQL can express them, their DuckDB equivalents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainclust.llm import bpe, html_text, langid, licenses, mixing, sharding, simhash, suffix_dedup, topk, vptree
from gainclust.llm.common import table

VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def vocabulary(name: str = VOCABULARY) -> tuple[str, str]:
    """Path of an installed public vocabulary and its pre-token pattern."""
    import public_tokenizers

    return str(public_tokenizers.path(name)), public_tokenizers.PATTERN


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(table(spark, sf_dir, "documents"), *vocabulary(), returns=("n_tokens", "ids_sha256", "decoded_sha256")).withColumnRenamed("id", "doc_id")


def op2_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op3_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return topk.exact_top_k(rows, rows.where("vec_id % 100 = 0"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's columns, then the shared passages of over 50 words, which may be shorter than its 400 bytes."""
    return suffix_dedup.remove_repeats_and_passages(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op5_vptree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return vptree.ann(rows, rows.where("vec_id % 50 = 0"))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 4 == 2
    model = langid.train(docs.where(~held))
    out = langid.identify(docs, model, keep=[held.alias("held_out")])
    return out.select(F.col("id").alias("doc_id"), "held_out", "lang_pred", "score")


def op8_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages")).withColumnRenamed("id", "page_id")


def op9_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")


def op10_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.shard_by_bytes(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_bpe, op2_licenses, op3_exact_top_k, op4_suffix_dedup, op5_vptree, op6_simhash, op7_language, op8_html, op9_mix, op10_shards, pipeline)}

_MIX = r"""WITH d AS (SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS skey,
    ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':42'), 1, 12))::BIGINT AS h FROM documents),
s0 AS (SELECT skey, sum(size)::BIGINT AS source_size, (row_number() OVER (ORDER BY skey) - 1) % 3 + 1 AS w FROM d GROUP BY skey),
s1 AS (SELECT *, source_size * 3 AS cap, (source_size * 3)::DOUBLE / w AS ratio FROM s0),
s2 AS (SELECT *, sum(source_size) OVER ()::BIGINT AS total, sum(w) OVER ()::BIGINT AS w_all,
    coalesce(sum(cap) OVER b, 0)::BIGINT AS c0, coalesce(sum(w) OVER b, 0)::BIGINT AS w0 FROM s1 WINDOW b AS (ORDER BY ratio, skey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
s3 AS (SELECT *, (total - c0)::DOUBLE / (w_all - w0) >= ratio AS capped FROM s2),
s4 AS (SELECT *, coalesce(sum(CASE WHEN capped THEN cap END) OVER (), 0)::BIGINT AS cc, coalesce(sum(CASE WHEN capped THEN w END) OVER (), 0)::BIGINT AS cw FROM s3),
s5 AS (SELECT skey, source_size, CASE WHEN capped THEN cap::DOUBLE ELSE (total - cc)::DOUBLE / nullif(w_all - cw, 0) * w END AS target FROM s4),
s AS (SELECT *, CASE WHEN source_size = 0 THEN 0 ELSE floor(target / source_size::DOUBLE)::BIGINT END AS copies FROM s5),
u AS (SELECT skey, h, sum(size)::BIGINT AS g FROM d WHERE size > 0 GROUP BY skey, h),
v AS (SELECT skey, h, g, sum(g) OVER (PARTITION BY skey ORDER BY h)::BIGINT - g AS before FROM u)
SELECT d.doc_id, d.size, s.source_size, s.target,
    (d.size * (s.copies + CASE WHEN d.size > 0 AND s.target - s.copies * s.source_size > 0 AND v.before + v.g / 2.0::DOUBLE <= s.target - s.copies * s.source_size THEN 1 ELSE 0 END))::BIGINT AS taken
FROM d JOIN s USING (skey) LEFT JOIN v ON v.skey = d.skey AND v.h = d.h"""

_TOP = """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(x::DOUBLE * 1024)::BIGINT) AS e FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND coalesce(list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x))), true)),
p AS (SELECT q.vec_id AS query_id, b.vec_id AS vec_id, list_sum(list_transform(list_zip(q.e, b.e), lambda z: z[1] * z[2]))::BIGINT AS score
    FROM v q JOIN v b ON q.vec_id <> b.vec_id AND len(q.e) = len(b.e) WHERE q.vec_id % 100 = 0),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10"""

ORACLE_SQL = {"op2_licenses": licenses.oracle(), "op3_exact_top_k": _TOP, "op9_mix": _MIX}
