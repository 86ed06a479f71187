"""Reading tables, cutting lineage through the shared folder, saving models."""

from __future__ import annotations

import json
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_rows(spark: SparkSession, path: str, form: str = "parquet", id_col: str = "id", vec_col: str = "vec", **options) -> DataFrame:
    """(id, vec) from Parquet, ORC, JSON, CSV or text files; in the last two the vector is written as [1.0, 2.0].

    A text line is an id, a tab and the vector. A vector that cannot be read is null, for validate() to judge.
    """
    if form in ("parquet", "orc"):
        raw = spark.read.format(form).options(**options).load(path)
    elif form == "json":
        raw = spark.read.schema(f"`{id_col}` long, `{vec_col}` array<double>").options(**options).json(path)
    elif form == "csv":
        raw = spark.read.options(**({"header": "true"} | options)).csv(path)
    elif form == "text":
        cut = F.split("value", "\t", 2)
        raw = spark.read.options(**options).text(path).select(F.try_element_at(cut, F.lit(1)).alias(id_col), F.try_element_at(cut, F.lit(2)).alias(vec_col))
    else:
        raise ValueError(f"unknown format {form!r}")
    vec = F.from_json(vec_col, "array<double>") if form in ("csv", "text") else F.col(vec_col)
    return raw.select(F.col(id_col).try_cast("long").alias("id"), F.transform(vec, lambda x: x.cast("double")).alias("vec"))


def write_bucketed(assignments: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by id, so that later joins on id need no shuffle."""
    assignments.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").format("parquet").saveAsTable(table)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; only a driver that is its own executor may go without a setting."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="gainclust-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """Written once, read back: iterations start from files, not from ever longer plans."""
    path = f"{shared_dir(df.sparkSession)}/gainclust/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stored_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables made by stored() that no later plan reads."""
    for df in tables:
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._stored_path)
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def save_model(path: str, tables: dict[str, DataFrame], params: dict) -> str:
    """A new version folder, then a pointer row that names it; readers never see half a model."""
    spark = next(iter(tables.values())).sparkSession
    version = uuid.uuid4().hex
    for name, df in tables.items():
        df.write.parquet(f"{path}/v-{version}/{name}")
    spark.createDataFrame([(version, json.dumps(params, sort_keys=True), list(tables))], "version string, params string, tables array<string>").coalesce(1).write.mode("overwrite").parquet(f"{path}/pointer")
    return version


def load_model(spark: SparkSession, path: str) -> tuple[dict[str, DataFrame], dict]:
    row = spark.read.parquet(f"{path}/pointer").first()
    return {t: spark.read.parquet(f"{path}/v-{row.version}/{t}") for t in row.tables}, json.loads(row.params)


def write_assignments(assignments: DataFrame, path: str) -> None:
    """Parquet by cluster, so that reading a cluster prunes the rest."""
    assignments.repartition("cluster").write.mode("overwrite").partitionBy("cluster").parquet(path)
