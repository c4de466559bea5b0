"""Readers with fixed schemas, sinks, and a source that streams a table's files."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "conversations": "conv_id long, turn long, role string, text string",
    "pages": "page_id long, url string, html string",
}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; instants come as TIMESTAMP, whatever the file says, so that watermarks accept them."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    zoneless = [f.name for f in df.schema if f.dataType.simpleString() == "timestamp_ntz"]
    return df.withColumns({c: F.col(c).cast("timestamp") for c in zoneless}) if zoneless else df


def stream(spark: SparkSession, folder: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def read_text_formats(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """JSON lines or CSV with a stated schema; a malformed record is an error rather than a row of nulls."""
    reader = spark.read.schema(schema).option("mode", "FAILFAST")
    return reader.json(path) if kind == "json" else reader.option("header", True).csv(path)


def stored(df: DataFrame, label: str) -> DataFrame:
    """``df`` written to the folder of ``spark.checkpoint.dir`` and read again: computed once, safe from lost executors."""
    spark = df.sparkSession
    base = spark.conf.get("spark.checkpoint.dir", None) or f"file://{tempfile.gettempdir()}/steerselect-stored"
    path = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def save(df: DataFrame, path: str, by: list[str] | None = None, mode: str = "errorifexists") -> None:
    """Parquet, in one folder per value of ``by``: a selection by step, split or grade is then read alone."""
    writer = df.write.mode(mode)
    (writer.partitionBy(*by) if by else writer).parquet(path)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose joins on ``key`` need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
