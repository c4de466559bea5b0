"""Streams over the event files, each run to the end of what is there and returned as a table.

Results are written by ``foreachBatch`` to a folder by batch number: a batch that is repeated after a failure replaces
itself.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def scratch(spark: SparkSession, label: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or f"file://{tempfile.gettempdir()}/steerselect-streams"
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def events(spark: SparkSession, path: str, late: str = "40 days") -> DataFrame:
    """The event files as a stream with a watermark; the instants become TIMESTAMP, which watermarks need."""
    folder, _, name = path.rpartition("/")
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", name).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def finish(df: DataFrame, schema, label: str, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs a stream over all that is available now and returns what its batches wrote."""
    spark = df.sparkSession
    out, checkpoint = scratch(spark, label), scratch(spark, f"{label}-log")

    def write(batch: DataFrame, number: int) -> None:
        (each(batch) if each else batch).write.mode("overwrite").parquet(f"{out}/batch={number}")

    df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(write).start().awaitTermination()
    try:
        return spark.read.schema(schema).option("recursiveFileLookup", True).parquet(out)
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return spark.createDataFrame([], schema)


def daily_counts(spark: SparkSession, path: str) -> DataFrame:
    """Tumbling daily counts; in update mode a later batch may restate a window, and its last statement counts."""
    rows = events(spark, path).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    flat = rows.select(F.col("window.start").alias("start"), "event_type", "n")
    out = finish(flat, flat.schema, "daily", "update")
    return out.groupBy("start", "event_type").agg(F.max("n").alias("n"))


def deduplicated(spark: SparkSession, path: str) -> DataFrame:
    rows = events(spark, path).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")
    return finish(rows, rows.schema, "dedup")


def joined(spark: SparkSession, path: str, users: DataFrame) -> DataFrame:
    rows = events(spark, path).join(users, "user_id").select("event_id", "user_id", "event_type")
    return finish(rows, rows.schema, "joined")


def buffered(spark: SparkSession, path: str, size: int) -> DataFrame:
    """(key, step, slot, event_id): per event type, buffers of ``size`` events; a state keeps each key's count."""

    def form(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = state.get[0] if state.exists else 0
        for pdf in batches:
            at = n + pd.RangeIndex(len(pdf)).to_numpy()
            yield pd.DataFrame({"key": key[0], "step": at // size, "slot": at % size, "event_id": pdf["event_id"].to_numpy()})
            n += len(pdf)
        state.update((n,))

    schema = "key string, step long, slot long, event_id long"
    rows = events(spark, path).groupBy("event_type").applyInPandasWithState(form, schema, "n long", "append", GroupStateTimeout.NoTimeout)
    return finish(rows, schema, "buffers")
