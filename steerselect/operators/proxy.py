"""Encoding, relevance to a benchmark, and the proxy pool."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.tokens import hash28, words
from ..sources.tables import stored

DIM = 32
#: Passages of a benchmark that travel at once.
BLOCK = 16_384


def positive(norm: str) -> Column:
    """A divisor, null where it is zero: a later filter on the quotient may be evaluated before the one that drops such rows."""
    return F.when(F.col(norm) > 0, F.col(norm))


def encode(df: DataFrame, id_col: str, text_col: str = "text", dim: int = DIM) -> DataFrame:
    """(id, vec): a frozen encoder: signed hashed word counts of unit length.  Texts without words, or whose words cancel out, have no row."""
    rows = df.select(id_col, F.explode(words(text_col)).alias("w")).select(id_col, hash28(F.col("w")).alias("h"))
    sign = 1 - 2 * (F.floor(F.col("h") / dim) % 2)
    parts = rows.groupBy(id_col, (F.col("h") % dim).alias("d")).agg(F.sum(sign).cast("double").alias("v"))
    held = parts.groupBy(id_col).agg(F.map_from_entries(F.collect_list(F.struct("d", "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    vec = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(dim - 1).cast("long")), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0)) / positive("norm"))
    return held.filter("norm > 0").select(id_col, vec.alias("vec"))


def scaled(sums: DataFrame, id_col: str) -> DataFrame:
    """(id, vec) of ``encode`` from signed sums (id, enc)."""
    norm = F.sqrt(F.aggregate("enc", F.lit(0.0), lambda s, v: s + v.cast("double") * v.cast("double")))
    return sums.select(id_col, "enc", norm.alias("norm")).filter("norm > 0").select(id_col, F.transform("enc", lambda v: v / positive("norm")).alias("vec"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def relevance(docs: DataFrame, bench: DataFrame, id_col: str, item_col: str, digits: int = 6) -> DataFrame:
    """(id, relevance, best_item) from (id, vec) and (item, vec): the greatest product, ties to the smaller item.

    Items come in blocks of at most about ``BLOCK``; each block is broadcast as a matrix and meets the documents in
    matrix products, so no pair becomes a row.  Vectors that are null, hold a null or have another length take no part.
    """
    spark = docs.sparkSession
    usable = lambda df, key: df.select(F.col(key).cast("long").alias("k"), F.col("vec").cast("array<double>").alias("vec")).filter(F.col("vec").isNotNull() & ~F.exists("vec", F.isnull))
    items, rows = usable(bench, item_col), usable(docs, id_col)
    blocks = -(-items.count() // BLOCK)
    if blocks > 1:
        items, rows = stored(items, "items"), stored(rows, "vectors")
    schema = "k long, s double, item long"

    def meeting(shared):
        def run(batches):
            ids, x = shared.value
            for b in batches:
                vec = b.column("vec")
                on = pc.equal(pc.list_value_length(vec), x.shape[1])
                keys, vec = b.column("k").filter(on), vec.filter(on)
                for i in range(0, len(keys), 1024):
                    part = vec.slice(i, 1024)
                    s = np.round(part.flatten().to_numpy().reshape(-1, x.shape[1]) @ x.T, digits)
                    at = s.argmax(1)
                    yield pa.RecordBatch.from_arrays([keys.slice(i, 1024), pa.array(s[np.arange(len(at)), at]), pa.array(ids[at])], names=["k", "s", "item"])

        return run

    parts = []
    for n in range(blocks):
        held = items.filter(F.pmod(F.xxhash64("k"), F.lit(blocks)) == n).orderBy("k").toPandas()  # about BLOCK rows
        if len(held):
            matrix = spark.sparkContext.broadcast((held["k"].to_numpy(np.int64), np.stack(held["vec"].to_numpy()).astype(float)))
            parts.append(rows.mapInArrow(meeting(matrix), schema))
    if not parts:
        return rows.limit(0).select(F.col("k").alias(id_col), F.lit(0.0).alias("relevance"), F.lit(0).cast("long").alias("best_item"))
    found = reduce(DataFrame.union, parts)
    if len(parts) > 1:
        found = found.groupBy("k").agg(F.max(F.struct("s", (-F.col("item")).alias("i"))).alias("best")).select("k", "best.s", (-F.col("best.i")).alias("item"))
    return found.select(F.col("k").alias(id_col), (F.col("s") + F.lit(0.0)).alias("relevance"), F.col("item").alias("best_item"))
