"""Exact deduplication with a heavy-hitter split, in DataFrame operations only.

Texts are equal when they agree after their blanks are deleted.  A frequent-items sketch (of the Misra-Gries
family) names every digest that can hold more than one in ``heavy_share`` rows; an exact, map-side combined count
verifies those few and finds each one's winner.  The winners are broadcast, so that rows of frequent digests are
settled where they are read; only the other rows are shuffled by digest.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh, text_or_empty, written

#: At most so many digests are tracked, verified and broadcast (64 bytes each).
TRACKED = 4096
HEAVY_SHARE = 1000


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n, digest, row): code points of the text, SHA-256 of the text without blanks, and a number per row."""
    text = text_or_empty(text_col)
    return docs.select(
        F.col(id_col).alias("id"),
        F.length(text).alias("n"),
        F.sha2(F.translate(text, " \t\n\x0b\x0c\r", ""), 256).alias("digest"),
        F.monotonically_increasing_id().alias("row"),
    )


def heavy_digests(table: DataFrame, share: int = HEAVY_SHARE, tracked: int = TRACKED) -> list[str]:
    """Digests that may hold more than one row in ``share``; never more than ``share`` of them."""
    total = table.count()
    if not total:
        return []
    top = table.agg(F.expr(f"approx_top_k(digest, {share}, {tracked})").alias("top")).first()["top"]
    return [x["item"] for x in top if x["count"] > max(1, total // share)]


def settle(table: DataFrame, share: int = HEAVY_SHARE) -> DataFrame:
    """(id, keep_id, group_size, kept, digest, row) for every row of a ``digests`` table.

    The row with the most code points stays; among those the smallest id (null last), then the first row.
    """
    heavy = heavy_digests(table, share)
    order = F.struct((-F.col("n")).alias("a"), F.col("id").isNull().alias("b"), F.col("id").alias("id"), F.col("row").alias("row"))
    out = ("id", "keep_id", "group_size", "kept", "digest", "row")
    rest = table
    settled = None
    if heavy:
        is_heavy = F.col("digest").isin(heavy)
        winners = (
            table.filter(is_heavy)
            .groupBy("digest")
            .agg(F.min(order).alias("best"), F.count(F.lit(1)).alias("group_size"))
            .select("digest", F.col("best.id").alias("keep_id"), F.col("best.row").alias("keep_row"), "group_size")
        )
        settled = table.filter(is_heavy).join(F.broadcast(winners), "digest").withColumn("kept", F.col("row") == F.col("keep_row")).select(*out)
        rest = table.filter(~is_heavy)
    same = Window.partitionBy("digest")
    first = same.orderBy(F.col("n").desc(), F.col("id").asc_nulls_last(), "row")
    light = (
        rest.withColumn("rank", F.row_number().over(first))
        .withColumn("keep_id", F.first("id").over(first))
        .withColumn("group_size", F.count(F.lit(1)).over(same))
        .withColumn("kept", F.col("rank") == 1)
        .select(*out)
    )
    return light if settled is None else light.unionByName(settled)


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", share: int = HEAVY_SHARE) -> DataFrame:
    """One row per row of ``docs``: ``id_col``, keep_id, group_size, kept, text_sha256.

    A null text is empty; null ids are ordinary ids that sort last; repeated rows form one group of which one row
    is kept; an empty table gives an empty result; other columns are ignored, whatever their names.
    """
    table = written(digests(docs, id_col, text_col), "digests")
    return settle(table, share).select(F.col("id").alias(id_col), "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", share: int = HEAVY_SHARE) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns.

    Rows are matched by id and digest; where one id repeats a text, its repetitions are ranked and one stays.
    """
    table = written(digests(docs, id_col, text_col), "digests")
    a, b, c, r = fresh(docs, "keep_key", "keep_digest", "times", "nth")
    gone = written(settle(table, share).groupBy(F.col("id").alias(a), F.col("digest").alias(b)).agg(F.count(F.lit(1)).alias(c), F.max("kept").alias("_k")), "settled")
    text = text_or_empty(text_col)
    keyed = docs.withColumn(b, F.sha2(F.translate(text, " \t\n\x0b\x0c\r", ""), 256))
    dropped = gone.filter(~F.col("_k")).select(a, F.col(b).alias("_d"))
    left = keyed.join(dropped, keyed[id_col].eqNullSafe(dropped[a]) & (keyed[b] == dropped["_d"]), "left_anti")
    if gone.filter(F.col("_k") & (F.col(c) > 1)).limit(1).count():
        one = Window.partitionBy(id_col, b).orderBy(F.length(text).desc(), text)
        left = left.withColumn(r, F.row_number().over(one)).filter(F.col(r) == 1)
    return left.select(*docs.columns)
