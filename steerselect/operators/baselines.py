"""Selectors to compare with: hashing, loss, importance weights, classifiers, grades and pairwise ratings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.tokens import SLICE, as_lists, hash28, hashes, spaced, split_column, unit, words
from ..sources.tables import stored
from .corpus import global_rank

BUCKETS = 1000
#: Pairs of a task of a step of ``pairwise_fit``.
FIT_ROWS = 32_768


def hash_order(docs: DataFrame, seed: str, id_col: str = "doc_id") -> DataFrame:
    """``docs`` with a uniform ``score`` that the id fixes: uniform choice at any budget."""
    return docs.withColumn("score", unit(F.concat(F.lit(f"{seed}|"), F.col(id_col).cast("string"))))


def gram_buckets(df: DataFrame, id_col: str, text_col: str = "text", buckets: int = BUCKETS, bigrams: bool = True) -> DataFrame:
    """(id, b, n): hashed unigrams and bigrams of each text, counted."""
    w, n = F.col("w"), F.size("w")
    two = F.zip_with(F.slice(w, 1, F.greatest(n - 1, F.lit(0))), F.slice(w, 2, F.greatest(n - 1, F.lit(0))), lambda a, b: F.concat(a, F.lit(" "), b))
    grams = F.concat(w, two) if bigrams else w
    rows = df.select(id_col, words(text_col).alias("w")).select(id_col, F.explode(grams).alias("g"))
    return rows.groupBy(id_col, (hash28(F.col("g")) % buckets).alias("b")).agg(F.count(F.lit(1)).alias("n"))


def gram_lists(df: DataFrame, id_col: str, text_col: str = "text", buckets: int = BUCKETS) -> DataFrame:
    """(id, b, n): ``gram_buckets`` with one row for each text that has words, its buckets and counts as lists, by whole columns."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                ids, texts = batch.slice(at, SLICE).columns
                size, w = split_column(texts)
                row = np.repeat(np.arange(len(size)), size)
                first = np.flatnonzero(row[1:] == row[:-1])
                two = pc.binary_join_element_wise(w.take(pa.array(first)), w.take(pa.array(first + 1)), " ")
                cells = np.concatenate((row * buckets + hashes(w) % buckets, row[first] * buckets + hashes(two) % buckets))
                n = np.bincount(cells, minlength=len(size) * buckets)
                met = np.flatnonzero(n)
                each = np.bincount(met // buckets, minlength=len(size))
                yield pa.RecordBatch.from_arrays([ids, as_lists(pa.array((met % buckets).astype(np.int16)), each), as_lists(pa.array(n[met].astype(np.int32)), each)], names=[id_col, "b", "n"])

    return df.select(id_col, spaced(text_col).alias("_s")).mapInArrow(run, f"{id_col} long, b array<smallint>, n array<int>").filter(F.size("b") > 0)


def totals(lists: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """(b, n): partial sums of the buckets of lists, for ``log_ratio``."""

    def run(batches):
        n = np.zeros(buckets)
        for batch in batches:
            n += np.bincount(batch.column(0).flatten().to_numpy(), batch.column(1).flatten().to_numpy(), buckets)
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[at].astype(np.int64))], names=["b", "n"])

    return lists.select("b", "n").mapInArrow(run, "b long, n long")


def summed_lists(lists: DataFrame, weights: DataFrame, id_col: str = "doc_id", buckets: int = BUCKETS) -> DataFrame:
    """``summed`` for lists: (id, total, n)."""
    r = np.zeros(buckets)
    for row in weights.collect():  # a row for each bucket
        r[row["b"]] = row["r"]

    def run(batches):
        for batch in batches:
            ids, b, n = batch.columns
            row, k = np.repeat(np.arange(len(b)), pc.list_value_length(b).to_numpy()), n.flatten().to_numpy()
            out = [np.bincount(row, v, len(b)) for v in (r[b.flatten().to_numpy()] * k, k)]
            yield pa.RecordBatch.from_arrays([ids, pa.array(out[0]), pa.array(out[1].astype(np.int64))], names=[id_col, "total", "n"])

    return lists.select(id_col, "b", "n").mapInArrow(run, f"{id_col} long, total double, n long")


def classifier_lists(lists: DataFrame, positive: DataFrame, negative: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """``classifier`` for lists."""
    w = log_ratio(*(totals(lists.join(ids.select(id_col), id_col, "left_semi")) for ids in (positive, negative)))
    return summed_lists(lists, w, id_col).select(id_col, (1 / (1 + F.exp(-F.col("total") / F.col("n") * 10))).alias("p"))


def log_ratio(target: DataFrame, raw: DataFrame, buckets: int = BUCKETS, alpha: float = 1.0) -> DataFrame:
    """(b, r): the logarithm of smoothed bucket shares of two sets, for every bucket."""
    every = raw.sparkSession.range(buckets).withColumnRenamed("id", "b")
    for name, rows in (("t", target), ("s", raw)):
        every = every.join(F.broadcast(rows.groupBy("b").agg(F.sum("n").alias(name))), "b", "left")
    total = every.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("tt"), F.coalesce(F.sum("s"), F.lit(0)).alias("ss"))
    share = {c: F.log((F.coalesce(c, F.lit(0)) + alpha) / (F.col(c + c) + alpha * buckets)) for c in "ts"}
    return every.crossJoin(F.broadcast(total)).select("b", (share["t"] - share["s"]).alias("r"))


def summed(grams: DataFrame, weights: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, total, n): the weights of a text's grams, added up."""
    met = grams.join(F.broadcast(weights), "b")
    return met.groupBy(id_col).agg(F.sum(F.col("n") * F.col("r")).alias("total"), F.sum("n").alias("n"))


def classifier(grams: DataFrame, positive: DataFrame, negative: DataFrame, id_col: str = "doc_id", buckets: int = BUCKETS) -> DataFrame:
    """(id, p): a linear classifier over hashed grams by mean log-odds of two sets of ids."""
    w = log_ratio(grams.join(positive, id_col, "left_semi"), grams.join(negative, id_col, "left_semi"), buckets)
    return summed(grams, w, id_col).select(id_col, (1 / (1 + F.exp(-F.col("total") / F.col("n") * 10))).alias("p"))


def pairs_by_rank(labels: DataFrame, per_loser: int = 3, id_col: str = "doc_id") -> DataFrame:
    """(win_id, lose_id): every row of quality 0 with ``per_loser`` rows of quality 1, dealt by hash ranks: no all-pairs join."""
    order = F.md5(F.concat(F.lit("pair|"), F.col(id_col).cast("string")))
    wins, loses = (global_rank(labels.filter(F.col("quality") == q).select(id_col), order, id_col, "r").withColumn("r", F.col("r") - 1) for q in (1, 0))
    wins = wins.select(F.col("r").cast("long").alias("at"), F.col(id_col).alias("win_id"))
    loses = loses.crossJoin(F.broadcast(wins.agg(F.count(F.lit(1)).alias("size")))).filter("size > 0")
    want = loses.select(F.col(id_col).alias("lose_id"), "r", "size", F.explode(F.array(*map(F.lit, range(per_loser)))).alias("j"))
    return want.withColumn("at", ((F.col("r") * per_loser + F.col("j")) % F.col("size")).cast("long")).join(wins, "at").select("win_id", "lose_id")


def ridge(vecs: DataFrame, target: str, dim: int, ridge_: float = 1.0) -> np.ndarray:
    """Least-squares weights of ``dim`` features (and the intercept) from sums of outer products; only those reach the driver.  No rows give zeros."""
    x = F.concat(F.col("vec"), F.array(F.lit(1.0)))
    rows = vecs.select(x.alias("x"), F.col(target).cast("double").alias("y"))
    cells = rows.select("x", "y", F.posexplode("x").alias("i", "v"))
    sums = cells.groupBy("i").agg(F.sum(F.col("v") * F.col("y")).alias("b"), *(F.sum(F.col("v") * F.col("x")[j]).alias(f"a{j}") for j in range(dim + 1))).orderBy("i").collect()
    if not sums:
        return np.zeros(dim + 1)
    a = np.array([[r[f"a{j}"] for j in range(len(sums))] for r in sums])
    return np.linalg.solve(a + ridge_ * np.eye(len(a)), np.array([r["b"] for r in sums]))


def pairwise_fit(diffs: DataFrame, dim: int, steps: int = 200, rate: float = 1.0, decay: float = 1e-3) -> np.ndarray:
    """Bradley-Terry weights from rows (d) of feature differences of winners and losers, all of them; without rows, zeros.

    The differences are kept in blocks, on disk where memory is short; a step is one job that sums the gradients of the blocks, and only sums reach the driver.
    """

    def block(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.column(0).flatten().to_numpy().tobytes()], pa.binary())], names=["x"])

    rows = stored(diffs.select("d"), "differences")
    count = rows.count()
    blocks = rows.repartition(max(1, -(-count // FIT_ROWS))).mapInArrow(block, "x binary").rdd.map(lambda r: bytes(r[0])).persist(StorageLevel.MEMORY_AND_DISK)
    sc, w = diffs.sparkSession.sparkContext, np.zeros(dim)

    def slope(held):
        total = np.zeros(dim)
        for x in held:
            d = np.frombuffer(x).reshape(-1, dim)
            total += (1 / (1 + np.exp(d @ w))) @ d
        return [total]

    for _ in range(steps if count else 0):
        w = w + rate * (np.sum(sc.runJob(blocks, slope), 0) / count - decay * w)
    blocks.unpersist()
    return w
