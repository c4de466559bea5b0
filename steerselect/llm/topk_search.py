"""Exact top-k inner products over norm-sorted vectors with partial sums and Cauchy-Schwarz bounds.

Integer vectors are rotated by singular vectors so that the first coordinates hold most of every inner product.  A task
takes its vectors by descending length, chunk by chunk.  Once length times query length falls below a query's k-th score, the rest of the chunk is
done; before that, the sum over the first coordinates plus the product of the residual lengths bounds a score, and only
vectors whose bound reaches the k-th score get their exact integer product.

Queries come in blocks of a bounded size, each against all vectors.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

#: Vectors that the rotation and the first thresholds are fitted on: the longest and a hash sample, so many each.
FIT = 2048
QUERY_BLOCK = 8192
CHUNK = 32768
STEP = 512
HEAD = 16


def usable(vector: str) -> Column:
    v = F.col(vector)
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return v.isNotNull() & ~bad


def scaled(table: DataFrame, id_col: str, vector: str, scale: int) -> DataFrame:
    """(id, v): floor(scale * x) of every component, of the rows that take part."""
    floor = F.transform(F.col(vector), lambda x: F.floor(x.cast("double") * scale).cast("long"))
    return table.filter(F.col(id_col).isNotNull() & usable(vector)).select(F.col(id_col).cast("long").alias("id"), floor.alias("v"))


def matrix(column: pa.ListArray, dims: int) -> np.ndarray:
    """Rows of equal length; a shorter vector ends in zeros."""
    sizes = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if (sizes == dims).all():
        return flat.reshape(-1, dims)
    out = np.zeros((len(sizes), dims))
    out[np.repeat(np.arange(len(sizes)), sizes), np.concatenate([np.arange(n) for n in sizes]).astype(int)] = flat
    return out


class Block:
    """A block of queries and what each has found so far."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, rotation: np.ndarray, k: int) -> None:
        self.ids, self.q, self.k = ids, q, k
        self.rotated = q @ rotation
        self.length = np.linalg.norm(q, axis=1)
        self.rest = np.linalg.norm(self.rotated[:, HEAD:], axis=1)
        self.floor = np.full(len(ids), -np.inf)

    def search(self, ids: np.ndarray, x: np.ndarray, rotation: np.ndarray, best: list[tuple[np.ndarray, np.ndarray]] | None) -> list[tuple[np.ndarray, np.ndarray]]:
        """The k best (scores, ids) per query among these vectors and ``best``; floors rise on the way."""
        length = np.linalg.norm(x, axis=1)
        order = np.argsort(-length, kind="stable")
        ids, x, length = ids[order], x[order], length[order]
        turned = x @ rotation
        rest = np.linalg.norm(turned[:, HEAD:], axis=1)
        best = best or [(np.zeros(0), np.zeros(0, np.int64))] * len(self.ids)
        for i in range(0, len(x), STEP):
            part = slice(i, i + STEP)
            slack = 1e-9 * self.length * length[i] + 1e-6
            alive = np.flatnonzero(self.length * length[i] + slack >= self.floor)
            if not len(alive):
                break
            bound = self.rotated[alive, :HEAD] @ turned[part, :HEAD].T + np.outer(self.rest[alive], rest[part]) + slack[alive, None]
            may = bound >= self.floor[alive, None]
            for row in np.flatnonzero(may.any(1)):
                n, at = alive[row], np.flatnonzero(may[row]) + i
                score = x[at] @ self.q[n]  # integers below 2**53: exact
                on = score >= self.floor[n]
                if not on.any():
                    continue
                s, v = np.concatenate((best[n][0], score[on])), np.concatenate((best[n][1], ids[at[on]]))
                top = np.lexsort((v, -s))[: self.k]
                best[n] = s[top], v[top]
                if len(top) == self.k:
                    self.floor[n] = max(self.floor[n], s[top[-1]])
        return best


def exact_top_k(table: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vector: str = "embedding", scale: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k highest integer inner products, ties to the smaller id.

    Every query row asks, and its candidates are all rows but itself, others of its id included; repeated query rows give
    repeated results.  Rows with a null id, or whose vector is null or holds a null or non-finite component, take no part;
    shorter vectors end in zeros; fewer than k candidates give fewer rows; other columns are ignored.  Scores are exact
    below 2**53.  No queries: an empty result.
    """
    spark = table.sparkSession
    vectors = scaled(table, id_col, vector, scale)
    # equal rows ask once; their numbers are written, so every reader sees the same ones
    asked = scaled(table.filter(is_query), id_col, vector, scale).groupBy("id", "v").agg(F.count(F.lit(1)).alias("times"))
    own = F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x * x)
    queries = written(asked.select(F.monotonically_increasing_id().alias("q"), "id", "v", "times", own.alias("own")), "queries")
    dims = vectors.agg(F.max(F.size("v"))).first()[0] or 0
    total = queries.count()
    schema = "q long, vec_id long, score long"
    parts: list[DataFrame] = []
    if total and dims:
        square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
        longest = vectors.orderBy(square.desc(), "id").limit(FIT)
        sample = vectors.orderBy(F.xxhash64("id"), "id").limit(FIT)
        fit = longest.union(sample).distinct().toArrow().combine_chunks()
        fit_ids, fit_x = fit.column("id").to_numpy(), matrix(fit.column("v").combine_chunks(), dims)
        rotation = np.linalg.svd(fit_x, full_matrices=True)[2].T if len(fit_x) <= dims else np.linalg.eigh(fit_x.T @ fit_x)[1][:, ::-1]
        blocks = -(-total // QUERY_BLOCK)
        for n in range(blocks):
            held = queries.filter(F.pmod(F.xxhash64("q"), F.lit(blocks)) == n).toArrow().combine_chunks()  # about QUERY_BLOCK rows
            if not held.num_rows:
                continue
            block = Block(held.column("q").to_numpy(), matrix(held.column("v").combine_chunks(), dims), rotation, k + 1)
            block.search(fit_ids, fit_x, rotation, None)  # first floors
            parts.append(vectors.mapInArrow(_searcher(spark.sparkContext.broadcast((block, rotation)), dims), schema))
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    found = parts[0]
    for p in parts[1:]:
        found = found.union(p)
    # one more than k are found, the query's own row among them if it is that near; one entry like it goes
    order = Window.partitionBy("q").orderBy(F.col("score").desc(), "vec_id")
    first = found.withColumn("nth", F.row_number().over(order)).filter(F.col("nth") <= k + 1).join(queries.select("q", "id", "times", "own"), "q")
    mine = ((F.col("vec_id") == F.col("id")) & (F.col("score") == F.col("own"))).cast("int")
    so_far = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = first.withColumn("mine", mine).withColumn("seen", F.sum("mine").over(so_far)).filter("not (mine = 1 and seen = 1)")
    ranked = seen.withColumn("rank", F.col("nth") - F.least(F.col("seen"), F.lit(1)).cast("int")).filter(F.col("rank") <= k)
    again = F.explode(F.sequence(F.lit(1).cast("long"), F.col("times"))).alias("again")
    return ranked.select(F.col("id").alias("query_id"), "rank", "vec_id", "score", again).drop("again")


def _searcher(shared, dims: int):
    def run(batches):
        import copy

        block, rotation = shared.value
        block = copy.copy(block)
        block.floor = block.floor.copy()
        best, ids, xs = None, [], []
        for b in batches:
            ids.append(b.column("id").to_numpy())
            xs.append(matrix(b.column("v"), dims))
            if sum(map(len, ids)) >= CHUNK:
                best = block.search(np.concatenate(ids), np.concatenate(xs), rotation, best)
                ids, xs = [], []
        if ids:
            best = block.search(np.concatenate(ids), np.concatenate(xs), rotation, best)
        if best:
            n = [len(s) for s, _ in best]
            score, vec = np.concatenate([s for s, _ in best]), np.concatenate([v for _, v in best])
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(block.ids, n)), pa.array(vec.astype(np.int64)), pa.array(score.astype(np.int64))], names=["q", "vec_id", "score"])

    return run
