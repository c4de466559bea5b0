"""A pair model over hashed tokens: losses, gradients and their products as joins with a small table.

The logit matrix is the logarithm of smoothed pair shares.  The gradient of a sequence's mean loss at (x, y) is
(n_x p(y|x) - n_xy) / pairs, an outer product of a one-hot input and an error for each position.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Sequences whose pairs are counted at once, a matrix of as many rows.
SLICE = 1000


def grid(df: DataFrame, vocabulary: int) -> DataFrame:
    """All (x, y) of the vocabulary: its size is a parameter, not data."""
    s = df.sparkSession.range(vocabulary * vocabulary)
    return s.select(F.floor(F.col("id") / vocabulary).cast("long").alias("x"), (F.col("id") % vocabulary).alias("y"))


def fit(pair_rows: DataFrame, vocabulary: int, alpha: float = 0.5) -> DataFrame:
    """(x, y, p, logp): smoothed shares of the next token, for every cell of the vocabulary."""
    return smoothed(pair_rows.groupBy("x", "y").agg(F.count(F.lit(1)).alias("n")), vocabulary, alpha)


def smoothed(counts: DataFrame, vocabulary: int, alpha: float = 0.5) -> DataFrame:
    """``fit`` from counts (x, y, n)."""
    rows = counts.groupBy("x").agg(F.sum("n").alias("nx"))
    cells = grid(counts, vocabulary).join(F.broadcast(counts), ["x", "y"], "left").join(F.broadcast(rows), "x", "left")
    p = (F.coalesce("n", F.lit(0)) + alpha) / (F.coalesce("nx", F.lit(0)) + alpha * vocabulary)
    return cells.select("x", "y", p.alias("p"), F.log(p).alias("logp"))


def pair_matrix(toks: pa.Array, vocabulary: int) -> tuple[np.ndarray, np.ndarray]:
    """(counts of adjacent pairs, a row for each sequence and a column for each pair; pairs of each sequence)."""
    size = pc.list_value_length(toks).to_numpy().astype(np.int64)
    x, row = toks.flatten().to_numpy().astype(np.int64), np.repeat(np.arange(len(size)), size)
    at = np.flatnonzero(row[1:] == row[:-1])
    cell = (row[at] * vocabulary + x[at]) * vocabulary + x[at + 1]
    return np.bincount(cell, minlength=len(size) * vocabulary**2).reshape(len(size), -1).astype(float), np.maximum(size - 1, 0)


def pair_counts(tokens: DataFrame, vocabulary: int) -> DataFrame:
    """(method, x, y, n) of rows (toks, methods): pairs counted for every method that holds a sequence, without a row for any pair."""

    def run(batches):
        total: dict = {}
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                toks, methods = batch.slice(at, SLICE).columns
                coded, size = methods.flatten().dictionary_encode(), pc.list_value_length(methods).to_numpy()
                held = np.zeros((len(coded.dictionary), len(size)))
                np.add.at(held, (coded.indices.to_numpy(), np.repeat(np.arange(len(size)), size)), 1.0)
                for m, n in zip(coded.dictionary.to_pylist(), held @ pair_matrix(toks, vocabulary)[0]):
                    total[m] = total.get(m, 0) + n
        for m, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([m] * len(at), pa.string()), pa.array(at // vocabulary), pa.array(at % vocabulary), pa.array(n[at].astype(np.int64))], names=["method", "x", "y", "n"])

    parts = tokens.filter(F.size("toks") > 1).select("toks", "methods").mapInArrow(run, "method string, x long, y long, n long")
    return parts.groupBy("method", "x", "y").agg(F.sum("n").alias("n"))


def losses(tokens: DataFrame, lms: DataFrame, vocabulary: int, id_col: str = "doc_id") -> DataFrame:
    """(id, method, n_pairs, nll) of rows (id, toks) under each of the models (method, x, y, logp), which are of the vocabulary's size."""
    table = lms.select("method", "x", "y", "logp").toPandas().pivot(index=["x", "y"], columns="method", values="logp").sort_index()
    names, logp = list(table.columns), table.to_numpy()

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                ids, toks = batch.slice(at, SLICE).columns
                counts, n = pair_matrix(toks, vocabulary)
                nll = -(counts @ logp) / n[:, None]
                for i, m in enumerate(names):
                    yield pa.RecordBatch.from_arrays([ids, pa.array([m] * len(n), pa.string()), pa.array(n), pa.array(nll[:, i])], names=[id_col, "method", "n_pairs", "nll"])

    return tokens.filter(F.size("toks") > 1).select(id_col, "toks").mapInArrow(run, f"{id_col} long, method string, n_pairs long, nll double")


def sequence_loss(pair_rows: DataFrame, lm: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, n_pairs, nll): mean negative log-likelihood; sequences without a pair have no row."""
    met = pair_rows.join(F.broadcast(lm), ["x", "y"])
    return met.groupBy(id_col).agg(F.count(F.lit(1)).alias("n_pairs"), (-F.avg("logp")).alias("nll"))


def gradient(pair_rows: DataFrame, lm: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, x, y, g): each sequence's gradient on the rows that it touches.  For tests and small vocabularies."""
    counts = pair_rows.groupBy(id_col, "x", "y").agg(F.count(F.lit(1)).alias("n"))
    rows = counts.groupBy(id_col, "x").agg(F.sum("n").alias("nx"))
    total = rows.groupBy(id_col).agg(F.sum("nx").alias("n_all"))
    dense = rows.join(F.broadcast(lm.select("x", "y", "p")), "x").join(total, id_col)
    return dense.join(counts, [id_col, "x", "y"], "left").select(id_col, "x", "y", ((F.col("nx") * F.col("p") - F.coalesce("n", F.lit(0))) / F.col("n_all")).alias("g"))


def mean_gradient(pair_rows: DataFrame, lm: DataFrame, by: list[str] | None = None, id_col: str = "doc_id") -> DataFrame:
    """(by..., x, y, g): the mean of sequences' gradients, without making any of them.

    Sequences weigh equally, so each pair weighs 1 / its sequence's pairs; the dense part needs only the row weights.
    """
    by = by or []
    weights = pair_rows.groupBy(*by, id_col).agg((1.0 / F.count(F.lit(1))).alias("w"))
    members = weights.groupBy(*by).agg(F.count(F.lit(1)).alias("members"))
    cells = pair_rows.join(weights, [*by, id_col]).groupBy(*by, "x", "y").agg(F.sum("w").alias("wxy"))
    rows = cells.groupBy(*by, "x").agg(F.sum("wxy").alias("wx"))
    dense = rows.join(F.broadcast(lm.select("x", "y", "p")), "x").join(cells, [*by, "x", "y"], "left")
    share = dense.join(members, by) if by else dense.crossJoin(members)
    return share.select(*by, "x", "y", ((F.col("wx") * F.col("p") - F.coalesce("wxy", F.lit(0.0))) / F.col("members")).alias("g"))


def direction_scores(pair_rows: DataFrame, lm: DataFrame, v: DataFrame, by: list[str] | None = None, id_col: str = "doc_id") -> DataFrame:
    """(by..., id, score): the product of each sequence's gradient with a direction (by..., x, y, v).

    It is the mean over the sequence's pairs of c(x) - v(x, y), c(x) the expected v of the row: one join with a small
    table and one average, no gradient and no sketch.
    """
    by = by or []
    expected = lm.select("x", "y", "p").join(v, ["x", "y"]).groupBy(*by, "x").agg(F.sum(F.col("p") * F.col("v")).alias("c"))
    keys = [*by, "x"]
    table = expected.join(v.select(*by, "x", "y", "v"), keys).select(*by, "x", "y", (F.col("c") - F.col("v")).alias("s"))
    met = pair_rows.join(F.broadcast(expected), keys, "left").join(F.broadcast(table.select(*by, "x", "y", "s")), [*by, "x", "y"], "left")
    return met.groupBy(*by, id_col).agg(F.avg(F.coalesce("s", "c", F.lit(0.0))).alias("score"))
