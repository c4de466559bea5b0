"""Scores of every step's candidates in one grouped pass, without gradients, sketches of candidates or growing broadcasts.

A step's group holds its candidates, its proxy documents and, on one row, the pair model's counts, whose size is the
vocabulary's.  The product of a candidate's gradient with any direction v is the mean over its pairs of c(x) - v(x, y),
c(x) the expected v of the row; so every score is one direction per step: the proxy's gradient as the geometry shapes it,
the same seen through a sketch, or the gradients of a history.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .precond import muon_factor
from .sketch import tables

SCORES = ("plain", "shaped", "muon", "sketched", "plain_sketched", "redundancy")


def counted(tokens: DataFrame) -> DataFrame:
    """One row: cells (x, y, n, w) of all adjacent pairs, w weighing sequences equally; as many as the vocabulary has pairs."""

    def run(batches):
        n = w = np.zeros((0, 0))
        for batch in batches:
            toks = batch.column(0)
            x, size = toks.flatten().to_numpy().astype(np.int64), pc.list_value_length(toks).to_numpy()
            v = max(len(n), int(x.max(initial=-1)) + 1)
            n, w = (np.pad(c, (0, v - len(c))) for c in (n, w))
            inside = np.ones(len(x), bool)
            inside[np.cumsum(size) - 1] = False  # a sequence's last token begins no pair
            at = np.flatnonzero(inside)
            code, share = x[at] * v + x[at + 1], np.repeat(1.0 / (size - 1), size - 1)
            n, w = n + np.bincount(code, minlength=v * v).reshape(v, v), w + np.bincount(code, share, v * v).reshape(v, v)
        i, j = np.nonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(n[i, j].astype(np.int64)), pa.array(w[i, j])], names=["x", "y", "n", "w"])

    parts = tokens.filter(F.size("toks") > 1).select("toks").mapInArrow(run, "x int, y int, n long, w double")
    cells = parts.groupBy("x", "y").agg(F.sum("n").alias("n"), F.sum("w").alias("w"))
    return cells.agg(F.collect_list(F.struct("x", "y", "n", "w")).alias("cells"))


def model_of(cells, vocabulary: int, alpha: float) -> tuple[np.ndarray, np.ndarray]:
    """(shares of the next token, mean gradient over the counted sequences)."""
    n, w = np.zeros((2, vocabulary, vocabulary))
    for c in cells:
        n[c["x"], c["y"]], w[c["x"], c["y"]] = c["n"], c["w"]
    p = (n + alpha) / (n.sum(1, keepdims=True) + alpha * vocabulary)
    members = w.sum()
    return p, (w.sum(1, keepdims=True) * p - w) / members if members else w


def gradient(p: np.ndarray, toks: np.ndarray) -> np.ndarray:
    """The gradient of a sequence's mean loss."""
    n = np.bincount(toks[:-1] * len(p) + toks[1:], minlength=p.size).reshape(p.shape)
    return (n.sum(1, keepdims=True) * p - n) / (len(toks) - 1)


def packed(toks, vocabulary: int):
    """Tokens on their way to a step's group: a byte each where the vocabulary allows it."""
    return toks.cast("array<tinyint>" if vocabulary <= 128 else "array<int>")


def by_step(candidates: DataFrame, proxy: DataFrame, model: DataFrame, vocabulary: int):
    """The rows of each step's group; the model's one row rides on the step's first candidate."""

    def role(rows: DataFrame, name: str, cells) -> DataFrame:
        return rows.select("step", F.lit(name).alias("role"), F.col("slot").cast("long").alias("slot"), "doc_id", packed(F.col("toks"), vocabulary).alias("toks"), cells.alias("cells"))

    first = F.when(F.col("slot") == 0, F.col("cells"))
    rows = role(candidates.crossJoin(F.broadcast(model)), "candidate", first).union(role(proxy.withColumn("slot", F.lit(-1)), "proxy", F.lit(None).cast(model.schema["cells"].dataType)))
    return rows.groupBy("step")


def members(pdf: pd.DataFrame) -> list[tuple]:
    """(role, slot, doc_id, tokens) of a group's sequences that have a pair; a null text has none."""
    return [(r, s, d, np.asarray(x, np.int64)) for r, s, d, x in zip(pdf["role"], pdf["slot"], pdf["doc_id"], pdf["toks"]) if x is not None and len(x) > 1]


def naive_pass(candidates: DataFrame, proxy: DataFrame, model: DataFrame, vocabulary: int, alpha: float = 0.5) -> DataFrame:
    """(step, doc_id, score): each candidate's whole gradient is made and multiplied with the proxy's, one after another in its step's group.

    No gradient leaves the worker that makes it; only tokens travel.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        p, _ = model_of(next((c for c in pdf["cells"] if c is not None), ()), vocabulary, alpha)
        rows = members(pdf)
        beside = [gradient(p, x) for r, _, _, x in rows if r == "proxy"]
        g = np.mean(beside, 0) if beside else np.zeros_like(p)
        own = [(d, float((gradient(p, x) * g).sum())) for r, _, d, x in rows if r == "candidate"]
        return pd.DataFrame({"step": [int(pdf["step"].iloc[0])] * len(own), "doc_id": [d for d, _ in own], "score": [s for _, s in own]})

    return by_step(candidates, proxy, model, vocabulary).applyInPandas(run, "step long, doc_id long, score double")


def step_pass(candidates: DataFrame, proxy: DataFrame, model: DataFrame, vocabulary: int, buckets: int, alpha: float = 0.5, scale: float = 1.0, eps: float = 1e-4, seed: int = 42, history: int = 4, phi: str | tuple[str, ...] | None = None) -> DataFrame:
    """(step, doc_id, one column for each of SCORES, phi) for rows (step, slot, doc_id, toks) of at least two tokens.

    Slots count from 0 within a step.

    ``shaped`` freezes AdamW's factor and ``muon`` the iteration's factor after one past step on the mean training
    gradient; ``redundancy`` is the product with the summed gradients of the first ``history`` slots; ``phi``, on
    request, the sketch of the gradient in the geometry named; of several, columns ``phi_`` and the name.  A step without proxy pairs scores zero.
    """

    phis = {f"phi_{k}": k for k in phi} if isinstance(phi, tuple) else {"phi": phi} if phi else {}

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        p, past = model_of(next((c for c in pdf["cells"] if c is not None), ()), vocabulary, alpha)
        shape = scale / (np.abs(past) + eps)
        bucket, sign = tables((vocabulary, vocabulary), buckets, seed)
        rows = members(pdf)
        beside = [gradient(p, x) for r, _, _, x in rows if r == "proxy"]
        g = np.mean(beside, 0) if beside else np.zeros_like(p)
        first = sum((gradient(p, x) for r, s, _, x in rows if r == "candidate" and s < history), np.zeros_like(p))
        seen = np.bincount(bucket.ravel(), (sign * g).ravel(), buckets)[bucket] * sign
        factor, left = muon_factor(past)
        directions = {"plain": g, "shaped": g * shape, "muon": factor.T @ g if left else g @ factor.T, "sketched": seen * shape, "plain_sketched": seen, "redundancy": first}
        v = np.stack([directions[k] for k in SCORES])
        gain = (p * v).sum(2, keepdims=True) - v
        own = [(d, x) for r, _, d, x in rows if r == "candidate"]
        out = {"step": [int(pdf["step"].iloc[0])] * len(own), "doc_id": [d for d, _ in own]}
        got = np.array([gain[:, x[:-1], x[1:]].mean(1) for _, x in own]).reshape(-1, len(SCORES))
        out |= {k: got[:, i] for i, k in enumerate(SCORES)}
        for column, name in phis.items():
            apply = {"plain": lambda x: x, "shaped": lambda x: shape * x, "muon": lambda x: factor @ x if left else x @ factor}[name]
            out[column] = [np.bincount(bucket.ravel(), (sign * apply(gradient(p, x))).ravel(), buckets) for _, x in own]
        return pd.DataFrame(out)

    schema = "step long, doc_id long, " + ", ".join(f"{k} double" for k in SCORES) + "".join(f", {c} array<double>" for c in phis)
    return by_step(candidates, proxy, model, vocabulary).applyInPandas(run, schema)
