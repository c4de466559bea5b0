"""Choosing K of a buffer's N candidates."""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tokens import gumbel


def quota(n: int, ratio: float) -> int:
    return int(np.floor(ratio * n + 1e-9))


def noise(seed: int, step: int, draw: int, doc) -> float:
    """Gumbel noise that the ids fix: the same on every retry and partitioning."""
    h = int(hashlib.md5(f"draw|{seed}|{step}|{draw}|{doc}".encode()).hexdigest()[:7], 16)
    return float(-np.log(-np.log((h + 0.5) / (1 << 28))))


def noises(seed: int, step: int, draw: int, docs) -> np.ndarray:
    """``noise`` of many ids at once."""
    start, got = hashlib.md5(f"draw|{seed}|{step}|{draw}|".encode()), []
    for doc in docs:
        h = start.copy()
        h.update(b"%d" % doc)
        got.append(h.digest()[:4])
    h = np.frombuffer(b"".join(got), ">u4") >> 4
    return -np.log(-np.log((h + 0.5) / (1 << 28)))


def pick_from_gram(align: np.ndarray, gram: np.ndarray, k: int, lr: float = 1.0, tau: float = 0.9, policy: str = "soft", penalty: bool = True, noise_of: Callable[[int, int], float] | None = None, ids=None, self_term: bool = False, normalise: str = "raw", noises_of: Callable[[int, np.ndarray], np.ndarray] | None = None) -> list[tuple[int, float, float]]:
    """(index, utility, probability) per draw.  The history enters as columns of the Gram matrix, so the state is N numbers.

    Ties go to the smaller id.  A temperature of 0 is the greedy policy.  ``noises_of`` gives the noise of a draw for
    many indices at once, of those that are left alone.
    """
    n = len(align)
    u = lr * np.asarray(align, float)
    if self_term:
        u = u - 0.5 * lr * lr * np.diag(gram)
    ids = np.arange(n) if ids is None else np.asarray(ids)
    left, out = np.ones(n, bool), []
    for draw in range(min(k, n)):
        v = u.copy()
        if normalise == "zscore":
            v = (v - v[left].mean()) / (v[left].std() or 1.0)
        elif normalise == "minmax":
            v = (v - v[left].min()) / (np.ptp(v[left]) or 1.0)
        if policy == "greedy" or tau <= 0:
            key, p = v, np.full(n, np.nan)
        else:
            e = np.where(left, np.exp((v - v[left].max()) / tau), 0)
            p = e / e.sum()
            key = v / tau + np.array([noise_of(draw, i) for i in range(n)]) if noise_of else v / tau
            if noises_of:
                at = np.flatnonzero(left)
                key[at] += noises_of(draw, at)
        at = np.flatnonzero(left)
        at = at[key[at] == key[at].max()]
        z = int(at[ids[at].argmin()])
        out.append((z, float(u[z]), float(p[z])))
        left[z] = False
        if penalty:
            u = u - lr * lr * gram[:, z]
    return out


def pick_steps(features: DataFrame, ratio: float = 0.5, lr: float = 1.0, tau: float = 0.9, policy: str = "soft", penalty: bool = True, seed: int = 42, local: bool = False, normalise: str = "raw") -> DataFrame:
    """(step, draw, doc_id, utility, prob) from rows (step, doc_id, align, phi), phi the candidate's sketch.

    A step's candidates from all workers meet in one group of the buffer's size; ``local`` keeps a ``worker`` column's
    candidates apart instead.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("doc_id")
        phi = np.stack(pdf["phi"].to_numpy()) if len(pdf) else np.zeros((0, 1))
        ids, step = pdf["doc_id"].to_numpy(), int(pdf["step"].iloc[0])
        got = pick_from_gram(pdf["align"].to_numpy(), phi @ phi.T, quota(len(pdf), ratio), lr, tau, policy, penalty, lambda d, i: noise(seed, step, d, ids[i]), ids, normalise=normalise)
        return pd.DataFrame({"step": [step] * len(got), "draw": range(len(got)), "doc_id": [ids[z] for z, _, _ in got], "utility": [u for _, u, _ in got], "prob": [p for _, _, p in got]})

    keys = ["step", "worker"] if local else ["step"]
    return features.groupBy(*keys).applyInPandas(run, "step long, draw int, doc_id long, utility double, prob double")


def softmax(scores: DataFrame, utility: str = "utility", tau: float = 0.9, by: str = "step") -> DataFrame:
    """``scores`` with the probability of each row in its step."""
    w = Window.partitionBy(by)
    e = F.exp((F.col(utility) - F.max(utility).over(w)) / tau)
    return scores.withColumn("_e", e).withColumn("prob", F.col("_e") / F.sum("_e").over(w)).drop("_e")


def rank_in_step(scores: DataFrame, key: Column, ratio: float, by: str = "step", id_col: str = "doc_id") -> DataFrame:
    """The floor(ratio N) rows of highest ``key`` per step, ties to the smaller id, with their rank ``rk``."""
    w = Window.partitionBy(by)
    ranked = scores.withColumn("_key", key).withColumn("rk", F.row_number().over(w.orderBy(F.col("_key").desc(), id_col)))
    return ranked.withColumn("_n", F.count(F.lit(1)).over(w)).filter(F.col("rk") <= F.floor(F.col("_n") * ratio + 1e-9)).drop("_key", "_n")


def pick_gumbel(scores: DataFrame, utility: str = "utility", tau: float = 0.9, ratio: float = 0.5, seed: int = 42) -> DataFrame:
    """Sampling without replacement in one sort: utility / tau plus Gumbel noise has the law of successive softmax draws."""
    key = F.round(F.col(utility) / tau + gumbel(F.concat_ws("|", F.lit(f"draw|{seed}"), F.col("step"), F.lit(0), F.col("doc_id"))), 9)
    return rank_in_step(scores, key, ratio)
