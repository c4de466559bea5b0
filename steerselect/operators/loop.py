"""The selection loop: proxy and candidates in one pass, scores in the optimizer's geometry, draws, and the update.

Per step the weights and the frozen geometries go out with the tasks (they are the model's size, not the data's); workers
return sketches and counts of pairs, never gradients of single texts.  Rows are dealt out by step, many steps at a time.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field
from hashlib import md5

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lm_block
from .pick import noises, pick_from_gram, quota
from .precond import Geometry, Optimizer, assign, clip_global_norm, lr_at
from .sketch import sketch, tables


@dataclass
class Config:
    vocabulary: int = 64
    d: int = 16
    h: int = 16
    mode: str = "hybrid"  # hybrid, adamw or sgd
    lr: dict = field(default_factory=lambda: {"adamw": 2e-3, "muon": 1e-2, "sgd": 0.1})
    ratio: float = 0.5
    tau: float = 0.9
    policy: str = "soft"
    penalty: bool = True
    sketch_dim: int | None = 512  # None: exact products
    proxy_batch: int = 8
    score_len: int = 512
    seed: int = 42
    selector: str = "geometry"  # geometry, raw, loss, random or full
    normalise: str = "raw"
    score_lr: float = 1.0
    refresh_every: int = 1
    muon_reference: str = "buffer"  # or "proxy": the proxy batch's gradient, which an empty buffer needs anyway


#: Steps whose rows are dealt out together.
CHUNK = 64
#: Tasks of a step, at most.
MOST_PARTS = 32

#: Hash tables of a worker, by layer and shape.
_tables: dict = {}


def features(grads: dict[str, np.ndarray], geo: dict[str, Geometry], cfg: Config, apply: bool) -> np.ndarray:
    """The concatenated sketches of a sequence's layer gradients, mapped by the geometry if ``apply``."""
    out = []
    for n, (name, g) in enumerate(sorted(grads.items())):
        g = geo[name].apply(g) if apply else g
        if cfg.sketch_dim is None:
            out.append(g.ravel())
            continue
        key = (name, g.shape, cfg.sketch_dim, cfg.seed)
        if key not in _tables:
            _tables[key] = tables(g.shape, cfg.sketch_dim, cfg.seed, n)
        out.append(sketch(g, _tables[key], cfg.sketch_dim))
    return np.concatenate(out)


def proxy_draws(proxy: DataFrame, cfg: Config, first: int, steps: int) -> list[tuple[int, int]]:
    """(step, doc_id): for each step the ``proxy_batch`` ids of the pool whose hash with the step is least; one job for all steps."""

    def least(rows: list[tuple[bytes, int]]) -> list[tuple[bytes, int]]:
        return heapq.nsmallest(cfg.proxy_batch, rows)

    def run(batches):
        ids = np.concatenate([np.zeros(0, np.int64), *(b.column(0).to_numpy(zero_copy_only=False) for b in batches)]).tolist()
        names = [b"%d" % i for i in ids]
        for step in range(first, first + steps):
            start = b"prx|%d|%d|" % (cfg.seed, step)
            got = [md5(start + x).digest() for x in names]
            head = np.frombuffer(b"".join(got), ">u8")[::2]
            at = np.flatnonzero(head <= np.partition(head, cfg.proxy_batch - 1)[cfg.proxy_batch - 1]).tolist() if len(ids) > cfg.proxy_batch else range(len(ids))
            best = least([(got[i], ids[i]) for i in at])
            yield pa.RecordBatch.from_arrays([pa.array([step] * len(best), pa.int64()), pa.array([h for h, _ in best], pa.binary()), pa.array([i for _, i in best], pa.int64())], names=["step", "h", "doc_id"])

    by_step: dict[int, list] = {}
    for r in proxy.select("doc_id").mapInArrow(run, "step long, h binary, doc_id long").collect():  # a batch for each step and task
        by_step.setdefault(r["step"], []).append((bytes(r["h"]), r["doc_id"]))
    return [(step, i) for step, rows in by_step.items() for _, i in least(rows)]


class Dealt:
    """The candidates and proxy documents of ``steps`` steps, dealt out so that each step has ``parts`` partitions of its own.

    The shuffle's files stay, so a job over a step starts that step's tasks and reads nothing else.
    """

    def __init__(self, buffers: DataFrame, proxy: DataFrame, cfg: Config, first: int, steps: int) -> None:
        spark = buffers.sparkSession
        self.sc, self.first, self.parts = spark.sparkContext, first, max(1, min(spark.sparkContext.defaultParallelism, MOST_PARTS))
        kind = np.min_scalar_type(max(1, cfg.vocabulary - 1))
        here = buffers.filter(F.col("step").between(first, first + steps - 1)).select("step", F.lit(False).alias("proxy"), "doc_id", "toks")
        drawn = proxy_draws(proxy, cfg, first, steps)
        if drawn:
            mine = proxy.join(F.broadcast(spark.createDataFrame(drawn, "step long, doc_id long")), "doc_id")  # ``proxy_batch`` rows a step
            here = here.unionByName(mine.select("step", F.lit(True).alias("proxy"), "doc_id", F.slice("toks", 1, cfg.score_len).alias("toks")))
        part = ((F.col("step") - first) * self.parts + F.pmod(F.xxhash64("doc_id"), F.lit(self.parts))).cast("int")

        def run(batches):
            for b in batches:
                toks = [np.asarray(x.values, kind).tobytes() for x in b.column("toks")]
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("part", "proxy", "doc_id")), pa.array(toks, pa.binary())], names=["part", "proxy", "doc_id", "toks"])

        flat = here.filter(F.size("toks") > 1).select(part.alias("part"), "proxy", "doc_id", "toks").mapInArrow(run, "part int, proxy boolean, doc_id long, toks binary")
        self.rows = flat.rdd.map(lambda r: (r[0], (r[1], r[2], bytes(r[3])))).partitionBy(steps * self.parts, int)
        self.kind = kind

    def job(self, step: int, make) -> list:
        """``make([(proxy, doc_id, tokens)])`` of each of the step's partitions that has rows; their order is the same in every run."""
        kind, low = self.kind, (step - self.first) * self.parts

        def run(pairs):
            rows = sorted(x for _, x in pairs)
            return [make([(p, d, np.frombuffer(t, kind).astype(np.int64)) for p, d, t in rows])] if rows else []

        return self.sc.runJob(self.rows, run, list(range(low, low + self.parts)))


@dataclass
class Scored:
    """The sequences of a step, and their counts of pairs (code x * vocabulary + y), ``cells`` of each."""

    proxy: np.ndarray
    doc: np.ndarray
    nll: np.ndarray
    phi: np.ndarray
    cells: np.ndarray
    codes: np.ndarray
    counts: np.ndarray


def score_pass(rows: Dealt, step: int, theta: dict, geo: dict, cfg: Config) -> Scored:
    """Losses and features of a step's proxy documents and candidates, by their prefix, and the pairs of whole texts: one pass."""

    def make(held):
        v, out = len(theta["head"]), []
        for proxy, doc, toks in held:
            loss, grads = lm_block.by_token(theta, toks[: cfg.score_len])
            codes, counts = np.unique(toks[:-1] * v + toks[1:], return_counts=True)
            out.append((proxy, doc, loss, features(grads, geo, cfg, not proxy), len(codes), codes.astype(np.int32), counts.astype(np.int32)))
        proxy, doc, nll, phi, cells, codes, counts = zip(*out)
        return np.array(proxy), np.array(doc, np.int64), np.array(nll), np.stack(phi), np.array(cells), np.concatenate(codes), np.concatenate(counts)

    got = rows.job(step, make)
    return Scored(*map(np.concatenate, zip(*got))) if got else Scored(np.zeros(0, bool), *[np.zeros(0)] * 6)


def gradient_of(scored: Scored, chosen: list[int], theta: dict) -> tuple[dict[str, np.ndarray], int]:
    """(mean gradient, tokens) of some of a step's sequences, whole: it is linear in their shares of pairs, which are added up first."""
    v = len(theta["head"])
    of = np.repeat(np.arange(len(scored.cells)), scored.cells)
    pairs = np.bincount(of, scored.counts, len(scored.cells))
    weight = np.zeros(len(pairs))
    weight[chosen] = 1 / (pairs[chosen] * len(chosen))
    shares = np.bincount(scored.codes, scored.counts * weight[of], v * v).reshape(v, v)
    return lm_block.by_counts(theta, np.arange(v), shares)[1], int(pairs[chosen].sum()) + len(chosen)


def proxy_gradient(rows: Dealt, step: int, theta: dict) -> dict[str, np.ndarray]:
    """The mean gradient of a step's proxy documents by their prefix: summed by each task, a table of the model's size."""

    def make(held):
        got = [lm_block.by_token(theta, toks)[1] for proxy, _, toks in held if proxy]
        return {k: sum(g[k] for g in got) for k in theta} if got else None, len(got)

    got = [g for g in rows.job(step, make) if g[1]]
    n = max(1, sum(g[1] for g in got))
    return {k: sum((g[0][k] for g in got), np.zeros(v.shape)) / n for k, v in theta.items()}


def choose(scored: Scored, cfg: Config, step: int) -> list[tuple[int, float]]:
    """(index into ``scored``, utility) of a step's picks in draw order."""
    own = np.flatnonzero(~scored.proxy)
    own = own[np.argsort(scored.doc[own], kind="stable")]
    ids, k = scored.doc[own], quota(len(own), cfg.ratio if cfg.selector != "full" else 1.0)
    if cfg.selector == "loss":
        order = np.lexsort((ids, -scored.nll[own]))[:k]
        return [(int(own[i]), float(scored.nll[own[i]])) for i in order]
    if cfg.selector in ("random", "full"):
        u = noises(cfg.seed, step, 0, ids.tolist())
        return [(int(own[i]), float(u[i])) for i in np.lexsort((ids, -u))[:k]]
    phi = scored.phi[own]
    proxy = scored.phi[scored.proxy].mean(0) if scored.proxy.any() else np.zeros(phi.shape[1])
    policy = "greedy" if cfg.selector == "raw" else cfg.policy
    got = pick_from_gram(phi @ proxy, phi @ phi.T, k, cfg.score_lr, cfg.tau, policy, cfg.penalty, None, ids, normalise=cfg.normalise, noises_of=lambda d, at: noises(cfg.seed, step, d, ids[at].tolist()))
    return [(int(own[z]), u) for z, u, _ in got]


def start(cfg: Config) -> tuple[dict, dict[str, Optimizer]]:
    theta = lm_block.init(cfg.vocabulary, cfg.d, cfg.h, cfg.seed)
    kinds = assign(lm_block.LAYERS, cfg.mode)
    return theta, {k: Optimizer(kinds[k], v.shape, cfg.lr[kinds[k]]) for k, v in theta.items()}


def frozen_geometry(optimizers: dict[str, Optimizer], rows: Dealt, step: int, theta: dict, cfg: Config) -> dict[str, Geometry]:
    """The maps of the next step; Muon's factor is taken at its momentum, or at the proxy batch's gradient."""
    if cfg.selector != "geometry":
        return {k: Geometry() for k in optimizers}
    by_proxy = {k for k, o in optimizers.items() if o.kind == "muon" and (cfg.muon_reference == "proxy" or not o.m.any())}
    g = proxy_gradient(rows, step, theta) if by_proxy else {}
    return {k: o.geometry(g[k], True) if k in by_proxy else o.geometry() for k, o in optimizers.items()}


def run_selection(buffers: DataFrame, proxy: DataFrame, cfg: Config, steps: int, theta: dict | None = None, optimizers: dict | None = None, first: int = 0) -> tuple[dict, dict, list[dict], list[dict]]:
    """Runs ``steps`` steps over ``buffers`` (step, doc_id, toks) with the pool ``proxy`` (doc_id, toks).

    Returns weights, optimizers, picks (step, draw, doc_id, utility) and a log (step, n, k, tokens, nll).  A buffer and a
    proxy batch have the buffer's size, so a step's features and counts of pairs, at most the squared vocabulary for each
    sequence, may come to the driver, where the draws are made; with ``refresh_every`` S the geometry and the weights stay
    for S steps.  A step is one job.
    """
    if theta is None:
        theta, optimizers = start(cfg)
    picks, log, frozen, geo, rows = [], [], theta, None, None
    for step in range(first, first + steps):
        if (step - first) % CHUNK == 0:
            rows = Dealt(buffers, proxy, cfg, step, min(CHUNK, first + steps - step))
        if geo is None or (step - first) % cfg.refresh_every == 0:
            frozen = theta
            geo = frozen_geometry(optimizers, rows, step, frozen, cfg)
        scored = score_pass(rows, step, frozen, geo, cfg)
        if scored.proxy.all():
            continue
        got = choose(scored, cfg, step)
        picks += [{"step": step, "draw": i, "doc_id": int(scored.doc[z]), "utility": u} for i, (z, u) in enumerate(got)]
        tokens = 0
        if got:
            g, tokens = gradient_of(scored, [z for z, _ in got], theta)
            g = clip_global_norm(g)
            theta = {k: optimizers[k].step(w, g[k], lr_at(step + 1, first + steps)) for k, w in theta.items()}
        own = ~scored.proxy
        log.append({"step": step, "n": int(own.sum()), "k": len(got), "tokens": tokens, "nll": float(scored.nll[own].mean())})
    return theta, optimizers, picks, log


def set_loss(rows: DataFrame, theta: dict) -> DataFrame:
    """(doc_id, n_pairs, nll) of rows (doc_id, toks) under the block model."""
    shared = rows.sparkSession.sparkContext.broadcast(theta)

    def run(batches):
        for pdf in batches:
            t = [np.asarray(x, np.int64) for x in pdf["toks"]]
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "n_pairs": [max(0, len(x) - 1) for x in t], "nll": [lm_block.loss(shared.value, x) for x in t]})

    return rows.select("doc_id", "toks").mapInPandas(run, "doc_id long, n_pairs int, nll double").filter(~F.isnan("nll"))
