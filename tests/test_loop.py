"""The selection loop against plain numpy: one job a step, rows dealt out for many steps at a time."""

from __future__ import annotations

from hashlib import md5

import numpy as np
import pytest

from steerselect.operators import lm_block, loop, pick, sketch
from steerselect.operators.precond import clip_global_norm, lr_at


def test_counts_of_pairs_give_loss_and_gradient():
    r = np.random.default_rng(3)
    theta = lm_block.init(9, 4, 5)
    for n in (2, 3, 700):
        toks = r.integers(0, 9, n)
        nll, got = lm_block.by_token(theta, toks)
        assert nll == pytest.approx(lm_block.loss(theta, toks))
        for k, v in lm_block.gradient(theta, toks).items():
            assert np.allclose(got[k], v, atol=1e-12)


def test_noise_of_many_ids_is_that_of_each():
    ids = [0, 7, 10**12, -3]
    assert pick.noises(5, 2, 3, ids) == pytest.approx([pick.noise(5, 2, 3, i) for i in ids], rel=1e-12)


def plain_loop(docs, pool, cfg, steps):
    theta, optimizers = loop.start(cfg)
    out = []
    for step in range(steps):
        near = sorted(pool, key=lambda x: (md5(f"prx|{cfg.seed}|{step}|{x[0]}".encode()).hexdigest(), x[0]))[: cfg.proxy_batch]
        near = [np.array(x[1][: cfg.score_len]) for x in near]
        grads = [lm_block.gradient(theta, x) for x in near]
        mean = {k: np.mean([g[k] for g in grads], 0) for k in theta}
        geo = {k: o.geometry(mean[k], True) if o.kind == "muon" and not o.m.any() else o.geometry() for k, o in optimizers.items()}
        tables = {k: sketch.tables(theta[k].shape, cfg.sketch_dim, cfg.seed, n) for n, k in enumerate(sorted(theta))}
        phi = lambda g: np.concatenate([sketch.sketch(g[k], tables[k], cfg.sketch_dim) for k in sorted(g)])
        own = sorted((d, x) for s, d, x in docs if s == step)
        if not own:
            continue
        mine = [lm_block.gradient(theta, np.array(x[: cfg.score_len])) for _, x in own]
        f = np.stack([phi({k: geo[k].apply(g[k]) for k in g}) for g in mine])
        q = np.mean([phi(g) for g in grads], 0)
        ids = np.array([d for d, _ in own])
        got = pick.pick_from_gram(f @ q, f @ f.T, len(own) // 2, cfg.score_lr, cfg.tau, noise_of=lambda d, i: pick.noise(cfg.seed, step, d, ids[i]), ids=ids)
        out += [(step, n, int(ids[z]), u) for n, (z, u, _) in enumerate(got)]
        whole = [lm_block.gradient(theta, np.array(own[z][1])) for z, _, _ in got]
        g = clip_global_norm({k: np.mean([x[k] for x in whole], 0) for k in theta})
        theta = {k: optimizers[k].step(w, g[k], lr_at(step + 1, steps)) for k, w in theta.items()}
    return out, theta


def test_loop_equals_plain_numpy_with_one_job_a_step(spark, monkeypatch):
    monkeypatch.setattr(loop, "CHUNK", 3)
    r = np.random.default_rng(1)
    draw = lambda: r.integers(0, 8, int(r.integers(2, 40))).tolist()
    docs = [(s, 10 * s + i, draw()) for s in (0, 1, 2, 4) for i in range(6)]  # step 3 has no rows
    pool = [(100 + i, draw()) for i in range(9)]
    cfg = loop.Config(vocabulary=8, d=3, h=3, score_len=10, proxy_batch=2, sketch_dim=32)
    rows = spark.createDataFrame(docs, "step long, doc_id long, toks array<long>").repartition(3)
    near = spark.createDataFrame(pool, "doc_id long, toks array<long>").repartition(3)
    jobs, run = [], spark.sparkContext.runJob
    monkeypatch.setattr(type(spark.sparkContext), "runJob", lambda self, rdd, f, parts=None, *a: jobs.append(parts) or run(rdd, f, parts, *a))
    theta, _, picks, log = loop.run_selection(rows, near, cfg, 5)
    want, weights = plain_loop(docs, pool, cfg, 5)
    assert [(p["step"], p["draw"], p["doc_id"]) for p in picks] == [x[:3] for x in want]
    assert [p["utility"] for p in picks] == pytest.approx([x[3] for x in want], rel=1e-6)
    assert all(np.allclose(theta[k], weights[k]) for k in theta) and [x["step"] for x in log] == [0, 1, 2, 4]
    assert len(jobs) == 6  # one for each step, and one for the first step's proxy gradient


def test_timed_stages_read_the_same_stored_tokens(spark, monkeypatch):
    """w10_efficiency stores tokens once: the naive stage does not make its own, within its time and on disk."""
    import __spark_entry__ as entry
    from steerselect.plans import context

    labels, stored = [], context.stored
    monkeypatch.setattr(context, "stored", lambda df, label: labels.append(label) or stored(df, label))
    got = entry.queries()["w10_efficiency"](spark, "/root/testdata/sf0.001").toPandas()
    assert labels.count("tokens") == 1 and len(got[got.block == "wall time"]) == 5
