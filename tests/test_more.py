"""The utility's forms, protocols, decoding, updates and the grouped scores against brute force; their queries against SQL."""

from __future__ import annotations

import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F
from test_queries import SF, rows

import __spark_entry__ as entry
from steerselect.operators import corpus, lm_block, lm_step, loop, measures, pick, precond, sketch, utility


def setting(seed=0):
    r = np.random.default_rng(seed)
    theta = lm_block.init(7, 4, 5, seed)
    toks = [r.integers(0, 7, 9) for _ in range(6)]
    g = utility.mean_gradient(theta, toks)
    geo = {
        "plain": {k: precond.plain() for k in theta},
        "adamw": {k: precond.adamw({"v": 0.05 * v * v}, 2, eps=0.05) for k, v in g.items()},
        "muon": {k: precond.muon(v, 0.85) for k, v in g.items()},
    }
    return theta, toks, geo


@pytest.mark.parametrize("name", ["plain", "adamw", "muon"])
def test_forms_approach_the_exact_marginal_gain(name):
    """Halving the rate quarters the error of either linear form: each is exact to first order, the next order is left."""
    theta, toks, geo = setting()
    for form, f in utility.FORMS.items():
        gap = []
        for lr in (2e-3, 1e-3):
            want = utility.marginal_exact(theta, geo[name], toks[:2], toks[2], toks[4:], lr)
            gap.append(abs(f(theta, geo[name], toks[:2], toks[2], toks[4:], lr) - want))
        assert gap[0] / gap[1] == pytest.approx(4, rel=0.2), form
    got = utility.exact(theta, geo[name], toks[:3], toks[4:], 1e-3) - utility.exact(theta, geo[name], toks[:2], toks[4:], 1e-3)
    assert got == pytest.approx(utility.marginal_exact(theta, geo[name], toks[:2], toks[2], toks[4:], 1e-3))


def test_the_hessian_form_follows_the_first_order_form():
    """The gradient's linearisation leaves a third-order rest, so the two differ by a cube of the rate."""
    theta, toks, geo = setting(3)
    gap = [abs(utility.marginal_hessian(theta, geo["plain"], toks[:2], toks[2], toks[4:], lr) - utility.marginal_first_order(theta, geo["plain"], toks[:2], toks[2], toks[4:], lr)) for lr in (0.04, 0.02)]
    assert gap[0] / gap[1] == pytest.approx(8, rel=0.25)
    d = utility.mean_gradient(theta, toks[:2])
    assert utility.dot(utility.hessian_product(theta, toks[4:], d), utility.mean_gradient(theta, toks[2:3])) == pytest.approx(utility.dot(utility.hessian_product(theta, toks[4:], utility.mean_gradient(theta, toks[2:3])), d), rel=1e-4)


def test_a_shift_of_all_updates_changes_no_choice():
    """Old momentum and decay move every candidate's update alike, so order and draws stay."""
    r = np.random.default_rng(5)
    phi, proxy, shift = r.normal(size=(12, 6)), r.normal(size=6), r.normal(size=6)
    plain = [z for z, _, _ in pick.pick_from_gram(phi @ proxy, phi @ phi.T, 6, 0.1, policy="greedy", penalty=False)]
    moved = [z for z, _, _ in pick.pick_from_gram((phi + shift) @ proxy, phi @ phi.T, 6, 0.1, policy="greedy", penalty=False)]
    assert plain == moved
    noise = lambda d, i: pick.noise(1, 2, d, i)
    assert [z for z, _, _ in pick.pick_from_gram(phi @ proxy, phi @ phi.T, 6, noise_of=noise)] == [z for z, _, _ in pick.pick_from_gram(phi @ proxy + shift @ proxy, phi @ phi.T, 6, noise_of=noise)]


@pytest.mark.parametrize("kind", ["sgd", "adamw", "muon"])
def test_updates_of_an_optimizer(kind):
    r = np.random.default_rng(1)
    o, w = precond.Optimizer(kind, (3, 4), 0.1, decay=0.01), r.normal(size=(3, 4))
    m = v = np.zeros((3, 4))
    for t in (1, 2, 3):
        g = r.normal(size=(3, 4))
        if kind == "adamw":
            m, v = 0.8 * m + 0.2 * g, 0.95 * v + 0.05 * g * g
            want = w - 0.1 * (m / (1 - 0.8**t)) / (np.sqrt(v / (1 - 0.95**t)) + 1e-8) - 0.1 * 0.01 * w
        elif kind == "muon":
            mu = precond.muon_momentum(t)
            m = mu * m + (1 - mu) * g
            q = mu * m + (1 - mu) * g
            s, left = precond.muon_factor(q)
            want = w - 0.1 * (s @ q if left else q @ s) / np.linalg.norm(q)
        else:
            want = w - 0.1 * g - 0.1 * 0.01 * w
        w = o.step(w, g)
        assert np.allclose(w, want)


def test_muon_takes_the_proxy_while_its_buffer_is_empty():
    r = np.random.default_rng(2)
    o, g, p = precond.Optimizer("muon", (4, 4), 0.1), r.normal(size=(4, 4)), r.normal(size=(4, 4))
    assert np.allclose(o.geometry(p).factor, precond.muon_factor(p)[0])
    o.step(np.zeros((4, 4)), g)
    assert np.allclose(o.geometry(p).factor, precond.muon_factor(o.m)[0]) and np.allclose(o.geometry(p, True).factor, precond.muon_factor(p)[0])


def test_grouped_scores_against_whole_gradients(spark):
    r, v, m = np.random.default_rng(4), 6, 8
    own = [(s, k, 10 * s + k, r.integers(0, v, int(r.integers(1, 12))).tolist()) for s in range(3) for k in range(7)]
    beside = [(s, 100 + 10 * s + k, r.integers(0, v, 9).tolist()) for s in range(2) for k in range(3)]
    train = [(1000 + k, r.integers(0, v, 15).tolist()) for k in range(9)] + [(2000, [1])]
    df = lambda x, c: spark.createDataFrame(x, c)
    model = lm_step.counted(df(train, "doc_id long, toks array<long>"))
    got = lm_step.step_pass(df(own, "step long, slot long, doc_id long, toks array<long>"), df(beside, "step long, doc_id long, toks array<long>"), model, v, m, scale=0.5, phi="shaped").toPandas().set_index("doc_id")
    n = np.zeros((v, v))
    for _, t in train:
        np.add.at(n, (t[:-1], t[1:]), 1.0)
    p = (n + 0.5) / (n.sum(1, keepdims=True) + 0.5 * v)
    grad = lambda t: lm_step.gradient(p, np.array(t))
    past = np.mean([grad(t) for _, t in train if len(t) > 1], 0)
    shape, factor, table = 0.5 / (np.abs(past) + 1e-4), precond.muon_factor(past)[0], sketch.tables((v, v), m)
    assert set(got.index) == {d for _, _, d, t in own if len(t) > 1}
    for s, _, d, t in own:
        if len(t) < 2:
            continue
        near = [grad(x) for b, _, x in beside if b == s]
        q = np.mean(near, 0) if near else np.zeros((v, v))
        first = sum(grad(x) for b, k, _, x in own if b == s and k < 4 and len(x) > 1)
        g, sk = grad(t), lambda x: sketch.sketch(x, table, m)
        want = {"plain": (g * q).sum(), "shaped": (shape * g * q).sum(), "muon": ((factor @ g) * q).sum(), "sketched": sk(shape * g) @ sk(q), "plain_sketched": sk(g) @ sk(q), "redundancy": (g * first).sum()}
        for k, x in want.items():
            assert got.loc[d, k] == pytest.approx(x, rel=1e-9, abs=1e-9), k
        assert np.allclose(got.loc[d, "phi"], sk(shape * g))


def test_decoding_by_hand(spark):
    logp = np.log(np.array([[0.5, 0.3, 0.15, 0.05], [0.25] * 4, [0.97, 0.01, 0.01, 0.01], [0.1, 0.2, 0.3, 0.4]]))
    lm = spark.createDataFrame([(x, y, float(logp[x, y])) for x in range(4) for y in range(4)], "x long, y long, logp double")
    after = measures.next_tokens(lm, 0.6, 0.9, 3)
    table = {(r.x, r.y): r.prob for r in after.collect()}
    keep = {}
    for x in range(4):
        e = np.exp(logp[x] / 0.6)
        order = sorted(range(4), key=lambda y: (-round(logp[x, y], 9), y))[:3]
        q = np.array([e[y] for y in order]) / sum(e[y] for y in order)
        kept = [y for i, y in enumerate(order) if round(q[:i].sum(), 9) < 0.9]
        keep[x] = {y: e[y] / sum(e[k] for k in kept) for y in kept}
    assert {(x, y): pytest.approx(v) for x in keep for y, v in keep[x].items()} == table and len(keep[2]) == 1
    got = measures.decode(spark.createDataFrame([(7, 0), (8, 3)], "doc_id long, last long"), after, 12, 1).collect()
    import hashlib

    for r in got:
        last, want = {7: 0, 8: 3}[r.doc_id], []
        for at in range(12):
            key = lambda y: (round(np.log(keep[last][y]) - np.log(-np.log((int(hashlib.md5(f"dec|1|{r.doc_id}|{at}|{y}".encode()).hexdigest()[:7], 16) + 0.5) / (1 << 28))), 9), -y)  # noqa: E731, B023
            last = max(keep[last], key=key)
            want.append(last)
        assert r.toks == want


def test_protocols_and_running_totals(spark):
    r = np.random.default_rng(6)
    data = [(s, 10 * s + i, float(round(r.normal() + s, 3)), int(r.integers(1, 9))) for s in range(4) for i in range(9)]
    df = spark.createDataFrame(data, "step long, doc_id long, score double, n long").repartition(5)
    by = sorted(data, key=lambda x: (-x[2], x[1]))
    assert {x.doc_id for x in corpus.run_static(df, 0.5).collect()} == {x[1] for x in by[:18]}
    assert {x.doc_id for x in corpus.run_dynamic(df, 0.5).collect()} == {x[1] for s in range(4) for x in [y for y in by if y[0] == s][:4]}
    import hashlib

    got = {x.doc_id: x.c for x in corpus.running_total(df, F.md5(F.col("doc_id").cast("string")), "doc_id", "n", "c", 1).collect()}
    total = 0
    for x in sorted(data, key=lambda x: hashlib.md5(str(x[1]).encode()).hexdigest()):
        total += x[3]
        assert got[x[1]] == total


def test_loop_reads_whole_texts_and_counts_their_tokens(spark):
    r = np.random.default_rng(0)
    docs = [(s, 10 * s + i, r.integers(0, 8, 30).tolist()) for s in range(2) for i in range(4)]
    pool = [(100 + i, r.integers(0, 8, 30).tolist()) for i in range(5)]
    cfg = loop.Config(vocabulary=8, d=3, h=3, score_len=10, proxy_batch=2, sketch_dim=32)
    rows = spark.createDataFrame(docs, "step long, doc_id long, toks array<long>")
    _, _, picks, log = loop.run_selection(rows, spark.createDataFrame(pool, "doc_id long, toks array<long>"), cfg, 2)
    assert [x["tokens"] for x in log] == [60, 60] and len(picks) == 4


@pytest.mark.parametrize("name", ["static_dynamic", "op_running_budget", "decode_table", "loss_length_rank_corr", "diversity_cosine", "op_setops_all", "op_spearman", "utility_sketched", "utility_full", "sketch_error", "base_raw_grad"])
def test_more_queries_equal_sql(spark, name):
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    assert rows(entry.queries()[name](spark, SF).toPandas()) == rows(c.execute(entry.oracle_sql()[name]).fetch_df())


def test_one_buffer_looked_at_closely(spark):
    from steerselect.plans.context import Tables
    from steerselect.plans.workloads import CLOSE_K, CLOSE_N, STATIC

    got = entry.queries()["w11_one_buffer"](spark, SF).toPandas()
    t = Tables(spark, SF)
    first = {r.doc_id for r in t.buffers.filter(f"step = 0 AND slot < {CLOSE_N}").collect()}
    score = {m: dict(zip(x.key.astype(int), x.value)) for m, x in got[got.metric == "score"].groupby("method")}
    place = {m: dict(zip(x.key.astype(int), x.value)) for m, x in got[got.metric == "place among the picks"].groupby("method")}
    assert set(score) == {"high-loss", "raw-gradient", "geometry", "geometry-muon", *STATIC} and set(place) == {*score, "soft draw"}
    assert all(set(x) <= first for x in score.values()) and set(score["random"]) == first
    want = {r.doc_id: r for r in t.step_scores().filter("step = 0").collect()}  # the whole buffer's pass gives its part the same scores
    for m, k in (("geometry", "shaped"), ("geometry-muon", "muon"), ("raw-gradient", "plain")):
        assert score[m] == {d: pytest.approx(want[d][k], abs=1e-5) for d in first if d in want}
    for m, x in place.items():
        assert sorted(x.values()) == list(range(1, CLOSE_K + 1))
        if m in score:
            assert min(score[m][d] for d in x) >= max((v for d, v in score[m].items() if d not in x), default=-np.inf)
    for r in got[got.metric == "shared"].itertuples():
        assert r.value == len(set(place[r.method]) & set(place[r.key]))


def test_sketch_sizes_and_timed_stages(spark):
    got = entry.queries()["w09_sensitivity"](spark, SF).toPandas()
    by = got[got.metric == "rank correlation"].set_index("method").value
    assert set(by.index) == {"m=64", "m=128", "m=256"} and by["m=64"] < by["m=256"] <= 1 and len(got[got.metric == "nll"]) == 12
    took = entry.queries()["w10_efficiency"](spark, SF).toPandas().query("block == 'wall time'")
    assert len(took) == 5 and (took.value > 0).all()
