"""Algebra, gradients, sketches, picks and the utility chain against brute force and hand-worked values."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from steerselect.operators import lm_block, pick, precond, sketch


def test_adamw_hand_worked():
    v = np.array([0.2])
    assert precond.adamw_scale(0.8, 2) == pytest.approx(0.555556, abs=1e-6)
    assert precond.adamw_map(v, 2, eps=0.0)[0] == pytest.approx(0.277778, abs=1e-6)
    assert precond.adamw_map(v, 2, eps=0.0, form="bar")[0] == pytest.approx(0.397973, abs=1e-6)  # 0.555556 / sqrt(1.948718)
    assert (precond.adamw_map(v, 1) == 1).all()
    assert precond.adamw_scale(0.8, 2, lr=3.0, boxed=True) == 3.0


def test_muon_values():
    assert 1 - 0.95**2 == pytest.approx(0.0975)
    assert precond.muon_lr(1.0, 4, 1) == 2 and precond.muon_lr(1.0, 1, 4) == 1
    assert precond.muon_momentum(150) == pytest.approx(0.90) and precond.muon_momentum(900) == pytest.approx(0.95)
    assert (precond.muon_factor(np.zeros((3, 5)))[0] == np.eye(3)).all()


@pytest.mark.parametrize("shape", [(4, 7), (7, 4)])
def test_muon_factor_is_the_whole_iteration(shape):
    r = np.random.default_rng(0).normal(size=shape)
    a, b, c = precond.QUINTIC
    x = r / np.linalg.norm(r)
    for _ in range(5):
        g = x @ x.T
        x = a * x + (b * g + c * g @ g) @ x
    s, left = precond.muon_factor(r)
    u = r / np.linalg.norm(r)
    assert np.allclose(s @ u if left else u @ s, x, atol=1e-9)


def test_assignment_clip_and_schedule():
    assert precond.assign(lm_block.LAYERS) == {"embedding": "adamw", "block": "muon", "head": "adamw"}
    g = precond.clip_global_norm({"a": np.array([3.0]), "b": np.array([4.0])})
    assert g["a"][0] == pytest.approx(0.6) and g["b"][0] == pytest.approx(0.8)
    assert precond.lr_at(5, 1000) == 0.5 and precond.lr_at(500, 1000) == 1.0


def test_block_gradients_by_central_differences():
    theta = lm_block.init(7, 4, 5)
    toks = np.array([1, 3, 2, 6, 3, 3, 0])
    grad = lm_block.gradient(theta, toks)
    for name, w in theta.items():
        for i in [(0, 0), (1, 2), (w.shape[0] - 1, w.shape[1] - 1)]:
            e = 1e-5
            up, down = ({k: v.copy() for k, v in theta.items()} for _ in range(2))
            up[name][i] += e
            down[name][i] -= e
            assert grad[name][i] == pytest.approx((lm_block.loss(up, toks) - lm_block.loss(down, toks)) / (2 * e), abs=1e-7)


def test_ghost_products_equal_full_products():
    theta = lm_block.init(9, 4, 6)
    a, b = lm_block.ghost(theta, np.array([1, 2, 3, 4])), lm_block.ghost(theta, np.array([8, 2, 2, 5, 1]))
    for k in a:
        assert lm_block.ghost_dot(a[k], b[k]) == pytest.approx(float(((a[k][0].T @ a[k][1]) * (b[k][0].T @ b[k][1])).sum()), abs=1e-12)


def test_sketch_is_unbiased_and_linear():
    r = np.random.default_rng(1)
    g, h = r.normal(size=(6, 5)), r.normal(size=(6, 5))
    err = [sketch.sketch(g, t, 16) @ sketch.sketch(h, t, 16) - (g * h).sum() for t in (sketch.tables((6, 5), 16, s) for s in range(800))]
    sd = np.sqrt(((g**2).sum() * (h**2).sum() + (g * h).sum() ** 2) / 16)
    assert abs(np.mean(err)) < 4 * sd / np.sqrt(800) and np.std(err) < 1.5 * sd
    t = sketch.tables((6, 5), 16)
    assert np.allclose(sketch.sketch(g + 2 * h, t, 16), sketch.sketch(g, t, 16) + 2 * sketch.sketch(h, t, 16))


def test_factored_sketch_equals_its_coordinates():
    r = np.random.default_rng(2)
    b, a, m = r.normal(size=(3, 6)), r.normal(size=(3, 5)), 16
    h1, s1, h2, s2 = table = sketch.factored_tables((6, 5), m)
    coordinate = ((h1[:, None] + h2[None]) % m, s1[:, None] * s2[None])
    assert np.allclose(sketch.sketch_outer(b, a, table, m), sketch.sketch(b.T @ a, coordinate, m), atol=1e-12)


def test_picks_hand_worked():
    align, gram = np.array([0.9, 0.85, 0.3]), np.array([[1, 0.5, 0], [0.5, 1, 0.1], [0, 0.1, 1]])
    order = lambda g, **k: [z for z, _, _ in pick.pick_from_gram(align, g, 2, policy="greedy", **k)]
    assert order(gram) == [0, 1]
    gram[0, 1] = gram[1, 0] = 0.6
    assert order(gram) == [0, 2] and order(gram, penalty=False) == [0, 1]
    assert pick.quota(32, 0.5) == 16 and pick.quota(1, 0.5) == 0 and pick.quota(9, 1.0) == 9


def test_copies_are_penalised():
    phi = np.array([[1.0, 0], [1, 0], [1, 0], [0, 1]])
    got = [z for z, _, _ in pick.pick_from_gram(np.ones(4), phi @ phi.T, 2, policy="greedy")]
    assert got == [0, 3]


@settings(max_examples=40, deadline=None)
@given(st.integers(2, 8), st.integers(0, 999), st.floats(0.01, 5))
def test_gram_loop_equals_history(n, seed, lr):
    r = np.random.default_rng(seed)
    phi, proxy = r.normal(size=(n, 5)), r.normal(size=5)
    noise = lambda d, i: pick.noise(1, seed, d, i)
    got = [z for z, _, _ in pick.pick_from_gram(phi @ proxy, phi @ phi.T, n // 2, lr, noise_of=noise)]
    left, history, want = list(range(n)), np.zeros(5), []
    for d in range(n // 2):
        u = {i: lr * phi[i] @ proxy - lr**2 * phi[i] @ history for i in left}
        z = max(left, key=lambda i: u[i] / 0.9 + noise(d, i))
        want.append(z)
        left.remove(z)
        history += phi[z]
    assert got == want


def test_one_shot_noise_has_the_law_of_successive_draws():
    u, k, tau = np.array([0.3, 0.0, 0.8]), 2, 0.9
    e = np.exp(u / tau)
    want = {}
    for i in range(3):
        for j in range(3):
            if i != j:
                want[i, j] = e[i] / e.sum() * e[j] / (e.sum() - e[i])
    g = np.random.default_rng(0).gumbel(size=(60_000, 3))
    top = np.argsort(-(u / tau + g), axis=1)[:, :k]
    for (i, j), p in want.items():
        assert ((top == (i, j)).all(1)).mean() == pytest.approx(p, abs=0.01)


def test_utility_orders():
    """Exact gain minus the first-order gain falls as the square of the rate; the first-order part wins for small rates."""
    theta, toks = lm_block.init(6, 3, 4), np.array([0, 1, 2, 3, 4, 5, 1, 2])
    val = np.array([2, 3, 4, 1, 2, 3])
    g, gv = lm_block.gradient(theta, toks), lm_block.gradient(theta, val)
    gap = []
    for lr in (0.02, 0.01):
        moved = {k: v - lr * g[k] for k, v in theta.items()}
        exact = lm_block.loss(theta, val) - lm_block.loss(moved, val)
        gap.append(abs(exact - lr * sum((g[k] * gv[k]).sum() for k in g)))
    assert gap[0] / gap[1] == pytest.approx(4, rel=0.15)
