"""A three-layer token model in numpy with closed-form gradients as ghost factors.

Embedding E (V x d), hidden B (h x d) with tanh, head W (V x h): one matrix inside a block and two outside, so that the
hybrid assignment has both kinds of layers.  A layer's gradient is the sum over positions of outer products b_t a_t of an
error and an input; the factors are all that is kept.
"""

from __future__ import annotations

import numpy as np

LAYERS = [
    {"layer": "embedding", "in_block": False, "ndim": 2},
    {"layer": "block", "in_block": True, "ndim": 2},
    {"layer": "head", "in_block": False, "ndim": 2},
]


def init(vocabulary: int = 64, d: int = 16, h: int = 16, seed: int = 42) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    return {"embedding": r.normal(0, 0.3, (vocabulary, d)), "block": r.normal(0, d**-0.5, (h, d)), "head": r.normal(0, h**-0.5, (vocabulary, h))}


def forward(theta: dict, toks: np.ndarray) -> tuple[np.ndarray, ...]:
    x, y = toks[:-1], toks[1:]
    h0 = theta["embedding"][x]
    h1 = np.tanh(h0 @ theta["block"].T)
    z = h1 @ theta["head"].T
    z -= z.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    return x, y, h0, h1, p


def loss(theta: dict, toks: np.ndarray) -> float:
    """Mean negative log-likelihood; NaN for fewer than two tokens."""
    if len(toks) < 2:
        return float("nan")
    _, y, _, _, p = forward(theta, toks)
    return float(-np.log(p[np.arange(len(y)), y]).mean())


def ghost(theta: dict, toks: np.ndarray) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Per layer (b, a), positions by rows: the gradient of the mean loss is b.T @ a."""
    x, y, h0, h1, p = forward(theta, toks)
    e = p
    e[np.arange(len(y)), y] -= 1
    e /= len(y)
    d = (e @ theta["head"]) * (1 - h1 * h1)
    one = np.zeros((len(x), len(theta["embedding"])))
    one[np.arange(len(x)), x] = 1
    return {"head": (e, h1), "block": (d, h0), "embedding": (one, d @ theta["block"])}


def gradient(theta: dict, toks: np.ndarray) -> dict[str, np.ndarray]:
    return {k: b.T @ a for k, (b, a) in ghost(theta, toks).items()}


def by_counts(theta: dict, x: np.ndarray, c: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """The loss and gradient of pairs of tokens ``x`` and any next ones, ``c`` being their weights, a row for each of ``x``.

    The model sees the current token alone, so positions of equal tokens share one row of everything but the next token.
    """
    h0 = theta["embedding"][x]
    h1 = np.tanh(h0 @ theta["block"].T)
    z = h1 @ theta["head"].T
    z -= z.max(1, keepdims=True)
    p = np.exp(z)
    total = p.sum(1, keepdims=True)
    e = c.sum(1, keepdims=True) * (p / total) - c
    d = (e @ theta["head"]) * (1 - h1 * h1)
    embedding = np.zeros_like(theta["embedding"])
    embedding[x] = d @ theta["block"]
    return -float((c * (z - np.log(total))).sum()), {"head": e.T @ h1, "block": d.T @ h0, "embedding": embedding}


def by_token(theta: dict, toks: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """(``loss``, ``gradient``) of a sequence of two tokens or more, from its counts of pairs."""
    x, at = np.unique(toks[:-1], return_inverse=True)
    v = len(theta["head"])
    return by_counts(theta, x, np.bincount(at * v + toks[1:], minlength=len(x) * v).reshape(len(x), v) / (len(toks) - 1))


def ghost_dot(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray]) -> float:
    """The product of two gradients from their factors alone."""
    return float(((one[0] @ two[0].T) * (one[1] @ two[1].T)).sum())
