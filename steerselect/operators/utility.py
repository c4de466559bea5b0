"""The gain of a batch on held-out text, from exact to isotropic: each form drops one thing that the one before it keeps.

Updates are linear maps of gradients, frozen for the step (``Geometry``); weights are a dict of matrices.  All forms cost
an evaluation or more for each candidate, so they serve tests and small studies; the engine uses the last one, sketched.
"""

from __future__ import annotations

import numpy as np

from . import lm_block
from .precond import Geometry

Weights = dict[str, np.ndarray]


def dot(a: Weights, b: Weights) -> float:
    return float(sum((a[k] * b[k]).sum() for k in a))


def mean_gradient(theta: Weights, batch: list[np.ndarray]) -> Weights:
    grads = [lm_block.gradient(theta, t) for t in batch]
    return {k: sum(g[k] for g in grads) / len(grads) for k in theta}


def moved(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], lr: float) -> Weights:
    """The weights after one step on the sum of the subset's gradients, all taken at ``theta``."""
    out = {k: w.copy() for k, w in theta.items()}
    for toks in subset:
        for k, g in lm_block.gradient(theta, toks).items():
            out[k] -= lr * geo[k].apply(g)
    return out


def val_loss(theta: Weights, val: list[np.ndarray]) -> float:
    return float(np.mean([lm_block.loss(theta, t) for t in val]))


def exact(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], val: list[np.ndarray], lr: float) -> float:
    """How much one step on the subset lowers the held-out loss."""
    return val_loss(theta, val) - val_loss(moved(theta, geo, subset, lr), val)


def marginal_exact(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], z: np.ndarray, val: list[np.ndarray], lr: float) -> float:
    return exact(theta, geo, [*subset, z], val, lr) - exact(theta, geo, subset, val, lr)


def _update(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], lr: float) -> Weights:
    after = moved(theta, geo, subset, lr)
    return {k: theta[k] - after[k] for k in theta}


def marginal_first_order(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], z: np.ndarray, val: list[np.ndarray], lr: float) -> float:
    """The candidate's update against the held-out gradient at the weights that the subset leads to."""
    return dot(_update(theta, geo, [z], lr), mean_gradient(moved(theta, geo, subset, lr), val))


def hessian_product(theta: Weights, val: list[np.ndarray], direction: Weights, h: float = 1e-4) -> Weights:
    """The held-out loss's Hessian times a direction, by central differences of gradients."""
    size = np.sqrt(dot(direction, direction))
    if not size:
        return {k: np.zeros_like(v) for k, v in theta.items()}
    up, down = (mean_gradient({k: v + s * h / size * direction[k] for k, v in theta.items()}, val) for s in (1, -1))
    return {k: (up[k] - down[k]) * size / (2 * h) for k in theta}


def marginal_hessian(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], z: np.ndarray, val: list[np.ndarray], lr: float) -> float:
    """The same with that gradient linearised at ``theta``: one Hessian product in place of a new model."""
    bend = hessian_product(theta, val, _update(theta, geo, subset, lr))
    g = mean_gradient(theta, val)
    return dot(_update(theta, geo, [z], lr), {k: g[k] - bend[k] for k in g})


def marginal_isotropic(theta: Weights, geo: dict[str, Geometry], subset: list[np.ndarray], z: np.ndarray, val: list[np.ndarray], lr: float, curvature: float = 1.0) -> float:
    """The same with a multiple of the identity as Hessian: alignment less overlap with what is chosen."""
    own = _update(theta, geo, [z], lr)
    return dot(own, mean_gradient(theta, val)) - curvature * dot(own, _update(theta, geo, subset, lr))


FORMS = {"first order": marginal_first_order, "hessian": marginal_hessian, "isotropic": marginal_isotropic}
