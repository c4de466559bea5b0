"""Geometries of optimizers: the linear maps that turn a gradient into an update, frozen for one step.

A layer's geometry is either elementwise (plain, AdamW) or a left factor (Muon).  What doesn't depend on the candidates
(decay, the old momentum) shifts all updates alike and is left out of scores.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: The published quintic iteration.
QUINTIC = (3.4445, -4.7750, 2.0315)


def adamw_scale(beta1: float, t: int, lr: float = 1.0, boxed: bool = False) -> float:
    return lr if boxed else lr * (1 - beta1) / (1 - beta1**t)


def adamw_map(v_prev: np.ndarray, t: int, beta1: float = 0.8, beta2: float = 0.95, eps: float = 1e-8, lr: float = 1.0, form: str = "hat", boxed: bool = False) -> np.ndarray:
    """The elementwise factor at step t from the second moments of step t - 1; before any state it is the identity.

    ``form`` "hat" corrects the bias as of step t - 1; "bar" decays once more and corrects as of step t.
    """
    if t < 2:
        return np.ones_like(v_prev, float)
    v = v_prev / (1 - beta2 ** (t - 1)) if form == "hat" else beta2 * v_prev / (1 - beta2**t)
    return adamw_scale(beta1, t, lr, boxed) / (np.sqrt(v) + eps)


def muon_momentum(t: int, low: float = 0.85, high: float = 0.95, steps: int = 300) -> float:
    return low + (high - low) * min(1.0, t / steps)


def muon_lr(lr: float, rows: int, cols: int) -> float:
    return lr * max(1.0, rows / cols) ** 0.5


def muon_factor(reference: np.ndarray, steps: int = 5, coefficients: tuple[float, float, float] = QUINTIC) -> tuple[np.ndarray, bool]:
    """(S, left): the composed factor of the iteration on the normalised reference.

    It multiplies from the left if the matrix is no taller than wide, else from the right; a zero reference gives the
    identity.
    """
    left = reference.shape[0] <= reference.shape[1]
    r = reference if left else reference.T
    norm = np.linalg.norm(r)
    total = np.eye(len(r))
    if norm == 0:
        return total, left
    r, (a, b, c) = r / norm, coefficients
    for _ in range(steps):
        gram = r @ r.T
        once = a * np.eye(len(r)) + b * gram + c * gram @ gram
        total, r = once @ total, once @ r
    return total, left


@dataclass
class Geometry:
    """``apply`` maps a gradient to its update; exactly one of the two factors is set, or none for the plain one."""

    elementwise: np.ndarray | None = None
    factor: np.ndarray | None = None
    left: bool = True
    scale: float = 1.0

    def apply(self, g: np.ndarray) -> np.ndarray:
        if self.elementwise is not None:
            return self.scale * self.elementwise * g
        if self.factor is not None:
            return self.scale * (self.factor @ g if self.left else g @ self.factor)
        return self.scale * g


def plain() -> Geometry:
    return Geometry()


def adamw(state: dict, t: int, **how) -> Geometry:
    return Geometry(elementwise=adamw_map(state["v"], t, **how))


def muon(reference: np.ndarray, mu: float, steps: int = 5, coefficients=QUINTIC) -> Geometry:
    """The double-smoothed direction gives a fresh gradient the weight 1 - mu^2."""
    s, left = muon_factor(reference, steps, coefficients)
    return Geometry(factor=s, left=left, scale=1 - mu * mu)


def assign(layers: list[dict], mode: str = "hybrid") -> dict[str, str]:
    """Optimizer per layer: in hybrid mode Muon takes matrices inside blocks, AdamW embeddings, heads and vectors."""
    return {l["layer"]: "muon" if mode == "hybrid" and l["in_block"] and l["ndim"] >= 2 else "adamw" if mode in ("hybrid", "adamw") else "sgd" for l in layers}


def lr_at(t: int, total: int, lr: float = 1.0, warm_share: float = 0.01) -> float:
    warm = max(1, round(total * warm_share))
    return lr * min(1.0, t / warm)


def clip_global_norm(grads: dict[str, np.ndarray], most: float = 1.0) -> dict[str, np.ndarray]:
    norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
    return grads if norm <= most else {k: g * (most / norm) for k, g in grads.items()}


class Optimizer:
    """State and update of one layer."""

    def __init__(self, kind: str, shape: tuple[int, int], lr: float, beta1: float = 0.8, beta2: float = 0.95, eps: float = 1e-8, decay: float = 0.0, ns_steps: int = 5) -> None:
        self.kind, self.shape, self.lr, self.beta1, self.beta2, self.eps, self.decay, self.ns_steps = kind, shape, lr, beta1, beta2, eps, decay, ns_steps
        self.m, self.v, self.t = np.zeros(shape), np.zeros(shape), 0

    def geometry(self, proxy: np.ndarray | None = None, by_proxy: bool = False) -> Geometry:
        """The frozen map of the next step; Muon's reference is its smoothed direction, or a proxy gradient where that is empty or asked for."""
        t = self.t + 1
        if self.kind == "adamw":
            return adamw({"v": self.v}, t, beta1=self.beta1, beta2=self.beta2, eps=self.eps)
        if self.kind == "muon":
            mu = muon_momentum(t)
            return muon(proxy if proxy is not None and (by_proxy or not self.m.any()) else mu * mu * self.m, mu, self.ns_steps)
        return plain()

    def step(self, w: np.ndarray, g: np.ndarray, rate: float = 1.0) -> np.ndarray:
        self.t += 1
        lr = self.lr * rate
        if self.kind == "adamw":
            self.m = self.beta1 * self.m + (1 - self.beta1) * g
            self.v = self.beta2 * self.v + (1 - self.beta2) * g * g
            up = self.m / (1 - self.beta1**self.t) / (np.sqrt(self.v / (1 - self.beta2**self.t)) + self.eps)
            return w - lr * up - lr * self.decay * w
        if self.kind == "muon":
            mu = muon_momentum(self.t)
            self.m = mu * self.m + (1 - mu) * g
            q = mu * self.m + (1 - mu) * g
            s, left = muon_factor(q, self.ns_steps)
            q = q / (np.linalg.norm(q) or 1.0)
            return w - muon_lr(lr, *self.shape) * (s @ q if left else q @ s)
        return w - lr * g - lr * self.decay * w
