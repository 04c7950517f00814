"""Optimisers over numpy vectors: L-BFGS (two loops, backtracking line search, curvature guard) and gradient steps."""

from __future__ import annotations

from collections import deque
from collections.abc import Callable

import numpy as np

Fun = Callable[[np.ndarray], tuple[float, np.ndarray]]


def _direction(g: np.ndarray, pairs: deque) -> np.ndarray:
    d, kept = -g, []
    for s, y, rho in reversed(pairs):
        a = rho * (s @ d)
        kept.append(a)
        d = d - a * y
    if pairs:
        s, y, _ = pairs[-1]
        d = d * ((s @ y) / (y @ y))
    for (s, y, rho), a in zip(pairs, reversed(kept), strict=True):
        d = d + s * (a - rho * (y @ d))
    return d


def lbfgs(fun: Fun, x0: np.ndarray, m: int = 10, iters: int = 5, tol: float = 1e-9, c1: float = 1e-4) -> np.ndarray:
    x, pairs = x0.astype(float).copy(), deque(maxlen=m)
    f, g = fun(x)
    for _ in range(iters):
        if np.linalg.norm(g) <= tol:
            break
        d = _direction(g, pairs)
        slope = g @ d
        if slope >= 0:  # not a descent: start anew from the gradient
            pairs.clear()
            d, slope = -g, -(g @ g)
        t = 1.0 if pairs else min(1.0, 1.0 / max(np.linalg.norm(g), 1e-12))
        for _ in range(30):
            new_f, new_g = fun(x + t * d)
            if new_f <= f + c1 * t * slope:
                break
            t *= 0.5
        else:
            break
        s, y = t * d, new_g - g
        if s @ y > 1e-12 * np.linalg.norm(s) * np.linalg.norm(y):
            pairs.append((s, y, 1.0 / (s @ y)))
        x, f, g = x + s, new_f, new_g
    return x


def gradient_steps(fun: Fun, x0: np.ndarray, lr: float = 0.5, iters: int = 1) -> np.ndarray:
    x = x0.astype(float).copy()
    for _ in range(iters):
        x = x - lr * fun(x)[1]
    return x


def sgd(x_rows: np.ndarray, y: np.ndarray, x0: np.ndarray, lr: float = 0.1, batch: int = 16, l2: float = 0.0, order: np.ndarray | None = None) -> np.ndarray:
    """One epoch of mini-batches in a given order."""
    w, order = x0.astype(float).copy(), np.arange(len(y)) if order is None else order
    for i in range(0, len(y), batch):
        rows = order[i : i + batch]
        w = w - lr * logistic(x_rows[rows], y[rows], l2)(w)[1]
    return w


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(z / 2))


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 0.0, weight: np.ndarray | None = None) -> Fun:
    """Mean log-loss and gradient at (weights, bias); the bias isn't shrunk."""
    n = max(len(y), 1)
    weight = np.ones(len(y)) if weight is None else weight

    def fun(theta: np.ndarray) -> tuple[float, np.ndarray]:
        w, b = theta[:-1], theta[-1]
        z = x @ w + b
        loss = (weight * (np.logaddexp(0, z) - y * z)).sum() / n + 0.5 * l2 * (w @ w)
        r = weight * (sigmoid(z) - y) / n
        return float(loss), np.append(x.T @ r + l2 * w, r.sum())

    return fun


def project(delta: np.ndarray, radius: float) -> np.ndarray:
    """Onto the ball."""
    norm = np.linalg.norm(delta)
    return delta if norm <= radius or norm == 0 else delta * (radius / norm)
