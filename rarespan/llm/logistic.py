"""Small logistic models for the driver: ridge by Newton steps, lasso by proximal gradient."""

from __future__ import annotations

import numpy as np


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -30, 30)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 50) -> np.ndarray:
    """Intercept and weights of a ridge-penalised logistic regression."""
    z = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(z.shape[1])
    penalty = np.full(z.shape[1], ridge)
    penalty[0] = 1e-3
    for _ in range(steps):
        p = _sigmoid(z @ w)
        gradient = z.T @ (p - y) + penalty * w
        curve = (z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty)
        move = np.linalg.solve(curve, gradient)
        w -= move
        if np.abs(move).max() < 1e-8:
            break
    return w


def fit_lasso_logistic(x: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Intercept and sparse weights: accelerated proximal gradient on mean log loss + penalty x sum of absolute weights."""
    n, k = x.shape
    bound = 0.25 * (np.linalg.norm(x, 2) ** 2 / n + 1.0) if n else 1.0
    w, b = np.zeros(k), 0.0
    v, c, t = w.copy(), b, 1.0
    for _ in range(steps):
        p = _sigmoid(x @ v + c) - y
        nw = v - (x.T @ p / n) / bound
        nw = np.sign(nw) * np.maximum(np.abs(nw) - penalty / bound, 0.0)
        nb = c - p.mean() / bound
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, c = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        if max(np.abs(nw - w).max(initial=0.0), abs(nb - b)) < 1e-7:
            w, b = nw, nb
            break
        w, b, t = nw, nb, nt
    return float(b), w
