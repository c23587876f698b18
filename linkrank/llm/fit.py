"""Logistic calibration on bounded training features."""

from __future__ import annotations

import numpy as np


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -700, 700)))


def logistic(x: np.ndarray, y: np.ndarray, odds: float | None = None) -> tuple[float, float]:
    """Slope and shift of P(y = 1) = sigmoid(slope * x + shift), by Newton's method.

    Targets are drawn in from 0 and 1 by the class sizes, so that separable classes
    have a finite fit. ``odds`` moves the shift to a population whose class 1 has these
    log-odds. Without both classes: slope 0 and the class's smoothed log-odds.
    """
    n1, n0 = float((y == 1).sum()), float((y == 0).sum())
    base = float(np.log((n1 + 1) / (n0 + 1)))
    if not n1 or not n0 or np.ptp(x) == 0:
        return 0.0, base if odds is None else odds
    middle, spread = float(x.mean()), float(x.std())
    z = (x - middle) / spread
    t = np.where(y == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    design = np.stack([z, np.ones_like(z)], axis=1)
    beta = np.array([0.0, base])
    for _ in range(60):
        p = sigmoid(design @ beta)
        w = np.maximum(p * (1 - p), 1e-9)
        hessian = (design * w[:, None]).T @ design + np.diag([1e-6, 1e-6])
        step = np.linalg.solve(hessian, design.T @ (t - p) - 1e-6 * beta)
        size = float(np.abs(step).max())
        beta = beta + step * min(1.0, 2.0 / max(size, 1e-12))
        if size < 1e-8:
            break
    return float(beta[0] / spread), float(beta[1] - beta[0] * middle / spread) + (0.0 if odds is None else odds - base)
