"""Regularised least squares on sufficient statistics: exact ridge, and lasso or elastic net by coordinate descent."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from vpcoreset.linalg import gram


@dataclass(frozen=True)
class Regularizer:
    """l2 |theta|^2 + l1 |theta|_1, the same whatever the number or weight of rows."""

    l2: float = 0.0
    l1: float = 0.0

    def value(self, theta: np.ndarray) -> float:
        return float(self.l2 * theta @ theta + self.l1 * np.abs(theta).sum())


def solve_gram(g: np.ndarray, b: np.ndarray, reg: Regularizer = Regularizer(), tol: float = 1e-12, steps: int = 10_000) -> np.ndarray:
    """Minimiser of theta'G theta - 2 b'theta + penalty."""
    if not reg.l1:
        return np.linalg.lstsq(g + reg.l2 * np.eye(len(b)), b, rcond=1e-12)[0]
    theta = np.zeros(len(b))
    for _ in range(steps):
        moved = 0.0
        for j in range(len(b)):
            rest = b[j] - g[j] @ theta + g[j, j] * theta[j]
            new = np.sign(rest) * max(abs(rest) - reg.l1 / 2, 0.0) / max(g[j, j] + reg.l2, 1e-300)
            moved = max(moved, abs(new - theta[j]))
            theta[j] = new
        if moved < tol * max(1.0, np.abs(theta).max()):
            break
    return theta


def fit(df: DataFrame, features: Sequence[str], label: str, reg: Regularizer = Regularizer(), weight: str | None = None) -> np.ndarray:
    """Weighted fit; one pass over df brings a (d+1) x (d+1) matrix to the server."""
    g, _ = gram(df, [*features, label], weight)
    return solve_gram(g[:-1, :-1], g[:-1, -1], reg)


def fit_arrays(x: np.ndarray, y: np.ndarray, w: np.ndarray, reg: Regularizer = Regularizer()) -> np.ndarray:
    return solve_gram((x * w[:, None]).T @ x, (x * w[:, None]).T @ y, reg)


def optimality_gap(g: np.ndarray, b: np.ndarray, theta: np.ndarray, reg: Regularizer) -> float:
    """Largest violation of the optimality conditions, relative to the size of b."""
    grad = 2 * (g @ theta - b) + 2 * reg.l2 * theta
    gap = np.where(theta != 0, np.abs(grad + reg.l1 * np.sign(theta)), np.maximum(np.abs(grad) - reg.l1, 0.0))
    return float(gap.max() / max(np.abs(b).max(), 1.0))
