"""Column-split incremental gradients with a table of one scalar a row.

A step takes one row; each party sends its partial inner product, the server returns the residual's change, and each
party updates its own block: 2 T units. The table keeps the last residual gradient of each row and the mean
gradient of each block.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SagaResult:
    theta: np.ndarray
    steps: int
    converged: bool
    gradient: float


def saga(x: np.ndarray, y: np.ndarray, w: np.ndarray, l2: float, *, seed: int = 0, passes: int = 200, tol: float = 1e-3) -> SagaResult:
    """Minimises sum w (x theta - y)^2 + l2 |theta|^2, the mean form scaled by the total weight; stops on the gradient's norm."""
    n, d = x.shape
    total = w.sum()
    c = n * w / total
    shrink = l2 / total
    size = 1 / (3 * (2 * (c * (x * x).sum(1)).max() + 2 * shrink))
    rng = np.random.default_rng(seed)
    theta, table, mean = np.zeros(d), np.zeros(n), np.zeros(d)
    begin = np.linalg.norm(2 * ((c * -y) @ x) / n) or 1.0
    for done in range(passes):
        for i in rng.integers(0, n, n):
            new = 2 * c[i] * (x[i] @ theta - y[i])
            change = new - table[i]
            theta = (theta - size * (change * x[i] + mean)) / (1 + 2 * size * shrink)
            table[i] = new
            mean = mean + change * x[i] / n
        norm = np.linalg.norm(2 * ((c * (x @ theta - y)) @ x) / n + 2 * shrink * theta) / begin
        if norm < tol:
            return SagaResult(theta, (done + 1) * n, True, float(norm))
    return SagaResult(theta, passes * n, False, float(norm))


def saga_blocks(df: DataFrame, features: Sequence[str], label: str, l2: float, *, blocks: int = 256, passes: int = 3, tol: float = 1e-3, seed: int = 0) -> SagaResult:
    """The same on all rows of a table, a step taking one of ``blocks`` hash blocks of rows instead of one row.

    The gradient of a block is affine in theta, so its Gram matrix stands for its rows: one scan brings ``blocks`` matrices of
    (d+1)^2 numbers to the server, whatever the number of rows, and the steps follow there. The protocol that is
    simulated sends the partial products of a block's rows in each step: 2 T units a row, 2 T n a pass.
    """
    cols, d = [*features, label], len(features)
    pairs = [(i, j) for i in range(d + 1) for j in range(i, d + 1)]
    rows = df.groupBy(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("block")).agg(
        F.count(F.lit(1)).alias("n"), *[F.sum(F.col(cols[i]) * F.col(cols[j])).alias(f"g{i}_{j}") for i, j in pairs]).collect()
    rows = sorted(rows, key=lambda r: r["block"])
    g = np.zeros((len(rows), d + 1, d + 1))
    for k, r in enumerate(rows):
        for i, j in pairs:
            g[k, i, j] = g[k, j, i] = r[f"g{i}_{j}"]
    n, b = sum(r["n"] for r in rows), len(rows)
    # Component k is b / n times the block's sum, so that the components' mean is the mean over rows.
    a, c = g[:, :d, :d] * (b / n), g[:, :d, d] * (b / n)
    shrink = l2 / n
    size = 1 / (3 * (2 * np.linalg.norm(a, 2, (1, 2)).max() + 2 * shrink))
    rng = np.random.default_rng(seed)
    theta, table, mean = np.zeros(d), np.zeros((b, d)), np.zeros(d)
    begin = np.linalg.norm(2 * c.mean(0)) or 1.0
    norm = 1.0
    for done in range(passes):
        for k in rng.integers(0, b, b):
            new = 2 * (a[k] @ theta - c[k])
            theta = (theta - size * (new - table[k] + mean)) / (1 + 2 * size * shrink)
            mean = mean + (new - table[k]) / b
            table[k] = new
        norm = float(np.linalg.norm(2 * (a.mean(0) @ theta - c.mean(0)) + 2 * shrink * theta) / begin)
        if norm < tol:
            return SagaResult(theta, (done + 1) * n, True, norm)
    return SagaResult(theta, passes * n, False, norm)


def saga_many(x: np.ndarray, y: np.ndarray, w: np.ndarray, l2: float, *, seed: int = 0, passes: int = 200, tol: float = 1e-3) -> list[SagaResult]:
    """``saga`` on several samples of the same size at once, steps in lockstep: x (samples, rows, d), y and w (samples, rows)."""
    s, n, d = x.shape
    total = w.sum(1)
    c = n * w / total[:, None]
    shrink = l2 / total
    size = 1 / (3 * (2 * (c * (x * x).sum(2)).max(1) + 2 * shrink))
    rng = np.random.default_rng(seed)
    theta, table, mean = np.zeros((s, d)), np.zeros((s, n)), np.zeros((s, d))
    begin = np.linalg.norm(2 * np.einsum("sn,snd->sd", c * -y, x) / n, axis=1)
    begin[begin == 0] = 1.0
    out: list[SagaResult | None] = [None] * s
    norm, shrunk = np.ones(s), 1 / (1 + 2 * size * shrink)
    for done in range(passes):
        for i in rng.integers(0, n, n).tolist():
            row = x[:, i]
            new = 2 * c[:, i] * ((row * theta).sum(1) - y[:, i])
            change = (new - table[:, i])[:, None] * row
            theta = (theta - size[:, None] * (change + mean)) * shrunk[:, None]
            table[:, i] = new
            mean = mean + change / n
        residual = c * (np.einsum("snd,sd->sn", x, theta) - y)
        norm = np.linalg.norm(2 * np.einsum("sn,snd->sd", residual, x) / n + 2 * shrink[:, None] * theta, axis=1) / begin
        for k in np.flatnonzero(norm < tol):
            out[k] = out[k] or SagaResult(theta[k].copy(), (done + 1) * n, True, float(norm[k]))
        if all(out):
            break
    return [r or SagaResult(theta[k], passes * n, False, float(norm[k])) for k, r in enumerate(out)]
