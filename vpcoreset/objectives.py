"""Costs of models and of centres on all rows or on weighted samples, and accuracy measures."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vpcoreset.functions import vectors
from vpcoreset.linalg import gram


def residual2(features: Sequence[str], label: str, theta: Sequence[float]) -> Column:
    r = vectors.dot([F.col(c) for c in features], theta) - F.col(label)
    return r * r


def regression_costs(df: DataFrame, features: Sequence[str], label: str, thetas: Sequence[Sequence[float]], weight: str | None = None, ridge: float = 0.0) -> list[float]:
    """Sum of w (x theta - y)^2 + ridge |theta|^2 for every probe, in one pass; the penalty is never scaled."""
    w = F.col(weight) if weight else F.lit(1.0)
    row = df.agg(*[F.sum(w * residual2(features, label, t)).alias(f"c{i}") for i, t in enumerate(thetas)]).collect()[0]
    return [float(row[f"c{i}"] or 0.0) + ridge * float(np.dot(t, t)) for i, t in enumerate(thetas)]


def test_loss(df: DataFrame, features: Sequence[str], label: str, theta: Sequence[float]) -> float:
    """Mean squared residual."""
    return float(df.agg(F.avg(residual2(features, label, theta))).collect()[0][0])


def least_d2(features: Sequence[str], centers: np.ndarray) -> Column:
    return vectors.nearest([F.col(c) for c in features], np.asarray(centers, float))["d2"]


def kmeans_costs(df: DataFrame, features: Sequence[str], center_sets: Sequence[np.ndarray], weight: str | None = None) -> list[float]:
    """Sum of w times the squared distance to the nearest centre, for every set, in one pass."""
    w = F.col(weight) if weight else F.lit(1.0)
    row = df.agg(*[F.sum(w * least_d2(features, c)).alias(f"c{i}") for i, c in enumerate(center_sets)]).collect()[0]
    return [float(row[f"c{i}"] or 0.0) for i in range(len(center_sets))]


def epsilon_certificate(full: DataFrame, sample: DataFrame, cols: Sequence[str], weight: str = "weight") -> float:
    """Least eps that holds for all models: extreme generalised eigenvalues of the weighted against the full Gram matrix."""
    from vpcoreset.linalg import whitener

    g, _ = gram(full, cols)
    s, _ = gram(sample, cols, weight)
    w = whitener(g)
    value = np.linalg.eigvalsh(w.T @ s @ w)
    return float(np.abs(value - 1).max())
