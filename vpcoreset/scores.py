"""Local scores: each party computes them from its own block; nothing is communicated."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vpcoreset.functions import vectors
from vpcoreset.linalg import gram, tsqr, whitener
from vpcoreset.parties import PartySpec, VerticalDataset, pin


def row_count(p: PartySpec) -> float:
    """Rows, or their total weight."""
    return float(p.df.agg((F.sum(F.col(p.weight).cast("double")) if p.weight else F.count(F.lit(1)).cast("double")).alias("n")).collect()[0]["n"] or 0.0)


def regression_scores(p: PartySpec, *, ridge: float = 0.0, basis: str = "gram") -> DataFrame:
    """(id, score): squared length of the row in an orthonormal basis of the block, plus its share of the rows.

    The basis is never stored: a d x rank whitener, from the Gram matrix or a tree QR, turns a row into its basis row. The
    label counts as a column of the last party's block. Weighted rows are scaled by the root of their weight.
    """
    block = p.block()
    if basis == "tsqr":
        if p.weight:
            raise ValueError("tsqr takes no weights")
        r = tsqr(block, p.columns)
        white, n = whitener(r.T @ r, ridge), row_count(p)
    else:
        g, n = gram(block, p.columns, p.weight)
        white = whitener(g, ridge)
    w = F.col(p.weight) if p.weight else F.lit(1.0)
    cols = [F.col(c) for c in p.columns]
    return block.select("id", (w * vectors.sq_norm_after(cols, white) + w / F.lit(n)).alias("score"))


@dataclass(frozen=True)
class CellStats:
    """Local clustering of a party: centres, and for each cell its size and cost."""

    centers: np.ndarray
    size: np.ndarray
    cost: np.ndarray

    @property
    def total(self) -> float:
        return float(self.cost.sum())


def assign(p: PartySpec, centers: np.ndarray) -> DataFrame:
    """The block with ``cell`` and ``d2``; ties go to the lowest centre."""
    best = vectors.nearest([F.col(c) for c in p.features], centers)
    return p.block().withColumn("best", best).select("*", F.col("best.cell").alias("cell"), F.col("best.d2").alias("d2")).drop("best")


def cell_stats(assigned: DataFrame, centers: np.ndarray, weight: str | None = None) -> CellStats:
    w = F.col(weight) if weight else F.lit(1.0)
    size, cost = np.zeros(len(centers)), np.zeros(len(centers))
    for r in assigned.groupBy("cell").agg(F.sum(w).alias("size"), F.sum(w * F.col("d2")).alias("cost")).collect():
        size[r["cell"]], cost[r["cell"]] = r["size"], r["cost"]
    return CellStats(centers, size, cost)


def kmeans_score(d2: Column, cell: Column, stats: CellStats, alpha: float = 1.0, weight: Column | None = None) -> Column:
    """Own share of the cost, the mean share of the own cell, and twice the inverse of its size; times alpha.

    Without any cost (at most k distinct points) the first two terms are zero.
    """
    full = stats.size > 0
    mean = np.where(full, stats.cost / np.where(full, stats.size, 1), 0.0) / (stats.total or 1.0)
    fixed = F.element_at(F.array(*[F.lit(float(alpha * (m + (2 / s if s else 0.0)))) for m, s in zip(mean, stats.size, strict=True)]), cell + 1)
    own = F.lit(float(alpha)) * d2 / F.lit(stats.total) if stats.total > 0 else F.lit(0.0)
    return (own + fixed) * weight if weight is not None else own + fixed


def kmeans_scores(p: PartySpec, k: int, *, clusterer: str | Callable[[PartySpec, int], np.ndarray] = "scalable", alpha: float = 1.0, iterations: int = 5, seed: str = "local", is_stored: bool = False) -> DataFrame:
    """(id, score, cell) from a local clustering of the party's features; ``is_stored``: the block is in the shared folder already."""
    from vpcoreset.solvers.kmeans import local_centers

    p = p if is_stored else pin(p)
    centers = clusterer(p, k) if callable(clusterer) else local_centers(p, k, clusterer, iterations=iterations, seed=seed)
    assigned = assign(p, centers)
    stats = cell_stats(assigned, centers, p.weight)
    return assigned.select("id", kmeans_score(F.col("d2"), F.col("cell"), stats, alpha, F.col(p.weight) if p.weight else None).alias("score"), "cell")


def score_table(ds: VerticalDataset, score: Callable[[PartySpec], DataFrame]) -> DataFrame:
    """(id, party, score) of all parties, one below the other."""
    out = None
    for j, p in enumerate(ds.parties):
        part = score(p).select("id", F.lit(j).alias("party"), "score")
        out = part if out is None else out.unionByName(part)
    return out
