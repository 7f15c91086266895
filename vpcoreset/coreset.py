"""End-to-end constructions, and the reduction: build a sample, then run any solver on it."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from vpcoreset.ledger import CommLedger, solving
from vpcoreset.parties import VerticalDataset
from vpcoreset.sampling import Coreset, two_level_sample
from vpcoreset.scores import kmeans_scores, regression_scores, score_table
from vpcoreset.solvers import ridge as ridge_solver


def regression_coreset(ds: VerticalDataset, m: int, seed: str = "reg", *, basis: str = "gram", **more) -> Coreset:
    return two_level_sample(score_table(ds, lambda p: regression_scores(p, basis=basis)), m, seed, **more)


def kmeans_coreset(ds: VerticalDataset, k: int, m: int, seed: str = "km", *, clusterer="scalable", alpha: float = 1.0, iterations: int = 5, **more) -> Coreset:
    return two_level_sample(score_table(ds, lambda p: kmeans_scores(p, k, clusterer=clusterer, alpha=alpha, iterations=iterations)), m, seed, **more)


@dataclass(frozen=True)
class Solved:
    model: np.ndarray
    ledger: CommLedger


#: Solvers with an encrypted exchange would plug in here; none is built.
Solver = Callable[[np.ndarray, np.ndarray | None, np.ndarray], np.ndarray]


def solve_on_coreset(ds: VerticalDataset, sample: Coreset, solver: Solver, *, method: str = "transfer", k: int = 0, replicate: int = 0, policy: str = "strict") -> Solved:
    """Runs solver(features, label, weights) on the rows of one replicate; at most m rows reach the server.

    Charged: the construction, the ids and weights sent to the parties (2 m T, strict policy) and the solver's messages.
    """
    rows = sample.materialize(ds).where(f"replicate = {replicate}").orderBy("id").toPandas()
    y = rows[ds.label].to_numpy(float) if ds.label else None
    ledger = CommLedger(list(sample.ledger.rows))
    if policy == "strict":
        for p in ds.parties:
            ledger.record(3, "distribution", "server", p.name, "sample", 2 * sample.m)
    ledger.extend(solving(method, sample.m, [len(p.features) for p in ds.parties], k=k, label=ds.label is not None, policy=policy))
    return Solved(solver(rows[ds.features].to_numpy(float), y, rows["weight"].to_numpy(float)), ledger)


def ridge_on(reg: ridge_solver.Regularizer) -> Solver:
    return lambda x, y, w: ridge_solver.fit_arrays(x, y, w, reg)
