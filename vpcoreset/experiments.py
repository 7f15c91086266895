"""The comparison grid: {coreset, uniform} x solver x size x repeat, in one sampling pass and one grouped job each.

Rows of all samples are fetched once; every (method, size, replicate) is a group of at most m rows that is solved in a task
of its own. Costs are taken on the full (or test) rows in one pass for all models.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset import objectives
from vpcoreset.ledger import construction, solving
from vpcoreset.parties import VerticalDataset, pin, standardize
from vpcoreset.sampling import BROADCAST_IDS, sample_grid, uniform_scores
from vpcoreset.scores import kmeans_scores, regression_scores, score_table
from vpcoreset.solvers import column_split, kmeans, ridge, saga
from vpcoreset.sources.io import materialize

SCHEMA = "task string, method string, size int, avg_cost double, std_cost double, units double, construction_frac double"


def regression_test_cost(test: DataFrame, features: Sequence[str], label: str, models: list[np.ndarray]) -> list[float]:
    """Mean squared residuals of many models from one Gram matrix: no second scan for more models."""
    from vpcoreset.linalg import gram

    g, n = gram(test, [*features, label])
    return [float(np.append(t, -1.0) @ g @ np.append(t, -1.0) / n) for t in models]


def kmeans_full_cost(full: DataFrame | kmeans.Held, features: Sequence[str], models: list[np.ndarray]) -> list[float]:
    """Mean squared distances for many center sets, in one scan."""
    sums, n = kmeans.costs_many(full, features, models)
    return [s / n for s in sums]


def _solve_groups(rows: DataFrame, ds: VerticalDataset, solve) -> list[tuple[str, int, int, np.ndarray]]:
    """(method, size, replicate, model) of every group."""
    features, label = ds.features, ds.label

    def one(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        model = solve(pdf[features].to_numpy(float), pdf[label].to_numpy(float) if label else None, pdf["weight"].to_numpy(float), int(key[2]))
        return pd.DataFrame({"method": [key[0]], "size": [key[1]], "replicate": [key[2]], "model": [np.asarray(model, float).ravel()]})

    found = rows.groupBy("method", "size", "replicate").applyInPandas(one, "method string, size int, replicate int, model array<double>").collect()
    return [(r["method"], r["size"], r["replicate"], np.array(r["model"])) for r in found]


def _samples(ds: VerticalDataset, scores: DataFrame, sizes: Sequence[int], repeats: int, n: int) -> DataFrame:
    """Rows of all samples of n rows, with their features, written once for all solvers."""
    grid = sample_grid(scores, sizes, repeats, rows=n * len(ds.parties)).withColumn("method", F.lit("coreset"))
    grid = grid.unionByName(sample_grid(uniform_scores(ds), sizes, repeats, seed="grid-uniform", p=20, rows=n).withColumn("method", F.lit("uniform")))
    grid = materialize(grid, "grid")
    ids = grid.select("id").distinct()
    ids = F.broadcast(ids) if 2 * max(sizes) * repeats <= BROADCAST_IDS else ids
    return materialize(grid.join(ds.concat(ids), "id"), "samples")


def summarise(rows: list[tuple[str, str, int, float, int, float]], spark) -> DataFrame:
    """rows: (task, method, size, cost, units, fraction)."""
    df = spark.createDataFrame(rows, "task string, method string, size int, cost double, units long, frac double")
    return df.groupBy("task", "method", "size").agg(
        F.avg("cost").alias("avg_cost"), F.coalesce(F.stddev_samp("cost"), F.lit(0.0)).alias("std_cost"),
        F.avg("units").alias("units"), F.avg("frac").alias("construction_frac"))


def _units(method: str, solver: str, m: int, ds: VerticalDataset, k: int, steps: int, policy: str) -> tuple[int, float]:
    ledger = construction(m, [m] + [0] * (len(ds.parties) - 1), method, policy)
    ledger.extend(solving(solver, m, [len(p.features) for p in ds.parties], k=k, steps=steps, label=ds.label is not None, policy=policy))
    return ledger.total(), ledger.fraction()


def _saga_groups(rows: DataFrame, ds: VerticalDataset, l2: float, passes: int) -> list[tuple[str, int, int, np.ndarray]]:
    """(method, size, replicate, model and steps): the repeats of a size run in lockstep in one task, padded with rows of weight zero."""
    features, label = ds.features, ds.label

    def one(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        parts = [g.sort_values("id") for _, g in pdf.groupby("replicate")]
        n = max(map(len, parts))
        x, y, w = np.zeros((len(parts), n, len(features))), np.zeros((len(parts), n)), np.zeros((len(parts), n))
        for i, g in enumerate(parts):
            x[i, : len(g)], y[i, : len(g)], w[i, : len(g)] = g[features].to_numpy(float), g[label].to_numpy(float), g["weight"].to_numpy(float)
        found = saga.saga_many(x, y, w, l2, passes=passes)
        return pd.DataFrame({"method": key[0], "size": key[1], "replicate": [int(g["replicate"].iloc[0]) for g in parts], "model": [np.append(r.theta, [r.steps, r.converged]) for r in found]})

    found = rows.groupBy("method", "size").applyInPandas(one, "method string, size int, replicate int, model array<double>").collect()
    return [(r["method"], r["size"], r["replicate"], np.array(r["model"])) for r in found]


def regression_table(ds: VerticalDataset, sizes: Sequence[int], repeats: int, *, test_share: float = 0.1, lam: float = 0.1, solvers: Sequence[str] = ("ridge",), policy: str = "table", scaled: bool = True, passes: int = 60) -> DataFrame:
    """Test loss of the full solvers and of both samplings. ``scaled``: all columns are scaled by the statistics of the training rows alone.

    The incremental solver on all rows takes blocks of rows and as many passes as it has on samples; where it does not converge
    its cost is null.
    """
    spark = ds.parties[0].df.sparkSession
    train, test = (part.map(pin) for part in ds.split(test_share))
    if scaled:
        train, test = standardize(train, train), standardize(test, train)
    held, full = materialize(test.concat(), "test"), materialize(train.concat(), "train")
    n = full.count()
    reg = ridge.Regularizer(l2=lam * n)
    widths = [len(p.features) for p in ds.parties]
    out = []
    rows = _samples(train, score_table(train, regression_scores), sizes, repeats, n)
    for solver in solvers:
        if solver == "saga":
            whole = saga.saga_blocks(full, ds.features, ds.label, reg.l2, passes=passes)
            cost = regression_test_cost(held, ds.features, ds.label, [whole.theta])[0] if whole.converged else None
            out.append(("regression", "full+saga", n, cost, solving("saga", n, widths, steps=whole.steps, policy=policy).total(), 0.0))
            found = _saga_groups(rows, train, reg.l2, passes)
            models, steps = [m[:-2] for *_, m in found], [int(m[-2]) for *_, m in found]
        else:
            theta = ridge.fit(full, ds.features, ds.label, reg)
            out.append(("regression", "full+ridge", n, regression_test_cost(held, ds.features, ds.label, [theta])[0], solving("transfer", n, widths, label=True, policy=policy).total(), 0.0))
            found = _solve_groups(rows, train, lambda x, y, w, s: ridge.fit_arrays(x, y, w, reg))
            models, steps = [m for *_, m in found], [0] * len(found)
        for (method, size, _, _), cost, step in zip(found, regression_test_cost(held, ds.features, ds.label, models), steps, strict=True):
            units, frac = _units(method, "saga" if solver == "saga" else "transfer", size, ds, 0, step, policy)
            out.append(("regression", f"{method}+{solver}", size, cost, units, frac))
    return summarise(out, spark)


def kmeans_table(ds: VerticalDataset, k: int, sizes: Sequence[int], repeats: int, *, solvers: Sequence[str] = ("kmeans++", "dimension"), clusterer: str = "scalable", policy: str = "table", restarts: int = 3) -> DataFrame:
    """Cost per row on the full data of centres found on both samplings, beside the full solvers; the full k-means++ is the best of ``restarts`` starts."""
    spark = ds.parties[0].df.sparkSession
    ds = ds.map(pin)
    wide = materialize(ds.concat(), "wide")
    n = wide.count()
    widths = [len(p.features) for p in ds.parties]
    cuts = np.cumsum([0, *widths])
    from vpcoreset.parties import PartySpec

    whole = kmeans.hold(PartySpec("all", wide, tuple(ds.features)))
    out = []
    if "kmeans++" in solvers:
        centers = kmeans.full_centers(whole, k, restarts=restarts)
        out.append(("kmeans", "full+kmeans++", n, kmeans_full_cost(whole, ds.features, [centers])[0], solving("transfer", n, widths).total(), 0.0))
    # The local clusterings serve the column-split solver and the scores alike.
    local = {p.name: kmeans.local_centers(p, k, clusterer) for p in ds.parties}
    if "dimension" in solvers:
        centers = column_split.fit(ds, k, centers=[local[p.name] for p in ds.parties], joined=wide)
        out.append(("kmeans", "full+dimension", n, kmeans_full_cost(whole, ds.features, [centers])[0], solving("dimension", n, widths, k=k).total(), 0.0))
    rows = _samples(ds, score_table(ds, lambda p: kmeans_scores(p, k, clusterer=lambda p, k: local[p.name], is_stored=True)), sizes, repeats, n)
    for solver in solvers:
        if solver == "dimension":
            solve = lambda x, y, w, s: column_split.fit_arrays([x[:, a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)], w, k, seed=s)
        else:
            solve = lambda x, y, w, s: kmeans.fit_weighted(x, w, k, seed=s)
        found = _solve_groups(rows, ds, solve)
        costs = kmeans_full_cost(whole, ds.features, [m.reshape(-1, len(ds.features)) for *_, m in found])
        for (method, size, _, _), cost in zip(found, costs, strict=True):
            units, frac = _units(method, "dimension" if solver == "dimension" else "transfer", size, ds, k, 0, policy)
            out.append(("kmeans", f"{method}+{solver}", size, cost, units, frac))
    whole.release()
    return summarise(out, spark)


def equal_communication(table: DataFrame) -> DataFrame:
    """For each coreset row, the uniform row of the same solver with the fewest units that are no less, and both costs."""
    c = table.where(F.col("method").startswith("coreset+")).select(F.substring_index("method", "+", -1).alias("solver"), F.col("size").alias("coreset_size"), F.col("units").alias("coreset_units"), F.col("avg_cost").alias("coreset_cost"))
    u = table.where(F.col("method").startswith("uniform+")).select(F.substring_index("method", "+", -1).alias("solver"), "size", "units", "avg_cost")
    near = F.min_by(F.struct(F.col("size").alias("uniform_size"), F.col("units").alias("uniform_units"), F.col("avg_cost").alias("uniform_cost")), F.col("units"))
    return c.join(u, "solver").where("units >= coreset_units").groupBy("solver", "coreset_size", "coreset_units", "coreset_cost").agg(near.alias("u")).select("solver", "coreset_size", "coreset_units", "coreset_cost", "u.*")


def relative(table: DataFrame, d: int) -> DataFrame:
    """Of every sampled row: cost over that of the full solver, share of the rows and of the numbers that are moved, and how many times fewer units; d numbers a row."""
    full = table.where(F.col("method").startswith("full+")).select(F.substring_index("method", "+", -1).alias("solver"), F.col("size").alias("n"), F.col("avg_cost").alias("full_cost"), F.col("units").alias("full_units"))
    rows = table.where(~F.col("method").startswith("full+")).withColumn("solver", F.substring_index("method", "+", -1)).join(F.broadcast(full), "solver")
    return rows.select(
        "task", "method", "size", (F.col("avg_cost") / F.col("full_cost")).alias("cost_ratio"), (F.col("size") / F.col("n")).alias("data_fraction"),
        (F.col("units") / (F.col("n") * d)).alias("moved_fraction"), (F.col("full_units") / F.col("units")).alias("units_saved"))


def probe_errors(full: DataFrame, sample: DataFrame, features: Sequence[str], label: str, thetas: list[np.ndarray], ridge_l2: float = 0.0) -> list[float]:
    """Relative error of the weighted cost for each probe."""
    a = objectives.regression_costs(full, features, label, thetas, ridge=ridge_l2)
    b = objectives.regression_costs(sample, features, label, thetas, "weight", ridge_l2)
    return [abs(y - x) / max(x, 1e-300) for x, y in zip(a, b, strict=True)]
