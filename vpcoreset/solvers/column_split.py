"""Column-split k-means: parties cluster their blocks, and the server clusters the product grid of their cells.

Each party sends k local centres and every row's cell (n T + k d units). Rows with the same tuple of cells count as one
weighted point, the chain of the local centres; at most min(n, k^T) such points are clustered into k.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.functions import vectors
from vpcoreset.parties import PartySpec, VerticalDataset, pin
from vpcoreset.solvers.kmeans import fit_weighted, full_centers, local_centers
from vpcoreset.sources.io import materialize

#: Tuples of cells that the server takes; the number that occurs is at most the number of rows and k^T.
LOCAL = 100_000


def party_cells(ds: VerticalDataset, centers: list[np.ndarray], joined: DataFrame | None = None) -> DataFrame:
    """(id, cell_1 .. cell_T). ``joined``: the blocks of all parties side by side, where they are stored so; else the parties' cells are joined."""
    if joined is not None:
        return joined.select("id", *[vectors.nearest([F.col(f) for f in p.features], c)["cell"].alias(f"cell_{j + 1}") for j, (p, c) in enumerate(zip(ds.parties, centers, strict=True))])
    out = None
    for j, (p, c) in enumerate(zip(ds.parties, centers, strict=True)):
        cells = p.block().select("id", vectors.nearest([F.col(f) for f in p.features], c)["cell"].alias(f"cell_{j + 1}"))
        out = cells if out is None else out.join(cells, "id")
    return out


def product_grid(cells: DataFrame, parties: int, weight: str | None = None) -> DataFrame:
    """(cell_1 .. cell_T, w), one row for each tuple that occurs."""
    return cells.groupBy(*[f"cell_{j + 1}" for j in range(parties)]).agg((F.sum(weight) if weight else F.count(F.lit(1)).cast("double")).alias("w"))


def fit(ds: VerticalDataset, k: int, *, clusterer: str = "scalable", iterations: int = 5, seed: int = 0, centers: list[np.ndarray] | None = None, local: int = LOCAL, joined: DataFrame | None = None) -> np.ndarray:
    """k centres over all features, from local clusterings of all rows.

    Up to ``local`` tuples of cells are clustered on the server; more of them stay a table and are clustered there.
    """
    if centers is None:
        ds = ds.map(pin)
        centers = [local_centers(p, k, clusterer, iterations=iterations) for p in ds.parties]
    names = [f"cell_{j + 1}" for j in range(len(centers))]
    grid = materialize(product_grid(party_cells(ds, centers, joined), len(centers)), "product-grid")
    if grid.count() <= local:
        rows = grid.orderBy(*names).toPandas()
        points = np.hstack([c[rows[n].to_numpy()] for n, c in zip(names, centers, strict=True)])
        return fit_weighted(points, rows["w"].to_numpy(float), k, seed=seed)
    at, cols = F.lit(0).cast("long"), []
    for n, c, p in zip(names, centers, ds.parties, strict=True):
        at = at * len(c) + F.col(n)
        cols += [F.element_at(F.array(*[F.lit(float(x)) for x in c[:, i]]), F.col(n) + 1).alias(f) for i, f in enumerate(p.features)]
    points = PartySpec("grid", grid.select(at.alias("id"), *cols, F.col("w").alias("__w")), tuple(ds.features), weight="__w")
    return full_centers(pin(points), k, seed=f"grid-{seed}")


def fit_arrays(blocks: list[np.ndarray], w: np.ndarray, k: int, *, seed: int = 0, iterations: int = 25) -> np.ndarray:
    """The same on a weighted sample."""
    from vpcoreset.solvers.kmeans import distances

    centers = [fit_weighted(b, w, k, seed=seed + j, iterations=iterations) for j, b in enumerate(blocks)]
    cells = np.stack([distances(b, c).argmin(1) for b, c in zip(blocks, centers, strict=True)], 1)
    tuples, inverse = np.unique(cells, axis=0, return_inverse=True)
    mass = np.bincount(inverse.ravel(), w, len(tuples))
    points = np.hstack([c[tuples[:, j]] for j, c in enumerate(centers)])
    return fit_weighted(points, mass, k, seed=seed)
