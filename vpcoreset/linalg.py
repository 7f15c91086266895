"""Gram matrices on the cluster, small factorisations on the driver.

A d x d Gram matrix is all that leaves a block. Up to NARROW columns it is one aggregate of products; wider blocks sum
numpy partials of Arrow batches, entry by entry, with partial aggregation.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NARROW = 12
RTOL = 1e-12


def gram(block: DataFrame, cols: Sequence[str], weight: str | None = None) -> tuple[np.ndarray, float]:
    """Sum of w x x' over the rows, and the sum of w."""
    d = len(cols)
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    out = np.zeros((d, d))
    if d <= NARROW:
        row = block.agg(F.sum(w).alias("w"), *[F.sum(w * F.col(cols[i]) * F.col(cols[j])).alias(f"g{i}_{j}") for i, j in pairs]).collect()[0]
        for i, j in pairs:
            out[i, j] = out[j, i] = row[f"g{i}_{j}"] or 0.0
        return out, float(row["w"] or 0.0)

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, size = np.zeros((d, d)), 0.0
        for batch in batches:
            x, v = batch[list(cols)].to_numpy(float), batch["__w"].to_numpy(float)
            total += (x * v[:, None]).T @ x
            size += v.sum()
        yield pd.DataFrame({"at": np.arange(d * d + 1), "value": np.append(total.ravel(), size)})

    sums = block.select(*cols, w.alias("__w")).mapInPandas(partial, "at int, value double").groupBy("at").agg(F.sum("value").alias("value")).collect()
    flat = np.zeros(d * d + 1)
    for r in sums:
        flat[r["at"]] = r["value"]
    return flat[:-1].reshape(d, d), float(flat[-1])


def whitener(g: np.ndarray, ridge: float = 0.0, rtol: float = RTOL) -> np.ndarray:
    """W of d x rank with |x W|^2 = x' G^+ x; scales columns first, which leaves that value unchanged."""
    scale = np.sqrt(np.maximum(np.diag(g), 0.0))
    kept = scale > 0
    inv = np.where(kept, 1 / np.where(kept, scale, 1), 0.0)
    value, vector = np.linalg.eigh(g * inv[:, None] * inv[None, :] + np.diag(ridge * inv * inv))
    good = value > rtol * max(value.max(initial=0.0), 1e-300)
    return (vector[:, good] / np.sqrt(value[good])) * inv[:, None]


def tsqr(block: DataFrame, cols: Sequence[str]) -> np.ndarray:
    """R of a tall QR: factors of partitions, merged in a tree. For blocks whose Gram matrix would lose digits."""
    d = len(cols)
    schema = "part int, r array<double>"

    def local(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        r = np.zeros((0, d))
        for batch in batches:
            x = batch[list(cols)].to_numpy(float) if "r" not in batch else np.stack(batch["r"].to_list()).reshape(-1, d)
            r = np.linalg.qr(np.vstack([r, x]), mode="r")
        if len(r):
            yield pd.DataFrame({"part": [0], "r": [r.ravel()]})

    from vpcoreset.sources.io import materialize

    factors = materialize(block.select(*cols).mapInPandas(local, schema), "tsqr")
    n = factors.count()
    while n > 1:
        n = -(-n // 8)
        factors = factors.repartition(n).mapInPandas(local, schema)
    rows = factors.collect()
    return np.array(rows[0]["r"]).reshape(-1, d) if rows else np.zeros((0, d))
