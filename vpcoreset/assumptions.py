"""Diagnostics of the data assumptions and of true sensitivities; analysis only, never charged."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.functions import vectors
from vpcoreset.functions.rng import u52
from vpcoreset.linalg import gram, whitener
from vpcoreset.parties import VerticalDataset


def gamma(ds: VerticalDataset) -> float:
    """Smallest singular value of the local orthonormal bases side by side, from one joint Gram matrix."""
    cols = [c for p in ds.parties for c in p.columns]
    g, _ = gram(ds.concat(), cols)
    at, blocks = 0, []
    for p in ds.parties:
        d = len(p.columns)
        blocks.append(whitener(g[at : at + d, at : at + d]))
        at += d
    wide = np.zeros((len(cols), sum(b.shape[1] for b in blocks)))
    i = j = 0
    for b in blocks:
        wide[i : i + b.shape[0], j : j + b.shape[1]] = b
        i, j = i + b.shape[0], j + b.shape[1]
    return float(np.sqrt(max(np.linalg.eigvalsh(wide.T @ g @ wide).min(), 0.0)))


def _largest_ratios(x: np.ndarray, y: np.ndarray, cuts: list[int], best: np.ndarray) -> np.ndarray:
    """``best``, raised to the largest ratio of each party over the pairs of a row of x and another row of y.

    Matrix products find the pairs that may hold the largest one, within the bound of their rounding errors; of
    those the ratio is taken from the differences themselves.
    """
    parts = list(zip(cuts[:-1], cuts[1:], strict=True))
    slack = 4 * (x.shape[1] + 4) * np.finfo(float).eps
    d, err = [], []
    for a, b in parts:
        nx, ny = (x[:, a:b] ** 2).sum(1), (y[:, a:b] ** 2).sum(1)
        size = nx[:, None] + ny[None, :]
        d.append(size - 2 * (x[:, a:b] @ y[:, a:b].T))
        err.append(slack * size)
    full, full_err = sum(d), sum(err)
    for j, (a, b) in enumerate(parts):
        if best[j] == np.inf:
            continue
        low = np.nanmax((full - full_err) / np.maximum(d[j] + err[j], 1e-300), initial=1.0)
        with np.errstate(divide="ignore", invalid="ignore"):
            close = ~(d[j] > err[j]) | ((full + full_err) / (d[j] - err[j]) >= max(low * (1 - 1e-9), best[j]))
        at = np.flatnonzero(close)
        for k in range(0, len(at), 1 << 14):
            r, c = np.divmod(at[k : k + (1 << 14)], len(y))
            diff = (x[r] - y[c]) ** 2
            mine, all_ = diff[:, a:b].sum(1), sum(diff[:, u:v].sum(1) for u, v in parts)
            if ((mine == 0) & (all_ > 0)).any():
                best[j] = np.inf
                break
            some = mine > 0
            best[j] = max(best[j], (all_[some] / mine[some]).max(initial=1.0))
    return best


def tau(ds: VerticalDataset, share: float = 1.0, seed: str = "tau", block: int = 8_192) -> DataFrame:
    """(party, tau): largest ratio of the full to the party's squared distance over pairs of rows.

    Exact with share 1: all pairs of distinct rows, in broadcast blocks of about ``block`` rows, each of which is compared with
    the rows of its own and later blocks, so the work grows with the square of the table. Otherwise over the pairs of a hash sample
    of rows, a lower bound. Pairs with a missing value count 1, and without two rows tau is null.
    """
    from vpcoreset.sources.io import materialize

    features = ds.features
    rows = ds.concat().select("id", *[F.col(c).cast("double").alias(c) for c in features])
    if share < 1:
        rows = rows.where(u52(seed, F.col("id")) < int(share * (1 << 52)))
    spark = rows.sparkSession
    # Equal rows give ratio 1 to each other and equal ratios to all others.
    rows = materialize(rows.groupBy(*features).agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n")), "tau-rows")
    size, total = rows.agg(F.count(F.lit(1)), F.sum("n")).collect()[0]
    best = np.ones(len(ds.parties))
    cuts = np.cumsum([0, *[len(p.features) for p in ds.parties]]).tolist()
    blocks = -(-size // block)
    no = F.pmod(F.xxhash64("id"), F.lit(max(blocks, 1)))
    for at in range(blocks):
        y = spark.sparkContext.broadcast(rows.where(no == at).select(*features).toPandas().to_numpy(float))
        start = best.copy()

        def search(batches: Iterator[pd.DataFrame], y=y, start=start) -> Iterator[pd.DataFrame]:
            found = start.copy()
            for batch in batches:
                x = batch.to_numpy(float)
                for k in range(0, len(x), 256):
                    found = _largest_ratios(x[k : k + 256], y.value, cuts, found)
            yield pd.DataFrame({"at": np.arange(len(found)), "value": found})

        for r in rows.where(no >= at).select(*features).mapInPandas(search, "at int, value double").groupBy("at").agg(F.max("value").alias("value")).collect():
            best[r["at"]] = max(best[r["at"]], r["value"])
        y.destroy()
    return spark.createDataFrame([(p.name, float(t) if (total or 0) > 1 else None) for p, t in zip(ds.parties, best, strict=True)], "party string, tau double")


def sensitivity_regression(ds: VerticalDataset) -> DataFrame:
    """(id, sensitivity): leverage of the row in all columns and the label, exact without a penalty."""
    cols = [c for p in ds.parties for c in p.columns]
    wide = ds.concat()
    g, _ = gram(wide, cols)
    return wide.select("id", vectors.sq_norm_after([F.col(c) for c in cols], whitener(g)).alias("sensitivity"))


def zeta(sensitivity: DataFrame, scores: DataFrame) -> float:
    """Largest ratio of true sensitivity to the sum of local scores."""
    total = scores.groupBy("id").agg(F.sum("score").alias("score"))
    return float(sensitivity.join(total, "id").agg(F.max(F.col("sensitivity") / F.col("score"))).collect()[0][0])


def sensitivity_kmeans_bound(d2, cell, stats, alpha: float = 1.0):
    """Upper bound of the k-means sensitivity up to a constant: the local score of all columns at once."""
    from vpcoreset.scores import kmeans_score

    return kmeans_score(d2, cell, stats, alpha)
