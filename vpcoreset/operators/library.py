"""Relational operators that users of samples and ledgers need, as functions on DataFrames."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpcoreset.functions import vectors
from vpcoreset.functions.rng import bucket_of


def restrict(party: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of a party whose id is in a sample; the sample is small, and Spark checks its size before it broadcasts it."""
    return party.join(ids.select("id"), "id", "left_semi")


def missing(a: DataFrame, b: DataFrame) -> DataFrame:
    """Ids of a that b lacks."""
    return a.select("id").join(b.select("id"), "id", "left_anti")


def alignment_report(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.select("id").join(b.select(F.col("id").alias("id2")), F.col("id") == F.col("id2"), "full")
    side = F.when(F.col("id2").isNull(), "left_only").when(F.col("id").isNull(), "right_only").otherwise("both")
    return both.groupBy(side.alias("side")).agg(F.count(F.lit(1)).alias("n"))


def cdf(rows: DataFrame, value: str, buckets: int) -> DataFrame:
    """(id, bucket, lo, hi): running sums inside hash buckets; never one task for all rows."""
    run = F.sum(value).over(W.partitionBy("bucket").orderBy("id").rowsBetween(W.unboundedPreceding, 0))
    return rows.withColumn("bucket", bucket_of(F.col("id"), buckets)).withColumn("hi", run).withColumn("lo", F.col("hi") - F.col(value)).select("id", "bucket", "lo", "hi")


def range_join(intervals: DataFrame, points: DataFrame) -> DataFrame:
    """points (bucket, t) to the interval of the same bucket that holds t: an equi-join with a range condition."""
    return points.join(intervals, "bucket").where((F.col("t") >= F.col("lo")) & (F.col("t") < F.col("hi")))


def asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """For each left row the latest right value at or before it, by group: one union, one window, no inequality join.

    Both have (id, by, on); right also has value.
    """
    rows = left.select("id", by, on, F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("side"))
    rows = rows.unionByName(right.select("id", by, on, value, F.lit(0).alias("side")))
    last = F.last(value, ignorenulls=True).over(W.partitionBy(by).orderBy(on, "side", "id").rowsBetween(W.unboundedPreceding, 0))
    return rows.withColumn("last", last).where("side = 1").select("id", by, on, F.col("last").alias(value))


def interval_join(a: DataFrame, b: DataFrame, by: str, seconds: int) -> DataFrame:
    """Pairs (id, id2) of the same group with b at most so many seconds before a; equi-join on (group, slot of time).

    a and b have (id, by, sec). Each b row goes to its own slot and the next, so every pair meets exactly once.
    """
    slot = lambda c: F.floor(c / seconds)
    left = a.select(by, F.col("id"), F.col("sec"), slot(F.col("sec")).alias("slot"))
    right = b.select(by, F.col("id").alias("id2"), F.col("sec").alias("sec2"), F.explode(F.array(slot(F.col("sec")), slot(F.col("sec")) + 1)).alias("slot"))
    gap = F.col("sec") - F.col("sec2")
    return left.join(right, [by, "slot"]).where((gap >= 0) & (gap <= seconds)).select(by, "id", "id2", gap.alias("gap"))


def distances(df: DataFrame, features: Sequence[str], centers: np.ndarray) -> DataFrame:
    """(id, cell, d2) of every row and centre, without a cross join: centres are literals."""
    d = F.array(*[F.struct(F.lit(i).alias("cell"), vectors.sq_dist([F.col(c) for c in features], c).alias("d2")) for i, c in enumerate(centers)])
    return df.select("id", F.explode(d).alias("x")).select("id", "x.*")


def pairs(df: DataFrame, key: str) -> DataFrame:
    """Pairs of rows i < j; for small tables alone."""
    a, b = df.select([F.col(c).alias(f"{c}_a") for c in df.columns]), df.select([F.col(c).alias(f"{c}_b") for c in df.columns])
    return a.join(b, F.col(f"{key}_a") < F.col(f"{key}_b"))


def weighted_centroids(df: DataFrame, cell: str, cols: Sequence[str], weight: str) -> DataFrame:
    w = F.sum(weight)
    return df.groupBy(cell).agg(*[(F.sum(F.col(weight) * F.col(c)) / w).alias(c) for c in cols])


def gram_long(df: DataFrame, cols: Sequence[str], weight: str | None = None) -> DataFrame:
    """(i, j, value) of the Gram matrix, d * d rows."""
    w = F.col(weight) if weight else F.lit(1.0)
    sums = df.agg(*[F.sum(w * F.col(a) * F.col(b)).alias(f"{a}__{b}") for a in cols for b in cols])
    cells = F.array(*[F.struct(F.lit(a).alias("i"), F.lit(b).alias("j"), F.col(f"{a}__{b}").alias("value")) for a in cols for b in cols])
    return sums.select(F.explode(cells).alias("x")).select("x.*")


def top_scores(df: DataFrame, k: int, value: str, by: str | None = None) -> DataFrame:
    """k largest rows overall (a heap a task) or of each group."""
    if by is None:
        return df.orderBy(F.desc(value), "id").limit(k)
    pos = F.row_number().over(W.partitionBy(by).orderBy(F.desc(value), "id"))
    return df.withColumn("pos", pos).where(F.col("pos") <= k)


def rank_scores(df: DataFrame, value: str, by: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(F.desc(value), "id")
    tie = W.partitionBy(by).orderBy(F.desc(value))
    return df.select("id", by, F.row_number().over(w).alias("rn"), F.rank().over(tie).alias("rk"), F.dense_rank().over(tie).alias("dense"), F.ntile(10).over(w).alias("decile"))


def report(df: DataFrame, dims: Sequence[str], measure: Column, how: str = "cube") -> DataFrame:
    return getattr(df, how)(*dims).agg(measure)


def table_layout(exp: DataFrame) -> DataFrame:
    """Sizes as rows, methods as columns."""
    return exp.groupBy("size").pivot("method", ["coreset", "uniform"]).agg(F.first("avg_cost"))


def profile(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    return df.agg(*[f(c).alias(f"{k}_{c}") for c in cols for k, f in (("mean", F.avg), ("std", F.stddev_pop))], *[F.corr(a, b).alias(f"corr_{a}_{b}") for i, a in enumerate(cols) for b in cols[i + 1 :]], *[F.covar_pop(a, b).alias(f"cov_{a}_{b}") for i, a in enumerate(cols) for b in cols[i + 1 :]])


def rolling(df: DataFrame, by: str, sec: str, value: str, seconds: int) -> DataFrame:
    """Mean of the value over the last so many seconds of the group, the row included."""
    w = W.partitionBy(by).orderBy(sec).rangeBetween(-seconds, 0)
    return df.select("id", by, F.avg(value).over(w).alias("mean"))


def carry_forward(df: DataFrame, by: str, order: str, value: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(order, "id").rowsBetween(W.unboundedPreceding, 0)
    return df.select("id", by, F.last(value, ignorenulls=True).over(w).alias(value))


def sessions(df: DataFrame, by: str, sec: str, gap: int) -> DataFrame:
    """Session number of each row: a new one starts after a gap."""
    w = W.partitionBy(by).orderBy(sec, "id")
    new = F.coalesce((F.col(sec) - F.lag(sec).over(w) > gap).cast("int"), F.lit(1))
    return df.withColumn("new", new).select("id", by, F.sum("new").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("session"))


def expand_replicates(sizes: DataFrame, replicates: int) -> DataFrame:
    """(size, replicate) grid of the sizes of a table."""
    return sizes.select("size", F.explode(F.sequence(F.lit(0), F.lit(replicates - 1))).alias("replicate"))


def ridge_udaf(l2: float):
    """Grouped-aggregate fit for SQL users: features array, label, weight -> coefficients."""
    from vpcoreset.solvers.ridge import Regularizer, fit_arrays

    @F.pandas_udf("array<double>")
    def ridge_fit(x: pd.Series, y: pd.Series, w: pd.Series) -> list:
        return fit_arrays(np.stack(x.to_list()), y.to_numpy(float), w.to_numpy(float), Regularizer(l2=l2)).tolist()

    return ridge_fit


def leverage_udf(white: np.ndarray):
    """Arrow scalar function: squared length of an array column behind a whitener."""

    @F.pandas_udf("double")
    def leverage(x: pd.Series) -> pd.Series:
        return pd.Series(((np.stack(x.to_list()) @ white) ** 2).sum(1)) if len(x) else pd.Series([], dtype=float)

    return leverage
