"""Instances without small samples: one row that no party can tell from the others decides the cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset.parties import VerticalDataset, split_by_names


def hard_regression(spark: SparkSession, n: int, row: int) -> VerticalDataset:
    """Two columns of +1 and -1, equal but at one row; (1, -1) has cost at that row only. Local scores are all equal."""
    return hard_regression_on(spark.range(n), row)


def hard_regression_on(rows: DataFrame, row: int) -> VerticalDataset:
    """The same for the ids of a table."""
    sign = F.when(F.col("id") % 2 == 0, 1.0).otherwise(-1.0)
    df = rows.select("id", sign.alias("a"), F.when(F.col("id") == row, -sign).otherwise(sign).alias("b"))
    return split_by_names(df, [["a"], ["b"]])


def hard_kmeans(spark: SparkSession, n: int, row: int | None) -> VerticalDataset:
    """(0,0), (0,1), (1,0) in turn, and at most one (1,1); three centres are free of cost without it."""
    return hard_kmeans_on(spark.range(n), row)


def hard_kmeans_on(rows: DataFrame, row: int | None) -> VerticalDataset:
    """The same for the ids of a table."""
    a, b = F.when(F.col("id") % 3 == 2, 1.0).otherwise(0.0), F.when(F.col("id") % 3 == 1, 1.0).otherwise(0.0)
    hidden = F.col("id") == F.lit(-1 if row is None else row)
    df = rows.select("id", F.when(hidden, 1.0).otherwise(a).alias("a"), F.when(hidden, 1.0).otherwise(b).alias("b"))
    return split_by_names(df, [["a"], ["b"]])
