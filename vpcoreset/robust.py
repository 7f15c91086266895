"""Robust coresets: cost on what is left when a small share of rows is set aside, for a given probe.

The set to leave out is existential; the witness tried here holds the rows of the largest cost under the probe, as many as both
shares (of all rows, and of the draws) allow. A success proves the property for the probe, a failure decides nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def order_statistic(rows: DataFrame, col: str, rank: int, few: int = 100_000) -> float:
    """The value of a rank (0: the least) among the non-null values, exactly.

    Sketches of quantiles narrow a band around it, which is counted exactly each time, until it holds few values; those are sorted
    on the driver. No task ever holds all values.
    """
    values = rows.where(F.col(col).isNotNull()).select(F.col(col).cast("double").alias("v"))
    below, band, size = 0, values, values.count()
    if not 0 <= rank < size:
        raise ValueError("no such rank")
    while size > few:
        share, slack = (rank - below) / size, 0.01
        low, high = band.agg(F.percentile_approx("v", [max(0.0, share - slack), min(1.0, share + slack)], F.lit(10_000)).alias("q")).collect()[0]["q"]
        c = band.agg(F.sum((F.col("v") < low).cast("long")).alias("less"), F.sum((F.col("v") <= high).cast("long")).alias("upto")).collect()[0]
        inside = c["less"] <= rank - below < c["upto"]
        if low == high and inside:
            return float(low)
        if not inside or c["upto"] - c["less"] >= size:  # many ties: cut at one value
            low = high = band.agg(F.percentile_approx("v", share, F.lit(10_000)).alias("q")).collect()[0]["q"]
            c = band.agg(F.sum((F.col("v") < low).cast("long")).alias("less"), F.sum((F.col("v") <= low).cast("long")).alias("upto")).collect()[0]
            if c["less"] <= rank - below < c["upto"]:
                return float(low)
            if rank - below < c["less"]:
                band, size = band.where(F.col("v") < low), c["less"]
            else:
                band, size, below = band.where(F.col("v") > low), size - c["upto"], below + c["upto"]
            continue
        band, size, below = band.where((F.col("v") >= low) & (F.col("v") <= high)), c["upto"] - c["less"], below + c["less"]
    return float(sorted(r["v"] for r in band.collect())[rank - below])


def largest_costs(rows: DataFrame, cost: Column, beta: float) -> DataFrame:
    """Rows with their cost and whether they belong to the beta share of largest costs; ties with the largest cost that stays, stay."""
    costed = rows.withColumn("cost", cost)
    n = costed.count()
    keep = int(beta * n)
    if not keep:
        return costed.withColumn("outlier", F.lit(False))
    return costed.withColumn("outlier", F.col("cost") > F.lit(order_statistic(costed, "cost", n - keep - 1)))


def robust_check(marked: DataFrame, sample: DataFrame, beta: float, eps: float, penalty: float = 0.0) -> dict:
    """marked: (id, cost, outlier) of all rows; sample: (id, draws, weight). Both shares, the error, and whether it holds."""
    full = marked.agg(F.sum("cost").alias("all"), F.sum(F.when(~F.col("outlier"), F.col("cost")).otherwise(0.0)).alias("kept"), F.count(F.lit(1)).alias("n"), F.sum(F.col("outlier").cast("long")).alias("out")).collect()[0]
    s = sample.join(marked, "id").agg(
        F.sum(F.when(~F.col("outlier"), F.col("weight") * F.col("cost")).otherwise(0.0)).alias("kept"), F.sum("draws").alias("m"),
        F.sum(F.col("outlier").cast("long") * F.col("draws")).alias("out")).collect()[0]
    error = abs((s["kept"] or 0.0) - full["kept"]) / max(full["all"] + penalty, 1e-300)
    shares = (full["out"] / full["n"], (s["out"] or 0) / s["m"])
    return {"share_rows": shares[0], "share_draws": shares[1], "error": error, "holds": max(shares) <= beta and error <= eps}
