"""Masked addition of scores, and a party that lies. A simulation of the protocol; the masks are not cryptography."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MODULUS = 1 << 61


def masked_scores(quanta: DataFrame, seed: str = "mask") -> DataFrame:
    """(id, party, masked): each pair of parties shares a stream that one adds and the other subtracts, modulo 2**61."""
    parties = sorted(r["party"] for r in quanta.select("party").distinct().collect())
    total = F.col("q").cast("decimal(38,0)")
    for a, b in combinations(parties, 2):
        text = F.md5(F.concat_ws(":", F.lit(seed), F.lit(str(a)), F.lit(str(b)), F.col("id").cast("string")))
        part = lambda start, digits: F.conv(F.substring(text, start, digits), 16, 10).cast("long")
        mask = (part(1, 13) * F.lit(512) + F.shiftright(part(14, 3), 3)).cast("decimal(38,0)")  # 52 and 9 bits: uniform below the modulus
        total = total + F.when(F.col("party") == a, mask).when(F.col("party") == b, -mask).otherwise(F.lit(0).cast("decimal(38,0)"))
    m = F.lit(MODULUS).cast("decimal(38,0)")
    return quanta.select("id", "party", F.pmod(total, m).cast("decimal(38,0)").alias("masked"))


def secure_sum(quanta: DataFrame, seed: str = "mask") -> DataFrame:
    """(id, q): what the server gets by adding masked scores. With two parties or more a summand alone is uniform below the modulus for whoever lacks the masks."""
    m = F.lit(MODULUS).cast("decimal(38,0)")
    return masked_scores(quanta, seed).groupBy("id").agg(F.pmod(F.sum("masked").cast("decimal(38,0)"), m).cast("long").alias("q"))


def inflate_party(scores: DataFrame, party: int, factor: float, mode: str = "uniform") -> DataFrame:
    """A party that reports ``factor`` times its total; 'uniform' also makes its draws uniform."""
    mine = F.col("party") == party
    if mode == "uniform":
        mean = scores.where(mine).agg(F.avg("score")).collect()[0][0]
        lie = F.lit(float(mean) * factor)
    elif mode == "scaled":
        lie = F.col("score") * factor
    else:
        raise ValueError(mode)
    return scores.withColumn("score", F.when(mine, lie).otherwise(F.col("score")))
