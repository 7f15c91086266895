"""Communication ledger: what crosses between the server and a party, an integer or a real being one unit.

Policies. 'strict' follows the three rounds: T totals up, T counts down, m indices up, m*T indices down, m*T scores up;
labels of moved rows are charged. 'table' charges 3*m*T for a coreset and m*T for a uniform sample, and no labels.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "round int, phase string, src string, dst string, kind string, units long"
#: What the server may see while a sample is built.
SERVER_VIEW = ("party_total", "row_ids", "score", "masked_score")


@dataclass
class CommLedger:
    rows: list[tuple[int, str, str, str, str, int]] = field(default_factory=list)

    def record(self, round_no: int, phase: str, src: str, dst: str, kind: str, units: int) -> None:
        if "server" not in (src, dst) or src == dst:
            raise ValueError("messages pass between the server and a party")
        if units < 0:
            raise ValueError("negative units")
        self.rows.append((round_no, phase, src, dst, kind, int(units)))

    def extend(self, other: CommLedger) -> CommLedger:
        self.rows.extend(other.rows)
        return self

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)

    def total(self, phase: str | None = None) -> int:
        return sum(r[5] for r in self.rows if phase in (None, r[1]))

    def fraction(self, phase: str = "construction") -> float:
        return self.total(phase) / self.total() if self.total() else 0.0

    def rollup(self, spark: SparkSession) -> DataFrame:
        return self.to_df(spark).rollup("phase", "round").agg(F.sum("units").alias("units"))

    def unexpected(self, spark: SparkSession, allowed: Iterable[str] = SERVER_VIEW) -> DataFrame:
        """Messages to the server, during construction, of a kind that it should not see."""
        seen = self.to_df(spark).where((F.col("dst") == "server") & (F.col("phase") == "construction"))
        return seen.join(spark.createDataFrame([(k,) for k in allowed], "kind string"), "kind", "left_anti")


def construction(m: int, draws_per_party: Iterable[int], method: str, policy: str = "strict", masked: bool = False) -> CommLedger:
    """Messages of building a sample of m draws over parties 1..T."""
    out, counts = CommLedger(), list(draws_per_party)
    names = [f"p{j + 1}" for j in range(len(counts))]
    if method == "uniform":
        for p in names:
            out.record(2, "construction", "server", p, "row_ids", m)
        return out
    if method != "coreset":
        raise ValueError(method)
    if policy == "table":
        for p in names:
            out.record(2, "construction", p, "server", "row_ids", m)
            out.record(2, "construction", "server", p, "row_ids", m)
            out.record(3, "construction", p, "server", "score", m)
        return out
    for p, a in zip(names, counts, strict=True):
        out.record(1, "construction", p, "server", "party_total", 1)
        out.record(1, "construction", "server", p, "draw_count", 1)
        out.record(2, "construction", p, "server", "row_ids", a)
        out.record(2, "construction", "server", p, "row_ids", m)
        out.record(3, "construction", p, "server", "masked_score" if masked else "score", m)
    return out


def solving(method: str, rows: int, widths: list[int], k: int = 0, steps: int = 0, label: bool = False, policy: str = "strict") -> CommLedger:
    """Messages of a solver on ``rows`` rows: 'transfer', 'dimension' (column-split k-means) or 'saga'."""
    out = CommLedger()
    last = len(widths) - 1
    for j, d in enumerate(widths):
        p = f"p{j + 1}"
        if method == "transfer":
            out.record(4, "solving", p, "server", "rows", rows * (d + (label and policy == "strict" and j == last)))
        elif method == "dimension":
            out.record(4, "solving", p, "server", "cells", rows)
            out.record(4, "solving", p, "server", "centers", k * d)
        elif method == "saga":
            out.record(4, "solving", p, "server", "products", steps)
            out.record(4, "solving", "server", p, "residuals", steps)
        else:
            raise ValueError(method)
    return out
