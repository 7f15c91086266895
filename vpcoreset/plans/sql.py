"""Names for spark.sql: functions and temporary views of a dataset and its sample."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from vpcoreset.functions.rng import u52_py
from vpcoreset.parties import VerticalDataset
from vpcoreset.sampling import Coreset


@F.udtf(returnType="draw_no: int, threshold: long")
class DrawStream:
    """Thresholds of m draws below a total."""

    def eval(self, seed: str, m: int, total: int):
        for r in range(m):
            yield r, (u52_py(seed, "row", 0, r) * total) >> 52


def register(spark: SparkSession, ds: VerticalDataset | None = None, scores=None, sample: Coreset | None = None) -> None:
    """SQL functions vp_u52, vp_dot, vp_sqdist, vp_leverage (of a row and the columns of a whitener) and vp_draws, and views vp_party_j, vp_scores and vp_coreset."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vp_u52(text STRING) RETURNS BIGINT RETURN CAST(conv(substr(md5(text), 1, 13), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vp_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vp_sqdist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vp_leverage(x ARRAY<DOUBLE>, columns ARRAY<ARRAY<DOUBLE>>) RETURNS DOUBLE RETURN aggregate(transform(columns, c -> aggregate(zip_with(x, c, (a, b) -> a * b), 0D, (s, v) -> s + v)), 0D, (s, t) -> s + t * t)")
    spark.udtf.register("vp_draws", DrawStream)
    for j, p in enumerate(ds.parties if ds else ()):
        p.block().createOrReplaceTempView(f"vp_party_{j + 1}")
    if scores is not None:
        scores.createOrReplaceTempView("vp_scores")
    if sample is not None:
        sample.df.createOrReplaceTempView("vp_coreset")
