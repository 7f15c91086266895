"""A party behind an endpoint, as a Python data source: rows arrive in record batches, one read task a stored file.

The endpoint here serves a folder that Spark has written: features of the parts, and a label that is a linear function of them plus
noise by hash, so that known coefficients can be recovered.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from vpcoreset.functions.rng import BITS, u52
from vpcoreset.sources.io import shared_path

#: Coefficients of the planted label.
THETA = (1.0, -2.0, 0.5)


class PartyReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        files, at = fs.FileSystem.from_uri(self.path)
        found = files.get_file_info(fs.FileSelector(at, recursive=True))
        return [InputPartition(f.path) for f in sorted(found, key=lambda f: f.path) if f.is_file and f.path.endswith(".parquet")]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow.parquet as pq
        from pyarrow import fs

        files, _ = fs.FileSystem.from_uri(self.path)
        with files.open_input_file(partition.value) as f:
            yield from pq.ParquetFile(f).iter_batches(columns=["id", "a", "b", "c", "y"])


class PartySource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vp_party"

    def schema(self) -> str:
        return "id long, a double, b double, c double, y double"

    def reader(self, schema) -> DataSourceReader:
        return PartyReader(self.options)


def planted(parts: DataFrame) -> DataFrame:
    """Features of the parts and the planted label."""
    x = [F.col("p_size") / 50.0, F.col("p_retailprice") / 2000.0, F.length("p_name") / 10.0]
    noise = 0.01 * (2 * u52("planted", F.col("p_partkey")) / F.lit(float(1 << BITS)) - 1)
    rows = parts.select(F.col("p_partkey").alias("id"), *[c.cast("double").alias(n) for n, c in zip("abc", x, strict=True)], noise.alias("noise"))
    return rows.select("id", "a", "b", "c", (THETA[0] * F.col("a") + THETA[1] * F.col("b") + THETA[2] * F.col("c") + F.col("noise")).alias("y"))


def serve(spark: SparkSession, rows: DataFrame) -> DataFrame:
    """The rows as the endpoint gives them out."""
    path = shared_path(spark, "endpoint")
    rows.write.parquet(path)
    spark.dataSource.register(PartySource)
    return spark.read.format("vp_party").option("path", path if "://" in path else f"file://{path}").load()
