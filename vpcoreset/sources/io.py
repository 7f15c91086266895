"""Party sources, co-located parties, sinks, and tables in the shared folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "csv", "json", "orc")


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder that the session names; without one, a temporary folder in local mode and an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isEmpty():
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="vpcoreset-"))
            held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get()
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts the plan, and survives lost executors."""
    path = shared_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_party(spark: SparkSession, path: str, features: list[str], id_col: str, fmt: str = "parquet", schema: str | None = None) -> DataFrame:
    """id and the party's own columns; other columns are never read from columnar files."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    reader = spark.read.schema(schema) if schema else spark.read
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path).select(F.col(id_col).alias("id"), *features)


def read_table(spark: SparkSession, name: str, features: list[str], id_col: str) -> DataFrame:
    return spark.table(name).select(F.col(id_col).alias("id"), *features)


def write_read(df: DataFrame, fmt: str) -> DataFrame:
    """Round trip through a format, with the schema declared."""
    path = shared_path(df.sparkSession, fmt)
    writer = df.write.option("header", True) if fmt == "csv" else df.write
    writer.format(fmt).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def bucket_parties(tables: dict[str, DataFrame], buckets: int) -> dict[str, DataFrame]:
    """Parties as tables bucketed and sorted by id: later joins on id need no exchange."""
    out = {}
    for name, df in tables.items():
        df.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(name)
        out[name] = df.sparkSession.table(name)
    return out


def write_coreset(df: DataFrame, path: str, mode: str = "error") -> None:
    (df.write.mode(mode).partitionBy("replicate") if "replicate" in df.columns else df.write.mode(mode)).parquet(path)


def write_report(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "error") -> None:
    df.write.mode(mode).format(fmt).save(path)
