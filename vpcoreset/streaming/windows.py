"""Streams of rows: window statistics, samples of windows, merge-and-reduce, and a one-pass reservoir.

A coreset of a coreset is again one, with errors compounding, and coresets of disjoint rows add up; so each micro-batch (or closed
window) is sampled by itself, and samples are merged and sampled again by their weights.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from vpcoreset.functions.rng import u52, u52_py
from vpcoreset.linalg import gram, whitener
from vpcoreset.functions import vectors
from vpcoreset.sampling import two_level_sample
from vpcoreset.sources.io import shared_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    """Events as a stream with a watermark on their time."""
    raw = spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/event[s].parquet")
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def run_once(stream: DataFrame, mode: str, sink: Callable[[DataFrame, int], None] | None = None, name: str = "stream") -> DataFrame:
    """Runs over what is there now, restartable from its checkpoint; returns the last (complete) or all (append, update) rows written."""
    spark = stream.sparkSession
    path, checkpoint = shared_path(spark, name), shared_path(spark, f"{name}-checkpoint")
    run_from(stream, mode, checkpoint, sink or epoch_sink(path, mode))
    return None if sink else read_epochs(spark, path, stream, mode)


def epoch_sink(path: str, mode: str) -> Callable[[DataFrame, int], None]:
    """Writes a batch to the folder of its number, so a batch that is run again replaces itself; complete results replace each other."""
    return lambda df, epoch: df.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/epoch={epoch}")


def run_from(stream: DataFrame, mode: str, checkpoint: str, sink: Callable[[DataFrame, int], None]) -> None:
    """Runs over what is new since the checkpoint, and ends."""
    stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", checkpoint).foreachBatch(sink).start().awaitTermination()


def read_epochs(spark: SparkSession, path: str, stream: DataFrame, mode: str) -> DataFrame:
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(path)
    return spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("epoch", T.IntegerType())])).parquet(path).select(*stream.columns)


def tumbling(stream: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """Count and Gram terms of (1, value) for each window: the sufficient statistics of a party."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = stream.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("s"), F.sum(F.col("value") * F.col("value")).alias("ss"))
    return out.select(F.unix_seconds("w.start").alias("start"), "n", "s", "ss")


def user_sessions(stream: DataFrame, gap: str) -> DataFrame:
    out = stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select("user_id", F.unix_seconds("w.start").alias("start"), "n")


def frozen_scores(stream: DataFrame, sample: DataFrame, cols: list[str], n: float) -> DataFrame:
    """Leverages of a stream's rows under a whitener fitted once on a batch: stateless."""
    white = whitener(gram(sample, cols)[0])
    return stream.withColumn("score", vectors.sq_norm_after([F.col(c) for c in cols], white) + F.lit(1.0 / n))


def batch_sample(rows: DataFrame, cols: list[str], m: int, seed: str, weight: str | None = None) -> DataFrame:
    """(id, weight) sample of a bounded set of (weighted) rows; weights of the input multiply."""
    g, n = gram(rows, cols, weight)
    w = F.col(weight) if weight else F.lit(1.0)
    score = w * vectors.sq_norm_after([F.col(c) for c in cols], whitener(g)) + w / F.lit(n)
    drawn = two_level_sample(rows.select("id", F.lit(0).alias("party"), score.alias("score")), m, seed).df.select("id", "draws", "weight")
    out = drawn.join(rows.select("id", *cols, w.alias("__w")), "id")
    return out.select("id", *cols, (F.col("weight") * F.col("__w")).alias("weight"), "draws")


def window_coresets(stream: DataFrame, cols: list[str], m: int, path: str) -> None:
    """A sample of every micro-batch, written as (batch, id, columns, weight, draws)."""

    def sink(df: DataFrame, epoch: int) -> None:
        if df.limit(1).count():
            batch_sample(df, cols, m, f"batch-{epoch}").withColumn("batch", F.lit(epoch)).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    run_once(stream, "append", sink)


def closed_window_samples(stream: DataFrame, cols: list[str], m: int, width: str, seed: str = "window") -> DataFrame:
    """(start, rows, id, draws, weight): a sample of m draws of the rows of every window, once its time has passed.

    A window's rows are its state until the watermark closes it; then one task scores and samples it by itself. Scores and draws are
    those of the three rounds with one party, on exact quanta.
    """
    row = F.struct("id", *cols)
    closed = stream.groupBy(F.window("ts", width).alias("w")).agg(F.collect_list(row).alias("rows")).select(F.unix_seconds("w.start").alias("start"), "rows")

    def sample(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for start, rows in zip(batch["start"], batch["rows"], strict=True):
                rows = sorted(rows, key=lambda r: (u52_py(r["id"]), r["id"]))
                x = np.array([[r[c] for c in cols] for r in rows], float)
                q = np.maximum(1, np.rint(((x @ whitener(x.T @ x)) ** 2).sum(1) * 2.0**40 + 2.0**40 / len(rows)).astype(np.int64))
                upto = np.cumsum(q)
                drawn = np.searchsorted(upto, [(u52_py(seed, start, r) * int(upto[-1])) >> 52 for r in range(m)], "right")
                at, n = np.unique(drawn, return_counts=True)
                yield pd.DataFrame({"start": start, "rows": len(rows), "id": [rows[i]["id"] for i in at], "draws": n, "weight": n * float(upto[-1]) / (m * q[at])})

    return closed.mapInPandas(sample, "start long, rows long, id long, draws long, weight double")


def reservoir(stream: DataFrame, k: int, seed: str = "reservoir", groups: int = 16) -> DataFrame:
    """k rows by the largest priorities ln(u) / score, without replacement: a one-pass variant, not the three-round sampler.

    Groups of ids each keep k rows as state, whatever the number of rows; the k largest of all groups are the sample.
    """
    keyed = stream.select(F.pmod(F.xxhash64("id"), F.lit(groups)).alias("grp"), "id", (F.log((u52(seed, F.col("id")) + 0.5) / F.lit(float(1 << 52))) / F.col("score")).alias("priority"))

    def keep(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, pri = (list(x) for x in state.get) if state.exists else ([], [])
        for b in batches:
            ids += b["id"].tolist()
            pri += b["priority"].tolist()
        top = sorted(zip(pri, ids, strict=True), key=lambda x: (-x[0], x[1]))[:k]
        state.update(([i for _, i in top], [p for p, _ in top]))
        yield pd.DataFrame({"grp": [key[0]] * len(top), "id": [i for _, i in top], "priority": [p for p, _ in top]})

    return keyed.groupBy("grp").applyInPandasWithState(keep, "grp long, id long, priority double", "ids array<long>, priorities array<double>", "update", GroupStateTimeout.NoTimeout)
