"""Streaming queries over the events table, run once over what is there, against batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset.functions.rng import u52
from vpcoreset.sources.io import shared_path
from vpcoreset.streaming import windows

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str):
    def keep(f):
        QUERIES[name], ORACLES[name] = f, oracle
        return f

    return keep


_STATS = "count(*) AS n, round(sum(value), 4) AS s, round(sum(value * value), 4) AS ss"


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("start", "n", F.round("s", 4).alias("s"), F.round("ss", 4).alias("ss"))


@query("st_tumbling_stats", f"SELECT CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS start, {_STATS} FROM events GROUP BY 1")
def st_tumbling_stats(spark: SparkSession, d: str) -> DataFrame:
    return _rounded(windows.run_once(windows.tumbling(windows.read_events(spark, d), "1 hour"), "complete"))


@query("st_sliding_stats", f"SELECT CAST(floor(epoch(ts) / 1800) * 1800 - o * 1800 AS BIGINT) AS start, {_STATS} FROM events, range(2) r(o) GROUP BY 1")
def st_sliding_stats(spark: SparkSession, d: str) -> DataFrame:
    return _rounded(windows.run_once(windows.tumbling(windows.read_events(spark, d), "1 hour", "30 minutes"), "complete"))


@query("st_session_users", """
WITH e AS (SELECT user_id, epoch(ts) AS s FROM events),
m AS (SELECT *, CASE WHEN s - lag(s) OVER w < 1800 THEN 0 ELSE 1 END AS new FROM e WINDOW w AS (PARTITION BY user_id ORDER BY s)),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY s ROWS UNBOUNDED PRECEDING) AS g FROM m)
SELECT user_id, CAST(floor(min(s)) AS BIGINT) AS start, count(*) AS n FROM g GROUP BY user_id, g.g""")
def st_session_users(spark: SparkSession, d: str) -> DataFrame:
    return windows.run_once(windows.user_sessions(windows.read_events(spark, d), "30 minutes"), "complete")


def _rows(spark: SparkSession, d: str) -> DataFrame:
    e = windows.read_events(spark, d)
    return e.select(F.col("event_id").alias("id"), F.col("value"), F.get_json_object("props", "$.k").cast("double").alias("k"), F.lit(1.0).alias("one"))


_COLS = ["value", "k", "one"]


@query("st_batch_coreset", "SELECT 300 AS draws, true AS weight_near_n")
def st_batch_coreset(spark: SparkSession, d: str) -> DataFrame:
    """A sample of every micro-batch."""
    path = shared_path(spark, "window-coresets")
    windows.window_coresets(_rows(spark, d), _COLS, 300, path)
    n = spark.read.parquet(f"{d}/events.parquet").count()
    out = spark.read.parquet(path).groupBy("batch").agg(F.sum("draws").alias("draws"), F.sum("weight").alias("w"))
    return out.agg(F.min("draws").alias("draws"), (F.abs(F.sum("w") / n - 1) < 0.2).alias("weight_near_n"))


@query("st_window_coreset", """
SELECT CAST(floor(epoch(ts) / 86400) * 86400 AS BIGINT) AS start, count(*) AS n, 100 AS draws FROM events
GROUP BY 1 HAVING floor(epoch(ts) / 86400) * 86400 + 86400 <= (SELECT max(epoch(ts)) - 3600 FROM events)""".replace("HAVING floor(epoch(ts) / 86400) * 86400", "HAVING start"))
def st_window_coreset(spark: SparkSession, d: str) -> DataFrame:
    """A sample of every day that the watermark has closed; days that may still get rows are not out yet."""
    e = windows.read_events(spark, d).select(F.col("event_id").alias("id"), "ts", "value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.lit(1.0).alias("one"))
    out = windows.run_once(windows.closed_window_samples(e, _COLS, 100, "1 day"), "append")
    return out.groupBy("start").agg(F.max("rows").alias("n"), F.sum("draws").alias("draws"))


@query("st_merge_reduce", "SELECT 200 AS draws, true AS weight_near_n, true AS sum_near")
def st_merge_reduce(spark: SparkSession, d: str) -> DataFrame:
    """Samples of four slices of the rows, merged, and sampled again by weight."""
    e = spark.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), "value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.lit(1.0).alias("one"))
    merged = None
    for i in range(4):
        part = windows.batch_sample(e.where(F.pmod("id", F.lit(4)) == i), _COLS, 400, f"slice-{i}")
        merged = part if merged is None else merged.unionByName(part)
    path = shared_path(spark, "merged")
    merged.select("id", *_COLS, "weight").write.parquet(path)
    reduced = windows.batch_sample(spark.read.parquet(path), _COLS, 200, "reduce", "weight")
    full = e.agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("s")).collect()[0]
    return reduced.agg(F.sum("draws").alias("draws"), (F.abs(F.sum("weight") / full["n"] - 1) < 0.25).alias("weight_near_n"), (F.abs(F.sum(F.col("weight") * F.col("value")) / full["s"] - 1) < 0.25).alias("sum_near"))


@query("st_frozen_scores", "SELECT count(*) AS n, 4.0 AS score_sum FROM events")
def st_frozen_scores(spark: SparkSession, d: str) -> DataFrame:
    """Scores of the stream with a whitener of the batch sum to rank + 1."""
    batch = spark.read.parquet(f"{d}/events.parquet").select("value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.lit(1.0).alias("one"))
    scored = windows.run_once(windows.frozen_scores(_rows(spark, d), batch, _COLS, float(batch.count())).select("id", "score"), "append")
    return scored.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("score"), 6).alias("score_sum"))


@query("st_reservoir", "SELECT 0 AS missed")
def st_reservoir(spark: SparkSession, d: str) -> DataFrame:
    """The stream's sample is the batch's top priorities."""
    e = windows.read_events(spark, d).select(F.col("event_id").alias("id"), (F.col("value") + 1).alias("score"))
    state = windows.run_once(windows.reservoir(e, 50), "update")
    last = state.orderBy(F.desc("priority"), "id").limit(50).select("id")
    pri = F.log((u52("reservoir", F.col("event_id")) + 0.5) / F.lit(float(1 << 52))) / (F.col("value") + 1)
    want = spark.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("id"), pri.alias("p")).orderBy(F.desc("p"), "id").limit(50)
    return want.join(last, "id", "left_anti").agg(F.count(F.lit(1)).alias("missed"))


@query("st_dedup", "SELECT count(DISTINCT user_id) AS users FROM events")
def st_dedup(spark: SparkSession, d: str) -> DataFrame:
    e = windows.read_events(spark, d, "60 days").select("user_id", "ts").dropDuplicatesWithinWatermark(["user_id"])
    return windows.run_once(e, "append").agg(F.count(F.lit(1)).alias("users"))


@query("st_static_join", "SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def st_static_join(spark: SparkSession, d: str) -> DataFrame:
    users = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_nationkey")
    joined = windows.read_events(spark, d).join(users, F.col("user_id") == F.col("c_custkey"))
    return windows.run_once(joined.groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n")), "complete")


_LATE = 5_400


def _two_files(spark: SparkSession, d: str, newest_first: bool) -> tuple[str, DataFrame, DataFrame]:
    """A folder, and the events of its two files: those of the last 90 minutes and all before."""
    e = spark.read.parquet(f"{d}/events.parquet")
    cut = e.agg(F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("m")).collect()[0]["m"] - _LATE * 1_000_000
    new = F.unix_micros(F.col("ts").cast("timestamp")) >= cut
    parts = e.where(new).coalesce(1), e.where(~new).coalesce(1)
    return shared_path(spark, "arriving"), *(parts if newest_first else parts[::-1])


@query("st_late_rows", f"""
WITH e AS (SELECT *, epoch(ts) AS s, max(epoch(ts)) OVER () AS newest FROM events)
SELECT CAST(floor(s / 3600) * 3600 AS BIGINT) AS start, count(*) AS n FROM e
WHERE s >= newest - {_LATE} OR floor(s / 3600) * 3600 + 3600 > newest - 3600 GROUP BY 1""")
def st_late_rows(spark: SparkSession, d: str) -> DataFrame:
    """The newest rows arrive first and set the watermark; of the older ones that follow, those of closed windows are dropped by the stream."""
    path, first, then = _two_files(spark, d, True)
    checkpoint, out = shared_path(spark, "late-checkpoint"), shared_path(spark, "late")
    first.write.parquet(f"{path}/part=1")

    def stream() -> DataFrame:
        raw = spark.readStream.schema(windows.EVENTS).parquet(f"{path}/part=*")
        timed = raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
        return timed.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")

    windows.run_from(stream(), "update", checkpoint, windows.epoch_sink(out, "update"))
    then.write.parquet(f"{path}/part=2")
    windows.run_from(stream(), "update", checkpoint, windows.epoch_sink(out, "update"))
    return windows.read_epochs(spark, out, stream(), "update").groupBy("start").agg(F.max("n").alias("n"))


@query("st_restart", "SELECT user_id, count(*) AS n, round(sum(value), 4) AS s FROM events GROUP BY 1")
def st_restart(spark: SparkSession, d: str) -> DataFrame:
    """A query that ends, and is started again from its checkpoint when more files are there, counts every row once."""
    path, first, then = _two_files(spark, d, False)
    checkpoint, out = shared_path(spark, "restart-checkpoint"), shared_path(spark, "restart")
    for no, part in enumerate((first, then)):
        part.write.parquet(f"{path}/part={no}")
        raw = spark.readStream.schema(windows.EVENTS).parquet(f"{path}/part=*")
        sums = raw.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("s"))
        windows.run_from(sums, "complete", checkpoint, windows.epoch_sink(out, "complete"))
    return spark.read.schema(sums.schema).parquet(out)
