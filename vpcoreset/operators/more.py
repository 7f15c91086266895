"""Further relational operators on their natural tables, each with its SQL twin."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from vpcoreset import robust, scores
from vpcoreset.linalg import gram, whitener
from vpcoreset.operators.queries import _R6, _events, _t, query
from vpcoreset.oracles import Chain, columns, gauss
from vpcoreset.parties import dataset
from vpcoreset.plans.methods import _BY_PHASE, _docs_ledger, _messages
from vpcoreset.plans.sql import register
from vpcoreset.sources.io import read_table, shared_path, write_report


@query("op_table_source", "SELECT count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer")
def op_table_source(spark, d):
    """A party from a catalogue table."""
    _t(spark, d, "customer").write.mode("overwrite").saveAsTable("vp_customer")
    party = read_table(spark, "vp_customer", ["c_acctbal"], "c_custkey")
    return party.agg(F.count("id").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("op_report_sink", _messages(_BY_PHASE, "strict"))
def op_report_sink(spark, d):
    """A ledger written as a report in three formats and read back; all agree."""
    rows = _docs_ledger(spark, d, "strict").to_df(spark)
    out = None
    for fmt in ("parquet", "csv", "json"):
        path = shared_path(spark, f"report-{fmt}")
        write_report(rows, path, fmt)
        back = spark.read.schema(rows.schema).format(fmt).load(path)
        out = back if out is None else out.unionByName(back)
    return out.groupBy("phase").agg((F.sum("units") / 3).cast("long").alias("units"))


@query("op_lateral_join", "SELECT o_orderpriority, replicate, count(*) AS n FROM orders, (SELECT unnest(range(3)) AS replicate) WHERE replicate < o_orderkey % 3 + 1 GROUP BY 1, 2")
def op_lateral_join(spark, d):
    """Each row with a number of replicates of its own, by a correlated table function."""
    o = _t(spark, d, "orders").select("o_orderkey", "o_orderpriority")
    tvf = spark.tvf.explode(F.sequence(F.lit(0).cast("long"), F.col("o_orderkey").outer() % 3)).toDF("replicate")
    return o.lateralJoin(tvf).groupBy("o_orderpriority", "replicate").agg(F.count(F.lit(1)).alias("n"))


@query("op_approx_distinct", "SELECT count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem")
def op_approx_distinct(spark, d):
    """The exact count, and whether the sketch is within three of its standard errors (2 %)."""
    li = _t(spark, d, "lineitem").agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("sketch"))
    return li.select("exact", (F.abs(F.col("sketch") / F.col("exact") - 1) <= 0.06).alias("near"))


@query("op_regression_stats", """
WITH s AS (SELECT avg(l_extendedprice) AS m FROM lineitem),
c AS (SELECT power(l_extendedprice - m, 2) AS m2, power(l_extendedprice - m, 3) AS m3, power(l_extendedprice - m, 4) AS m4 FROM lineitem, s)
SELECT (SELECT round(regr_slope(l_extendedprice, l_quantity), 4) FROM lineitem) AS slope, (SELECT round(regr_intercept(l_extendedprice, l_quantity), 2) FROM lineitem) AS intercept,
       (SELECT round(regr_r2(l_extendedprice, l_quantity), 6) FROM lineitem) AS r2, round(avg(m3) / power(avg(m2), 1.5), 6) AS skewness, round(avg(m4) / power(avg(m2), 2) - 3, 6) AS kurtosis FROM c""")
def op_regression_stats(spark, d):
    y, x = F.col("l_extendedprice"), F.col("l_quantity")
    return _t(spark, d, "lineitem").agg(
        F.round(F.regr_slope(y, x), 4).alias("slope"), F.round(F.regr_intercept(y, x), 2).alias("intercept"), _R6(F.regr_r2(y, x)).alias("r2"),
        _R6(F.skewness(y)).alias("skewness"), _R6(F.kurtosis(y)).alias("kurtosis"))


@query("op_percentile_exact", "SELECT round(v, 6) AS cut, true AS sketch_near FROM (SELECT value AS v, row_number() OVER (ORDER BY value) AS pos, count(*) OVER () AS n FROM events) WHERE pos = CAST(floor(0.95 * n) AS BIGINT)")
def op_percentile_exact(spark, d):
    """An order statistic by narrowing bands, and whether the sketch of the same share is within a thousandth of the ranks."""
    e = _t(spark, d, "events").select("value")
    n = e.count()
    cut = robust.order_statistic(e, "value", int(0.95 * n) - 1, few=500)
    sketch = e.agg(F.percentile_approx("value", 0.95, F.lit(10_000)).alias("s")).collect()[0]["s"]
    off = e.where(F.col("value").between(min(cut, sketch), max(cut, sketch))).count() - 1
    return spark.createDataFrame([(round(cut, 6), off <= 0.001 * n + 1)], "cut double, sketch_near boolean")


@query("op_percent_rank", "SELECT event_id AS id, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS upto FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value)")
def op_percent_rank(spark, d):
    w = W.partitionBy("user_id").orderBy("value")
    return _events(spark, d).select("id", _R6(F.percent_rank().over(w)).alias("share"), _R6(F.cume_dist().over(w)).alias("upto"))


@query("op_first_nth", """
SELECT DISTINCT user_id, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second, last_value(value) OVER w AS last
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def op_first_nth(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    e = _t(spark, d, "events")
    return e.select("user_id", F.first_value("value").over(w).alias("first"), F.nth_value("value", 2).over(w).alias("second"), F.last_value("value").over(w).alias("last")).distinct()


@query("op_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS steps FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def op_levenshtein(spark, d):
    n = _t(spark, d, "nation")
    a, b = n.select("n_regionkey", F.col("n_nationkey").alias("i"), F.col("n_name").alias("a")), n.select("n_regionkey", F.col("n_nationkey").alias("j"), F.col("n_name").alias("b"))
    return a.join(b, "n_regionkey").where("i < j").select("a", "b", F.levenshtein("a", "b").alias("steps"))


@query("op_intervals", """
SELECT o_orderkey, CAST(epoch(o_orderdate + INTERVAL 1 MONTH - INTERVAL 36 HOUR) AS BIGINT) AS due, CAST(epoch(date_trunc('month', o_orderdate)) AS BIGINT) AS month,
       date_diff('day', CAST(date_trunc('year', o_orderdate) AS DATE), CAST(o_orderdate AS DATE)) AS day FROM orders""")
def op_intervals(spark, d):
    at = F.col("o_orderdate").cast("timestamp")
    due = at + F.expr("INTERVAL 1 MONTH") - F.expr("INTERVAL 36 HOUR")
    return _t(spark, d, "orders").select(
        "o_orderkey", F.unix_seconds(due).alias("due"), F.unix_seconds(F.date_trunc("month", at)).alias("month"), F.datediff(at.cast("date"), F.date_trunc("year", at).cast("date")).cast("long").alias("day"))


@query("op_cogroup_weights", "SELECT c_mktsegment AS segment, round(sum(c_acctbal * w) / sum(w), 4) AS mean FROM customer JOIN (SELECT o_custkey, count(*)::DOUBLE AS w FROM orders GROUP BY 1) ON c_custkey = o_custkey GROUP BY 1")
def op_cogroup_weights(spark, d):
    """Features and weights that live in two tables meet group by group; a group here is a slice of customers."""
    c = _t(spark, d, "customer").select("c_custkey", "c_mktsegment", "c_acctbal", (F.col("c_custkey") % 64).alias("slice"))
    o = _t(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).cast("double").alias("w")).withColumn("slice", F.col("o_custkey") % 64)

    def meet(features: pd.DataFrame, weights: pd.DataFrame) -> pd.DataFrame:
        both = features.merge(weights, left_on="c_custkey", right_on="o_custkey")
        both["wx"] = both["w"] * both["c_acctbal"]
        return both.groupby("c_mktsegment", as_index=False)[["wx", "w"]].sum()

    part = c.groupBy("slice").cogroup(o.groupBy("slice")).applyInPandas(meet, "c_mktsegment string, wx double, w double")
    return part.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.round(F.sum("wx") / F.sum("w"), 4).alias("mean"))


def _grouped_oracle() -> str:
    chain = Chain()
    chain.regression_scores(chain.wide("docs3"), columns("docs3"))
    c = chain.coreset(chain.draws("scores", 100, "grid", 4), 100)
    cols = ["digits", "dots", "punct"]
    chain.add("rows", f"SELECT c.replicate, z.*, c.weight FROM z JOIN {c} c USING (id)")
    t = gauss(chain, "rows", cols, "y", "1.0", "weight", by=("replicate",))
    return chain.select(" UNION ALL ".join(f"SELECT replicate, '{c}' AS feature, round(t{i}, 4) AS coef FROM {t}" for i, c in enumerate(cols)))


@query("grouped_map_solver", _grouped_oracle())
def grouped_map_solver(spark, d):
    """A solver a group: ridge on each replicate of a sample."""
    from vpcoreset.experiments import _samples, _solve_groups
    from vpcoreset.solvers.ridge import Regularizer, fit_arrays

    ds = dataset(spark, d, "docs3", standard=True)
    rows = _samples(ds, scores.score_table(ds, scores.regression_scores), (100,), 4).where("method = 'coreset'")
    found = _solve_groups(rows, ds, lambda x, y, w, s: fit_arrays(x, y, w, Regularizer(l2=1.0)))
    return spark.createDataFrame([(r, f, float(np.round(v, 4))) for _, _, r, t in found for f, v in zip(ds.features, t, strict=True)], "replicate int, feature string, coef double")


def _leverage_oracle() -> str:
    chain = Chain()
    lev = chain.leverage("s", chain.wide("docs3"), ["digits", "dots", "punct"])
    return chain.select(f"SELECT id, round(lev, 6) AS lev FROM {lev}")


@query("sql_leverage", _leverage_oracle())
def sql_leverage(spark, d):
    """Leverages from spark.sql by the registered function."""
    ds = dataset(spark, d, "docs3", standard=True)
    wide = ds.concat()
    register(spark)
    w = whitener(gram(wide, ds.features)[0])
    matrix = ", ".join(f"array({', '.join(f'{float(v)!r}D' for v in col)})" for col in w.T)
    return spark.sql(f"SELECT id, round(vp_leverage(array({', '.join(ds.features)}), array({matrix})), 6) AS lev FROM {{rows}}", rows=wide)

