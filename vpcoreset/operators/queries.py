"""One query for each operator on its natural table, each with its SQL twin."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset import coreset, sampling, scores
from vpcoreset.functions import vectors
from vpcoreset.functions.rng import u52, u52_sql
from vpcoreset.linalg import gram, whitener
from vpcoreset.operators import library as ops
from vpcoreset.oracles import Chain, gauss, unpivot
from vpcoreset.parties import check_numeric, dataset
from vpcoreset.plans.methods import M, _reg_chain, _reg_table
from vpcoreset.plans.sql import register
from vpcoreset.sources.io import bucket_parties, read_party, shared_path, write_coreset, write_read

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str):
    def keep(f):
        QUERIES[name], ORACLES[name] = f, oracle
        return f

    return keep


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _events(spark: SparkSession, d: str) -> DataFrame:
    e = _t(spark, d, "events")
    return e.select(F.col("event_id").alias("id"), "user_id", "event_type", "value", F.unix_seconds(F.col("ts").cast("timestamp")).alias("sec"))


_EV = "SELECT event_id AS id, user_id, event_type, value, CAST(floor(epoch(ts)) AS BIGINT) AS sec FROM events"
_R6 = lambda c: F.round(F.col(c) if isinstance(c, str) else c, 6)


@query("op_scan_pruned", "SELECT l_orderkey AS id, l_quantity, l_discount FROM lineitem")
def op_scan_pruned(spark, d):
    return read_party(spark, f"{d}/lineitem.parquet", ["l_quantity", "l_discount"], "l_orderkey")


@query("op_roundtrip_formats", "SELECT f.fmt, p_partkey, p_name, p_size, p_retailprice FROM part, (VALUES ('parquet'), ('csv'), ('json'), ('orc')) f(fmt)")
def op_roundtrip_formats(spark, d):
    part = _t(spark, d, "part").select("p_partkey", "p_name", "p_size", "p_retailprice")
    out = None
    for fmt in ("parquet", "csv", "json", "orc"):
        df = write_read(part, fmt).withColumn("fmt", F.lit(fmt))
        out = df if out is None else out.unionByName(df)
    return out


@query("op_coreset_sink", _reg_chain("docs", 50, "sample", 2).select("SELECT replicate, count(*) AS ids, CAST(sum(draws) AS BIGINT) AS draws FROM coreset GROUP BY 1"))
def op_coreset_sink(spark, d):
    path = shared_path(spark, "coreset")
    write_coreset(sampling.two_level_sample(_reg_table(spark, d), 50, replicates=range(2)).df, path)
    return spark.read.parquet(path).groupBy("replicate").agg(F.count(F.lit(1)).alias("ids"), F.sum("draws").alias("draws"))


@query("op_bucketed_align", "SELECT count(*) AS n, 0 AS exchanges FROM orders")
def op_bucketed_align(spark, d):
    """Two bucketed parties join without an exchange; the plan's exchanges are counted."""
    o = _t(spark, d, "orders")
    names = [f"vp_bucketed_{j}" for j in (1, 2)]
    made = bucket_parties({names[0]: o.select(F.col("o_orderkey").alias("id"), "o_totalprice"), names[1]: o.select(F.col("o_orderkey").alias("id"), "o_custkey")}, 8)
    joined = made[names[0]].hint("merge").join(made[names[1]], "id")
    plan = joined._jdf.queryExecution().executedPlan().toString()
    return joined.agg(F.count(F.lit(1)).alias("n")).withColumn("exchanges", F.lit(plan.count("Exchange hashpartitioning")))


@query("op_project_blocks", "SELECT l_orderkey AS id, 'p1' AS party, l_quantity + l_discount AS s FROM lineitem UNION ALL SELECT l_orderkey, 'p2', l_tax FROM lineitem")
def op_project_blocks(spark, d):
    from vpcoreset.parties import split_by_names

    ds = split_by_names(_t(spark, d, "lineitem").withColumnRenamed("l_orderkey", "id"), [["l_quantity", "l_discount"], ["l_tax"]])
    parts = [p.df.select("id", F.lit(p.name).alias("party"), vectors.add([F.col(c) for c in p.features]).alias("s")) for p in ds.parties]
    return parts[0].unionByName(parts[1])


@query("op_vector_blocks", "SELECT vec_id AS id, CAST((pos - 1) AS INTEGER) AS pos, CASE WHEN pos <= 22 THEN 'p1' WHEN pos <= 43 THEN 'p2' ELSE 'p3' END AS party, round(CAST(embedding[pos] AS DOUBLE), 6) AS x FROM embeddings, range(1, 65) r(pos)")
def op_vector_blocks(spark, d):
    e = _t(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.posexplode("embedding").alias("pos", "x"))
    party = F.when(F.col("pos") < 22, "p1").when(F.col("pos") < 43, "p2").otherwise("p3")
    return e.select("id", "pos", party.alias("party"), _R6(F.col("x").cast("double")).alias("x"))


@query("op_train_test", f"SELECT CAST('0x' || substr(md5(concat_ws(':', 'split', o_orderkey)), 1, 13) AS BIGINT) < {int(0.1 * (1 << 52))} AS test, count(*) AS n FROM orders GROUP BY 1")
def op_train_test(spark, d):
    test = u52("split", F.col("o_orderkey")) < int(0.1 * (1 << 52))
    return _t(spark, d, "orders").groupBy(test.alias("test")).agg(F.count(F.lit(1)).alias("n"))


@query("op_bucket_filter", "SELECT count(*) AS n, true AS pruned FROM lineitem WHERE CAST('0x' || substr(md5(CAST(l_orderkey AS VARCHAR)), 1, 13) AS BIGINT) >> 48 IN (3, 7, 12)")
def op_bucket_filter(spark, d):
    """Rows of three of sixteen buckets of a clustered table: the others' directories are not read, by the plan."""
    from vpcoreset.functions.rng import place_of

    path = shared_path(spark, "clustered")
    rows = _t(spark, d, "lineitem").select("l_orderkey", F.shiftright(place_of(F.col("l_orderkey")), 48).cast("int").alias("bucket"))
    rows.repartition("bucket").write.partitionBy("bucket").parquet(path)
    part = spark.read.parquet(path).where(F.col("bucket").isin(3, 7, 12))
    pruned = "PartitionFilters: [bucket" in part._jdf.queryExecution().sparkPlan().toString()
    return part.agg(F.count(F.lit(1)).alias("n")).withColumn("pruned", F.lit(pruned))


@query("op_null_guard", "SELECT CAST(count(*) FILTER (WHERE event_id % 10 = 0) AS BIGINT) AS v_null, CAST(count(*) FILTER (WHERE event_id % 10 = 1) AS BIGINT) AS v_odd FROM events")
def op_null_guard(spark, d):
    v = F.when(F.col("event_id") % 10 == 0, F.lit(None)).when(F.col("event_id") % 10 == 1, F.lit(float("nan"))).otherwise(F.col("value"))
    return check_numeric(_t(spark, d, "events").select(v.cast("double").alias("v")), ["v"])


@query("op_case_between_in_like", "SELECT p_partkey, CASE WHEN p_size BETWEEN 10 AND 20 THEN 'mid' WHEN p_size IN (1, 2, 3) THEN 'tiny' WHEN p_type LIKE '%STEEL%' THEN 'steel' ELSE 'rest' END AS tag FROM part")
def op_case_between_in_like(spark, d):
    tag = F.when(F.col("p_size").between(10, 20), "mid").when(F.col("p_size").isin(1, 2, 3), "tiny").when(F.col("p_type").like("%STEEL%"), "steel").otherwise("rest")
    return _t(spark, d, "part").select("p_partkey", tag.alias("tag"))


@query("op_align_inner", "SELECT count(*) AS n, round(sum(l_quantity * p_size), 3) AS s FROM lineitem JOIN part ON l_partkey = p_partkey")
def op_align_inner(spark, d):
    j = _t(spark, d, "lineitem").join(_t(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return j.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("l_quantity") * F.col("p_size")), 3).alias("s"))


@query("op_broadcast_cells", "SELECT doc_id AS id, lang, n, round(mean, 4) AS mean FROM documents JOIN (SELECT lang, count(*) AS n, avg(n_chars) AS mean FROM documents GROUP BY 1) USING (lang)")
def op_broadcast_cells(spark, d):
    """Cell statistics go back to the rows; Spark broadcasts them while they stay below its threshold."""
    docs = _t(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang", "n_chars")
    stats = docs.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.avg("n_chars").alias("mean"))
    return docs.join(stats, "lang").select("id", "lang", "n", F.round("mean", 4).alias("mean"))


@query("op_semi_sample", _reg_chain("docs").select("SELECT doc_id AS id, n_chars FROM documents WHERE doc_id IN (SELECT id FROM coreset)"))
def op_semi_sample(spark, d):
    ids = sampling.two_level_sample(_reg_table(spark, d), M).df
    return ops.restrict(_t(spark, d, "documents").select(F.col("doc_id").alias("id"), "n_chars"), ids)


_IDS = lambda spark, d, t: _t(spark, d, t).select(F.col("doc_id").alias("id"))


@query("op_anti_missing", "SELECT doc_id AS id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_anti_missing(spark, d):
    return ops.missing(_IDS(spark, d, "documents"), _IDS(spark, d, "labels"))


@query("op_full_outer_audit", "SELECT CASE WHEN l.doc_id IS NULL THEN 'left_only' WHEN d.doc_id IS NULL THEN 'right_only' ELSE 'both' END AS side, count(*) AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def op_full_outer_audit(spark, d):
    return ops.alignment_report(_IDS(spark, d, "documents"), _IDS(spark, d, "labels"))


_BUCKET = "CAST(CAST('0x' || substr(md5(CAST(id AS VARCHAR)), 1, 8) AS BIGINT) % 16 AS INTEGER)"
_CDF = f"SELECT id, {_BUCKET} AS bucket, sum(q) OVER (PARTITION BY {_BUCKET} ORDER BY id) - q AS lo, sum(q) OVER (PARTITION BY {_BUCKET} ORDER BY id) AS hi FROM (SELECT id, CAST(floor(value * 1000) + 1 AS BIGINT) AS q FROM ({_EV}))"


def _cdf(spark, d):
    return ops.cdf(_events(spark, d).select("id", (F.floor(F.col("value") * 1000) + 1).cast("long").alias("q")), "q", 16)


@query("op_running_cdf", f"SELECT id, bucket, CAST(lo AS BIGINT) AS lo, CAST(hi AS BIGINT) AS hi FROM ({_CDF})")
def op_running_cdf(spark, d):
    return _cdf(spark, d)


@query("op_range_join_cdf", f"SELECT p.t, p.bucket, c.id FROM (SELECT CAST(range % 16 AS INTEGER) AS bucket, range * 37 AS t FROM range(2000)) p JOIN ({_CDF}) c ON p.bucket = c.bucket AND p.t >= c.lo AND p.t < c.hi")
def op_range_join_cdf(spark, d):
    points = spark.range(2000).select((F.col("id") % 16).cast("int").alias("bucket"), (F.col("id") * 37).alias("t"))
    return ops.range_join(_cdf(spark, d), points).select("t", "bucket", "id")


@query("op_lag_lo_hi", f"SELECT id, CAST(coalesce(lag(hi) OVER (PARTITION BY bucket ORDER BY id), 0) AS BIGINT) AS lo FROM ({_CDF})")
def op_lag_lo_hi(spark, d):
    from pyspark.sql import Window as W

    return _cdf(spark, d).select("id", F.coalesce(F.lag("hi").over(W.partitionBy("bucket").orderBy("id")), F.lit(0)).alias("lo"))


@query("op_asof_join", f"WITH e AS ({_EV}) SELECT l.id, l.user_id, l.sec, (SELECT r.value FROM e r WHERE r.event_type = 'click' AND r.user_id = l.user_id AND r.sec <= l.sec ORDER BY r.sec DESC, r.id DESC LIMIT 1) AS value FROM e l WHERE l.event_type = 'purchase'")
def op_asof_join(spark, d):
    e = _events(spark, d)
    return ops.asof(e.where("event_type = 'purchase'"), e.where("event_type = 'click'"), "sec", "user_id", "value")


@query("op_cross_centers", "SELECT vec_id AS id, CAST(c AS INTEGER) AS cell, round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - c / 10.0) * (CAST(x AS DOUBLE) - c / 10.0))), 5) AS d2 FROM embeddings, range(10) r(c)")
def op_cross_centers(spark, d):
    e = dataset(spark, d, "emb3", label=False)
    out = ops.distances(e.concat(), e.features, np.array([[c / 10.0] * 64 for c in range(10)]))
    return out.select("id", "cell", F.round("d2", 5).alias("d2"))


@query("op_theta_pairs", "SELECT a.s_suppkey AS s_suppkey_a, b.s_suppkey AS s_suppkey_b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey")
def op_theta_pairs(spark, d):
    return ops.pairs(_t(spark, d, "supplier").select("s_suppkey"), "s_suppkey")


@query("op_star_join", "SELECT c_mktsegment, p_brand, count(*) AS n, round(sum(l_extendedprice), 2) AS revenue FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2")
def op_star_join(spark, d):
    j = _t(spark, d, "lineitem").join(_t(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey")).join(_t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    j = j.join(_t(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(_t(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return j.groupBy("c_mktsegment", "p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("revenue"))


@query("op_interval_join", f"WITH e AS ({_EV}) SELECT a.user_id, a.id, b.id AS id2, a.sec - b.sec AS gap FROM e a JOIN e b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'click' AND a.sec - b.sec BETWEEN 0 AND 86400")
def op_interval_join(spark, d):
    e = _events(spark, d)
    return ops.interval_join(e.where("event_type = 'error'"), e.where("event_type = 'click'"), "user_id", 86_400)


_DRAWS = _reg_chain("docs")


def _draws(spark, d):
    quanta = sampling.store_quanta(_reg_table(spark, d))
    return sampling.draw_rows(quanta, sampling.make_thresholds(quanta.totals, M, "sample", [0]))


@query("op_union_multiset", _DRAWS.select("SELECT id, count(*) AS n FROM draws GROUP BY 1"))
def op_union_multiset(spark, d):
    draws = _draws(spark, d)
    parts = [draws.where(F.col("party") == j).select("id") for j in range(3)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("id").agg(F.count(F.lit(1)).alias("n"))


def _both_sql(op: str) -> str:
    from vpcoreset.oracles import uniform

    chain = _reg_chain("docs")
    uniform(chain, "w", M, "uniform")
    return chain.select(f"SELECT id FROM coreset {op} SELECT id FROM ucoreset")


def _both(spark, d):
    return sampling.two_level_sample(_reg_table(spark, d), M).df.select("id"), sampling.uniform_sample(dataset(spark, d, "docs"), M).df.select("id")


@query("op_intersect_ids", _both_sql("INTERSECT"))
def op_intersect_ids(spark, d):
    a, b = _both(spark, d)
    return a.intersect(b)


@query("op_except_ids", _both_sql("EXCEPT"))
def op_except_ids(spark, d):
    a, b = _both(spark, d)
    return a.subtract(b)


@query("op_lateral_replicates", "SELECT size, CAST(r AS INTEGER) AS replicate FROM (SELECT count(*) AS size FROM lineitem GROUP BY l_linenumber), range(20) g(r)")
def op_lateral_replicates(spark, d):
    """Twenty replicates of each size, the sizes being the numbers of lines of a line number."""
    return ops.expand_replicates(_t(spark, d, "lineitem").groupBy("l_linenumber").agg(F.count(F.lit(1)).alias("size")), 20)


@query("op_collect_draws", _DRAWS.select("SELECT party, array_to_string(list(id ORDER BY id), ',') AS ids FROM draws GROUP BY 1"))
def op_collect_draws(spark, d):
    return _draws(spark, d).groupBy("party").agg(F.array_join(F.array_sort(F.collect_list("id")), ",").alias("ids"))


@query("op_distinct_ids", _DRAWS.select("SELECT count(DISTINCT id) AS ids, count(*) AS draws FROM draws"))
def op_distinct_ids(spark, d):
    return _draws(spark, d).agg(F.count_distinct("id").alias("ids"), F.count(F.lit(1)).alias("draws"))


for _how, _sql in (("cube", "CUBE"), ("rollup", "ROLLUP")):
    @query(f"op_{_how}_report", f"SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY {_sql} (l_returnflag, l_linestatus)")
    def op_report(spark, d, how=_how):
        return ops.report(_t(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], F.round(F.sum("l_quantity"), 2).alias("q"), how)


@query("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def op_grouping_sets(spark, d):
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM {t} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", t=_t(spark, d, "lineitem"))


@query("op_pivot_report", "SELECT l_linenumber AS size, round(avg(l_tax) FILTER (WHERE l_returnflag = 'A'), 6) AS coreset, round(avg(l_tax) FILTER (WHERE l_returnflag = 'R'), 6) AS uniform FROM lineitem WHERE l_returnflag IN ('A', 'R') GROUP BY 1")
def op_pivot_report(spark, d):
    li = _t(spark, d, "lineitem").where("l_returnflag IN ('A', 'R')")
    exp = li.groupBy(F.col("l_linenumber").alias("size"), F.when(F.col("l_returnflag") == "A", "coreset").otherwise("uniform").alias("method")).agg(F.round(F.avg("l_tax"), 6).alias("avg_cost"))
    return ops.table_layout(exp)


@query("op_stats_columns", "SELECT round(avg(l_quantity), 6) AS mean_l_quantity, round(stddev_pop(l_quantity), 6) AS std_l_quantity, round(avg(l_tax), 6) AS mean_l_tax, round(stddev_pop(l_tax), 6) AS std_l_tax, round(corr(l_quantity, l_tax), 6) AS corr_l_quantity_l_tax, round(covar_pop(l_quantity, l_tax), 6) AS cov_l_quantity_l_tax FROM lineitem")
def op_stats_columns(spark, d):
    out = ops.profile(_t(spark, d, "lineitem"), ["l_quantity", "l_tax"])
    return out.select(*[_R6(c).alias(c) for c in out.columns])


@query("op_percentile_cut", "SELECT round(quantile_cont(value, 0.95), 6) AS cut FROM events")
def op_percentile_cut(spark, d):
    return _t(spark, d, "events").agg(_R6(F.percentile("value", F.lit(0.95))).alias("cut"))


@query("op_outlier_filter", "SELECT event_id FROM events WHERE value <= (SELECT quantile_cont(value, 0.95) FROM events)")
def op_outlier_filter(spark, d):
    e = _t(spark, d, "events").select("event_id", "value")
    cut = e.agg(F.percentile("value", F.lit(0.95)).alias("c")).collect()[0]["c"]
    return e.where(F.col("value") <= F.lit(cut)).select("event_id")


@query("op_argmin_center", "SELECT arg_min(o_orderkey, struct_pack(v := abs(o_totalprice - 100000), k := o_orderkey)) AS nearest FROM orders")
def op_argmin_center(spark, d):
    return _t(spark, d, "orders").agg(F.min_by("o_orderkey", F.struct(F.abs(F.col("o_totalprice") - 100000), "o_orderkey")).alias("nearest"))


_GRAM_COLS = ["l_quantity", "l_discount", "l_tax"]


@query("op_gram", " UNION ALL ".join(f"SELECT '{a}' AS i, '{b}' AS j, round(sum({a} * {b}), 4) AS value FROM lineitem" for a in _GRAM_COLS for b in _GRAM_COLS))
def op_gram(spark, d):
    return ops.gram_long(_t(spark, d, "lineitem"), _GRAM_COLS).withColumn("value", F.round("value", 4))


@query("op_weighted_mean", "SELECT lang, round(sum(n_chars * doc_id) / sum(n_chars), 4) AS doc_id FROM documents GROUP BY 1")
def op_weighted_mean(spark, d):
    return ops.weighted_centroids(_t(spark, d, "documents"), "lang", ["doc_id"], "n_chars").withColumn("doc_id", F.round("doc_id", 4))


@query("op_rank_family", "SELECT doc_id AS id, lang, row_number() OVER w AS rn, rank() OVER t AS rk, dense_rank() OVER t AS dense, CAST(ntile(10) OVER w AS INTEGER) AS decile FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars DESC, doc_id), t AS (PARTITION BY lang ORDER BY n_chars DESC)")
def op_rank_family(spark, d):
    return ops.rank_scores(_t(spark, d, "documents").withColumnRenamed("doc_id", "id"), "n_chars", "lang")


@query("op_ntile_scores", "SELECT decile, count(*) AS n, CAST(max(n_chars) AS BIGINT) AS most FROM (SELECT n_chars, CAST(ntile(10) OVER (PARTITION BY source ORDER BY n_chars, doc_id) AS INTEGER) AS decile FROM documents) GROUP BY 1")
def op_ntile_scores(spark, d):
    from pyspark.sql import Window as W

    docs = _t(spark, d, "documents").select("n_chars", F.ntile(10).over(W.partitionBy("source").orderBy("n_chars", "doc_id")).alias("decile"))
    return docs.groupBy("decile").agg(F.count(F.lit(1)).alias("n"), F.max("n_chars").alias("most"))


@query("op_rolling_range", f"SELECT id, user_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 5) AS mean FROM ({_EV})")
def op_rolling_range(spark, d):
    return ops.rolling(_events(spark, d), "user_id", "sec", "value", 3600).withColumn("mean", F.round("mean", 5))


@query("op_last_non_null", f"SELECT id, user_id, last_value(p IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY sec, id ROWS UNBOUNDED PRECEDING) AS p FROM (SELECT *, CASE WHEN event_type = 'purchase' THEN value END AS p FROM ({_EV}))")
def op_last_non_null(spark, d):
    return ops.carry_forward(_events(spark, d).withColumn("p", F.when(F.col("event_type") == "purchase", F.col("value"))), "user_id", "sec", "p")


@query("op_session_gap", f"SELECT id, user_id, CAST(sum(new) OVER (PARTITION BY user_id ORDER BY sec, id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS session FROM (SELECT *, CASE WHEN sec - lag(sec) OVER (PARTITION BY user_id ORDER BY sec, id) <= 86400 THEN 0 ELSE 1 END AS new FROM ({_EV}))")
def op_session_gap(spark, d):
    return ops.sessions(_events(spark, d), "user_id", "sec", 86_400)


@query("op_order_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def op_order_limit(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


_TOP = (lambda c: (c.leverage("s", c.wide("docs3"), ["digits", "dots", "punct"]), c)[1])(type(_DRAWS)())


def _leverage(spark, d):
    ds = dataset(spark, d, "docs3", standard=True)
    wide = ds.concat()
    white = whitener(gram(wide, ds.features)[0])
    return wide.select("id", vectors.sq_norm_after([F.col(c) for c in ds.features], white).alias("lev"))


@query("op_topk_leverage", _TOP.select("SELECT id, round(lev, 6) AS lev FROM sl ORDER BY lev DESC, id LIMIT 10"))
def op_topk_leverage(spark, d):
    return ops.top_scores(_leverage(spark, d), 10, "lev").select("id", _R6("lev").alias("lev"))


@query("op_topk_per_group", "SELECT doc_id AS id, lang, pos FROM (SELECT doc_id, lang, CAST(row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS INTEGER) AS pos FROM documents) WHERE pos <= 5")
def op_topk_per_group(spark, d):
    docs = _t(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang", "n_chars")
    return ops.top_scores(docs, 5, "n_chars", "lang").select("id", "lang", "pos")


@query("op_math", "SELECT o_orderkey, round(sqrt(o_totalprice), 6) AS r, round(ln(o_totalprice), 6) AS l, floor(o_totalprice / 7)::BIGINT AS f, o_orderkey % 7 AS m FROM orders")
def op_math(spark, d):
    p = F.col("o_totalprice")
    return _t(spark, d, "orders").select("o_orderkey", _R6(F.sqrt(p)).alias("r"), _R6(F.log(p)).alias("l"), F.floor(p / 7).alias("f"), F.pmod("o_orderkey", F.lit(7)).alias("m"))


@query("op_string_counts", "SELECT doc_id, length(text) - length(translate(text, '0123456789', '')) AS digits, length(text) AS n, substr(md5(text), 1, 8) AS h FROM documents")
def op_string_counts(spark, d):
    t = F.col("text")
    return _t(spark, d, "documents").select("doc_id", (F.length(t) - F.length(F.translate(t, "0123456789", ""))).cast("long").alias("digits"), F.length(t).cast("long").alias("n"), F.substring(F.md5(t), 1, 8).alias("h"))


@query("op_date_parts", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS h, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow, CAST(date_trunc('day', ts) AS DATE) AS day FROM events")
def op_date_parts(spark, d):
    return _t(spark, d, "events").select("event_id", F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.to_date("ts").alias("day"))


@query("op_array_dot", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS norm2 FROM embeddings")
def op_array_dot(spark, d):
    v = F.col("embedding").cast("array<double>")
    return _t(spark, d, "embeddings").select("vec_id", _R6(vectors.array_dot(v, v)).alias("norm2"))


@query("op_map_coefs", "SELECT event_type AS feature, round(2 * avg(value), 6) AS coef FROM events GROUP BY 1")
def op_map_coefs(spark, d):
    """Mean values of the kinds of events as one map, doubled in it and taken out again."""
    means = _t(spark, d, "events").groupBy("event_type").agg(F.avg("value").alias("mean"))
    m = means.agg(F.map_from_entries(F.collect_list(F.struct("event_type", "mean"))).alias("m"))
    doubled = F.transform_values("m", lambda k, v: v * 2)
    return m.select(F.explode(F.map_entries(doubled)).alias("e")).select(F.col("e.key").alias("feature"), _R6("e.value").alias("coef"))


@query("op_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def op_json_props(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("op_md5_u52", "SELECT o_orderkey, CAST('0x' || substr(md5(concat_ws(':', 'x', o_orderkey)), 1, 13) AS BIGINT) AS u FROM orders")
def op_md5_u52(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", u52("x", F.col("o_orderkey")).alias("u"))


@query("udf_leverage", _TOP.select("SELECT id, round(lev, 6) AS lev FROM sl"))
def udf_leverage(spark, d):
    ds = dataset(spark, d, "docs3", standard=True)
    wide = ds.concat()
    leverage = ops.leverage_udf(whitener(gram(wide, ds.features)[0]))
    return wide.select("id", _R6(leverage(F.array(*ds.features))).alias("lev"))


def _ridge_lang() -> str:
    from vpcoreset.oracles import Chain

    chain = Chain()
    chain.wide("docs3")
    return chain.select("SELECT doc_lang AS lang, round(sum(digits * y) / (sum(digits * digits) + 5.0), 5) AS coef FROM z JOIN (SELECT doc_id, lang AS doc_lang FROM documents) ON doc_id = id GROUP BY 1")


@query("udaf_ridge", _ridge_lang())
def udaf_ridge(spark, d):
    ds = dataset(spark, d, "docs3", standard=True)
    rows = ds.concat().join(_t(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang"), "id")
    fit = ops.ridge_udaf(5.0)
    return rows.groupBy("lang").agg(fit(F.array("digits"), F.col("y"), F.lit(1.0)).alias("c")).select("lang", F.round(F.col("c")[0], 5).alias("coef"))


@query("udtf_draws", "SELECT CAST(range AS INTEGER) AS draw_no, CAST((CAST(CAST('0x' || substr(md5(concat_ws(':', 's', 'row', 0, range)), 1, 13) AS BIGINT) AS HUGEINT) * 1000) // 4503599627370496 AS BIGINT) AS threshold FROM range(50)")
def udtf_draws(spark, d):
    register(spark)
    return spark.sql("SELECT * FROM vp_draws('s', 50, 1000L)")


def _endpoint_oracle() -> str:
    chain = Chain()
    chain.add("x", f"SELECT p_size / 50.0 AS a, p_retailprice / 2000.0 AS b, length(p_name) / 10.0 AS c, 0.01 * (2 * {u52_sql(repr('planted'), 'p_partkey')} / 4503599627370496.0 - 1) AS noise FROM part")
    chain.add("y", "SELECT a::DOUBLE AS a, b::DOUBLE AS b, c::DOUBLE AS c, (a - 2 * b + 0.5 * c + noise)::DOUBLE AS y FROM x")
    return chain.select(unpivot(["a", "b", "c"], gauss(chain, "y", ["a", "b", "c"], "y", "0.0"), 6))


@query("op_endpoint_source", _endpoint_oracle())
def op_endpoint_source(spark, d):
    """The parts through a Python data source; least squares finds the planted coefficients."""
    from vpcoreset.solvers.ridge import fit
    from vpcoreset.sources.endpoint import planted, serve

    theta = fit(serve(spark, planted(_t(spark, d, "part"))), ["a", "b", "c"], "y")
    return spark.createDataFrame([(n, float(round(t, 6))) for n, t in zip("abc", theta, strict=True)], "feature string, coef double")


@query("op_totals", _reg_chain("docs").select("SELECT party, round(qp / 1099511627776.0, 6) AS party_total, round(grand / 1099511627776.0, 6) AS grand_total FROM tot"))
def op_totals(spark, d):
    """Party totals and the grand total in one grouped pass."""
    sums = sampling.quantize(_reg_table(spark, d)).groupBy("party").agg(F.sum("q").alias("q"))
    grand = sums.agg(F.sum("q").alias("g"))
    unit = float(1 << sampling.QUANTA)
    return sums.crossJoin(F.broadcast(grand)).select("party", F.round(F.col("q") / unit, 6).alias("party_total"), F.round(F.col("g") / unit, 6).alias("grand_total"))


@query("op_rollup_ledger", "SELECT phase, round, CAST(sum(units) AS BIGINT) AS units FROM (VALUES ('construction', 1, 6), ('construction', 2, 400), ('construction', 3, 300), ('solving', 4, 9100)) t(phase, round, units) GROUP BY ROLLUP (phase, round)")
def op_rollup_ledger(spark, d):
    from vpcoreset.plans.methods import _ledger

    return _ledger("strict").rollup(spark)


@query("sql_pipeline", _reg_chain("docs", M, "reg").select("SELECT CAST(sum(draws) AS BIGINT) AS draws, round(sum(weight), 2) AS weight, round((SELECT sum(score) FROM scores), 5) AS total FROM coreset"))
def sql_pipeline(spark, d):
    ds = dataset(spark, d, "docs", standard=True)
    table = scores.score_table(ds, scores.regression_scores)
    register(spark, ds, table, coreset.regression_coreset(ds, M))
    return spark.sql("SELECT sum(draws) AS draws, round(sum(weight), 2) AS weight, (SELECT round(sum(score), 5) FROM vp_scores) AS total FROM vp_coreset")
