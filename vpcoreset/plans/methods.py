"""Queries of scores, sampling, solvers, baselines and measures on the given tables."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset import assumptions, coreset, experiments, hard, objectives, planner, privacy, robust, sampling, scores
from vpcoreset.functions.rng import u52
from vpcoreset.ledger import construction, solving
from vpcoreset.linalg import gram
from vpcoreset.oracles import Chain, columns, descent, gauss, ridge3, uniform, unpivot
from vpcoreset.parties import PartySpec, VerticalDataset, dataset, pin, split_by_names
from vpcoreset.solvers import column_split, kmeans, ridge, saga
from vpcoreset.sources.fixtures import FIXTURES, wide_sql
from vpcoreset.sources.io import materialize

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return keep


def _r(c, digits: int = 6):
    return F.round(c, digits)


# ---- parties


def _party_query(title: str, fixture: str) -> None:
    cols = [c for block in columns(fixture) for c in block]
    chain = Chain()
    chain.wide(fixture, False)
    query(title, chain.select(f"SELECT id, {', '.join(f'round({c}, 6) AS {c}' for c in cols)} FROM w"))(
        lambda spark, d: dataset(spark, d, fixture).concat().select("id", *[_r(F.col(c)).alias(c) for c in cols]))


for _title, _fixture in (("party_split_emb", "emb3"), ("party_split_line", "line_star"), ("party_docs_features", "docs"), ("party_events_features", "ev"), ("party_pages_features", "pages"), ("party_conv_features", "conv")):
    _party_query(_title, _fixture)


@query("align_audit_docs_labels", """
SELECT count(*) AS total, count(*) FILTER (WHERE d.doc_id IS NOT NULL AND l.doc_id IS NOT NULL) AS both,
       count(*) FILTER (WHERE l.doc_id IS NULL) AS left_only, count(*) FILTER (WHERE d.doc_id IS NULL) AS right_only
FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id""")
def align_audit(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs_quality")
    a, b = ds.parties[0].df.select("id"), ds.parties[2].df.select(F.col("id").alias("id2"))
    both = a.join(b, F.col("id") == F.col("id2"), "full")
    return both.agg(
        F.count(F.lit(1)).alias("total"), F.sum((F.col("id").isNotNull() & F.col("id2").isNotNull()).cast("long")).alias("both"),
        F.sum(F.col("id2").isNull().cast("long")).alias("left_only"), F.sum(F.col("id").isNull().cast("long")).alias("right_only"))


def _standard_query(title: str, fixture: str) -> None:
    cols = [c for block in columns(fixture) for c in block]
    chain = Chain()
    chain.wide(fixture)
    query(title, chain.select(f"SELECT id, {', '.join(f'round({c}, 6) AS {c}' for c in cols)} FROM z"))(
        lambda spark, d: dataset(spark, d, fixture, standard=True).concat().select("id", *[_r(F.col(c)).alias(c) for c in cols]))


_standard_query("standardize_docs", "docs")
_standard_query("standardize_emb", "emb3")


@query("u52_stream", "SELECT range AS i, CAST('0x' || substr(md5(concat_ws(':', 'seed', 'row', 0, range)), 1, 13) AS BIGINT) AS u FROM range(1000)")
def u52_stream(spark: SparkSession, d: str) -> DataFrame:
    return spark.range(1000).select(F.col("id").alias("i"), u52("seed", "row", 0, F.col("id")).alias("u"))


# ---- scores


def _score_query(title: str, fixture: str) -> None:
    chain = Chain()
    chain.regression_scores(chain.wide(fixture), columns(fixture))
    query(title, chain.select("SELECT id, party, round(score * count(*) OVER (PARTITION BY party), 4) AS n_score FROM scores"))(
        lambda spark, d: _scaled(scores.score_table(ds := dataset(spark, d, fixture, standard=True), scores.regression_scores), ds))


def _scaled(table: DataFrame, ds: VerticalDataset, digits: int = 4) -> DataFrame:
    n = scores.row_count(ds.parties[0])
    return table.select("id", "party", _r(F.col("score") * n, digits).alias("n_score"))


_score_query("reg_scores_docs", "docs")
_score_query("reg_scores_line", "line_star")


@query("reg_scores_rank_deficient", "SELECT 2.0 AS score_sum, 3.0 AS score_sum_two")
def reg_scores_rank_deficient(spark: SparkSession, d: str) -> DataFrame:
    """A copied column adds nothing: the scores of {x, x} sum to rank 1 plus 1, those of {x, x, y} to 2 plus 1."""
    p = dataset(spark, d, "docs").parties[0]
    same = PartySpec("same", p.df.select("id", F.col("digits").alias("a"), F.col("digits").alias("b")), ("a", "b"))
    more = PartySpec("more", p.df.select("id", F.col("digits").alias("a"), (F.col("digits") * 2).alias("b"), F.col("upper").alias("c")), ("a", "b", "c"))
    one, two = (scores.regression_scores(x).agg(_r(F.sum("score")).alias("s")) for x in (same, more))
    return one.select(F.col("s").alias("score_sum")).crossJoin(two.select(F.col("s").alias("score_sum_two")))


def _weighted_oracle() -> str:
    chain = Chain()
    chain.wide("line_star", False)
    at = chain.leverage("p", "w", ["disc", "tax"], "qty")
    return chain.select(f"SELECT id, round((lev + qty / sum(qty) OVER ()) * count(*) OVER (), 4) AS n_score FROM {at} JOIN w USING (id)")


@query("reg_scores_weighted", _weighted_oracle())
def reg_scores_weighted(spark: SparkSession, d: str) -> DataFrame:
    p = dataset(spark, d, "line_star").parties[0]
    weighted = PartySpec("w", p.df, ("disc", "tax"), weight="qty")
    n = p.df.count()
    return scores.regression_scores(weighted).select("id", _r(F.col("score") * n, 4).alias("n_score"))


@query("reg_scores_emb_sum", "SELECT * FROM (VALUES (0, 23.0), (1, 22.0), (2, 23.0)) t(party, score_sum)")
def reg_scores_emb_sum(spark: SparkSession, d: str) -> DataFrame:
    """Rank plus one for each party; the last block holds the label."""
    table = scores.score_table(dataset(spark, d, "emb3"), scores.regression_scores)
    return table.groupBy("party").agg(_r(F.sum("score")).alias("score_sum"))


@query("reg_scores_tsqr", "SELECT 0.0 AS largest_difference")
def reg_scores_tsqr(spark: SparkSession, d: str) -> DataFrame:
    """The tree QR gives the scores of the Gram route."""
    p = dataset(spark, d, "docs", standard=True).parties[2]
    a, b = scores.regression_scores(p), scores.regression_scores(p, basis="tsqr").withColumnRenamed("score", "score2")
    return a.join(b, "id").agg(_r(F.max(F.abs(F.col("score") - F.col("score2")))).alias("largest_difference"))


K, STEPS = 4, 2


def _km_chain(fixture: str) -> tuple[Chain, str, list[list[str]]]:
    chain = Chain()
    rel = chain.wide(fixture)
    blocks = [[c for c in b if c != "y"] for b in columns(fixture)]
    return chain, rel, blocks


def _first(p: PartySpec, k: int) -> np.ndarray:
    return kmeans.local_centers(p, k, "first", iterations=STEPS)


def _centers_df(spark: SparkSession, centers: np.ndarray, names: list[str]) -> DataFrame:
    rows = [(i, n, float(round(v, 6))) for i, c in enumerate(centers) for n, v in zip(names, c, strict=True)]
    return spark.createDataFrame(rows, "cell int, feature string, value double")


def _centers_sql(rel: str, cols: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT cell, '{c}' AS feature, round({c}, 6) AS value FROM {rel}" for c in cols)


def _fixed_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    c, _ = chain.clusters("k", rel, blocks[0], K, STEPS)
    return chain.select(_centers_sql(c, blocks[0]))


@query("km_local_centers_fixed", _fixed_oracle())
def km_local_centers_fixed(spark: SparkSession, d: str) -> DataFrame:
    p = dataset(spark, d, "docs", standard=True).parties[0]
    return _centers_df(spark, _first(p, K), list(p.features))


def _cells_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    _, a = chain.clusters("k", rel, blocks[0], K, STEPS)
    return chain.select(f"SELECT id, cell, round(d2, 6) AS d2 FROM {a}")


@query("km_cells_docs", _cells_oracle())
def km_cells_docs(spark: SparkSession, d: str) -> DataFrame:
    p = dataset(spark, d, "docs", standard=True).parties[0]
    return scores.assign(p, _first(p, K)).select("id", "cell", _r(F.col("d2")).alias("d2"))


def _km_scores_query(title: str, fixture: str) -> None:
    chain, rel, blocks = _km_chain(fixture)
    chain.kmeans_scores(rel, blocks, K, STEPS)
    query(title, chain.select("SELECT id, party, round(score * count(*) OVER (PARTITION BY party), 4) AS n_score FROM scores"))(
        lambda spark, d: _scaled(scores.score_table(ds := dataset(spark, d, fixture, standard=True, label=False), lambda p: scores.kmeans_scores(p, K, clusterer=_first)), ds))


_km_scores_query("km_scores_docs", "docs")
_km_scores_query("km_scores_emb", "emb3")


@query("km_scores_total", "SELECT * FROM (VALUES (0, 44.0), (1, 44.0), (2, 44.0)) t(party, score_sum)")
def km_scores_total(spark: SparkSession, d: str) -> DataFrame:
    """alpha (2 + 2 k) for each party without empty cells: alpha 2, k 10."""
    table = scores.score_table(dataset(spark, d, "emb3", label=False), lambda p: scores.kmeans_scores(p, 10, alpha=2.0))
    return table.groupBy("party").agg(_r(F.sum("score")).alias("score_sum"))


def _farthest_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    cols = blocks[0]
    named = ", ".join(cols)
    at = chain.add("f0", f"SELECT id, {named}, 0 AS cell FROM {rel} ORDER BY id LIMIT 1")
    for i in range(1, K):
        d2 = " + ".join(f"(r.{x} - c.{x}) * (r.{x} - c.{x})" for x in cols)
        near = chain.add(f"n{i}", f"SELECT r.id, {', '.join(f'any_value(r.{x}) AS {x}' for x in cols)}, min({d2}) AS d2 FROM {rel} r CROSS JOIN {at} c GROUP BY r.id")
        at = chain.add(f"f{i}", f"SELECT id, {named}, cell FROM {at} UNION ALL SELECT id, {named}, {i} FROM (SELECT * FROM {near} ORDER BY d2 DESC, id LIMIT 1)")
    return chain.select(_centers_sql(at, cols))


@query("km_seed_farthest", _farthest_oracle())
def km_seed_farthest(spark: SparkSession, d: str) -> DataFrame:
    p = dataset(spark, d, "docs", standard=True).parties[0]
    return _centers_df(spark, kmeans.farthest_centers(p, K), list(p.features))


def _race_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    cols = blocks[0]
    named = ", ".join(cols)
    u = lambda i: f"-ln((CAST('0x' || substr(md5(concat_ws(':', 'd2', '{i}', r.id)), 1, 13) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496::DOUBLE)"
    at = chain.add("d0", f"SELECT id, {named}, 0 AS cell FROM {rel} r ORDER BY {u(0)}, id LIMIT 1")
    for i in range(1, K):
        d2 = " + ".join(f"(r.{x} - c.{x}) * (r.{x} - c.{x})" for x in cols)
        near = chain.add(f"n{i}", f"SELECT r.id, {', '.join(f'any_value(r.{x}) AS {x}' for x in cols)}, any_value({u(i)}) AS u, min({d2}) AS d2 FROM {rel} r CROSS JOIN {at} c GROUP BY r.id")
        at = chain.add(f"d{i}", f"SELECT id, {named}, cell FROM {at} UNION ALL SELECT id, {named}, {i} FROM (SELECT * FROM {near} WHERE d2 > 0 ORDER BY u / d2, id LIMIT 1)")
    return chain.select(_centers_sql(at, cols))


@query("km_seed_d2", _race_oracle())
def km_seed_d2(spark: SparkSession, d: str) -> DataFrame:
    p = dataset(spark, d, "docs", standard=True).parties[0]
    return _centers_df(spark, kmeans.d2_centers(p, K), list(p.features))


# ---- sampling

M = 200


def _reg_chain(fixture: str, m: int = M, seed: str = "sample", replicates: int = 1) -> Chain:
    chain = Chain()
    chain.regression_scores(chain.wide(fixture), columns(fixture))
    chain.coreset(chain.draws("scores", m, seed, replicates), m)
    return chain


def _reg_table(spark: SparkSession, d: str, fixture: str = "docs") -> DataFrame:
    return scores.score_table(dataset(spark, d, fixture, standard=True), scores.regression_scores)


@query("draw_party_totals", _reg_chain("docs").select("SELECT party, round(qp / 1099511627776.0, 6) AS party_total FROM tot"))
def draw_party_totals(spark: SparkSession, d: str) -> DataFrame:
    totals = sampling.store_quanta(_reg_table(spark, d)).party_totals
    return spark.createDataFrame([(j, round(t / (1 << 40), 6)) for j, t in totals.items()], "party int, party_total double")


@query("draw_allocation", _reg_chain("docs").select("SELECT party, count(*) AS draws FROM par GROUP BY 1"))
def draw_allocation(spark: SparkSession, d: str) -> DataFrame:
    drawn = sampling.allocate_draws(sampling.store_quanta(_reg_table(spark, d)).party_totals, M, "sample")
    return spark.createDataFrame([(j,) for j in drawn], "party int").groupBy("party").agg(F.count(F.lit(1)).alias("draws"))


@query("draw_draws", _reg_chain("docs").select("SELECT replicate, draw_no, party, id FROM draws"))
def draw_draws(spark: SparkSession, d: str) -> DataFrame:
    quanta = sampling.store_quanta(_reg_table(spark, d))
    return sampling.draw_rows(quanta, sampling.make_thresholds(quanta.totals, M, "sample", [0])).drop("bucket")


@query("draw_weights", _reg_chain("docs").select(f"SELECT d.draw_no, d.party, d.id, round(c.weight / c.draws, 3) AS weight FROM draws d JOIN coreset c USING (replicate, id)"))
def draw_weights(spark: SparkSession, d: str) -> DataFrame:
    out = sampling.two_level_sample(_reg_table(spark, d), M, collapse=False).df
    return out.select("draw_no", "party", "id", _r(F.col("weight"), 3).alias("weight"))


def _collapsed(df: DataFrame) -> DataFrame:
    return df.select("replicate", "id", "draws", _r(F.col("weight"), 3).alias("weight"))


_COLLAPSED = "SELECT replicate, id, draws, round(weight, 3) AS weight FROM coreset"


@query("draw_coreset_collapsed", _reg_chain("line_star").select(_COLLAPSED))
def draw_coreset_collapsed(spark: SparkSession, d: str) -> DataFrame:
    return _collapsed(sampling.two_level_sample(_reg_table(spark, d, "line_star"), M).df)


@query("draw_replicates", _reg_chain("docs", 50, "sample", 5).select(_COLLAPSED))
def draw_replicates(spark: SparkSession, d: str) -> DataFrame:
    return _collapsed(sampling.two_level_sample(_reg_table(spark, d), 50, replicates=range(5)).df)


@query("draw_one_party", "SELECT 0.0 AS largest_difference")
def draw_one_party(spark: SparkSession, d: str) -> DataFrame:
    """With one party the weights are those of plain importance sampling, G / (m g)."""
    ds = dataset(spark, d, "docs", standard=True)
    one = VerticalDataset((replace(ds.parties[0], name="one"),))
    table = scores.score_table(one, scores.regression_scores)
    out = sampling.two_level_sample(table, M).df.join(table.select("id", "score"), "id")
    total = table.agg(F.sum("score")).collect()[0][0]
    plain = F.col("draws") * F.lit(total) / (F.lit(M) * F.col("score"))
    return out.agg(_r(F.max(F.abs(F.col("weight") / plain - 1))).alias("largest_difference"))


@query("draw_offline_sensitivity")
def draw_offline_sensitivity(spark: SparkSession, d: str) -> DataFrame:
    """Offline importance sampling by exact joint sensitivities."""
    s = assumptions.sensitivity_regression(dataset(spark, d, "docs", standard=True))
    return _collapsed(sampling.two_level_sample(s.select("id", F.lit(0).alias("party"), F.col("sensitivity").alias("score")), M, "offline").df)


def _uniform_oracle(select: str) -> str:
    chain = Chain()
    chain.wide("line_star", False)
    uniform(chain, "w", M, "uniform")
    return chain.select(select)


@query("uniform_sample", _uniform_oracle("SELECT replicate, id, draws, round(weight, 3) AS weight FROM ucoreset"))
def uniform_sample(spark: SparkSession, d: str) -> DataFrame:
    return _collapsed(sampling.uniform_sample(dataset(spark, d, "line_star"), M).df)


@query("uniform_weights", _uniform_oracle("SELECT count(*) AS ids, CAST(sum(draws) AS BIGINT) AS draws, round(sum(weight), 3) AS weight, (SELECT count(*) FROM w) AS n FROM ucoreset"))
def uniform_weights(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "line_star")
    out = sampling.uniform_sample(ds, M).df.agg(F.count(F.lit(1)).alias("ids"), F.sum("draws").alias("draws"), _r(F.sum("weight"), 3).alias("weight"))
    return out.crossJoin(ds.parties[0].df.agg(F.count(F.lit(1)).alias("n")))


def _hash_oracle(select: str) -> str:
    chain = Chain()
    chain.wide("line_star", False)
    chain.add("h", "SELECT id, CAST('0x' || substr(md5(concat_ws(':', 'bernoulli', id)), 1, 13) AS BIGINT) AS u, CAST('0x' || substr(md5(concat_ws(':', 'without', id)), 1, 13) AS BIGINT) AS v FROM w")
    return chain.select(select)


@query("bernoulli_by_hash", _hash_oracle(f"SELECT id, 20.0 AS weight FROM h WHERE u < {int(0.05 * (1 << 52))}"))
def bernoulli_by_hash(spark: SparkSession, d: str) -> DataFrame:
    return sampling.bernoulli_sample(dataset(spark, d, "line_star").parties[0].df, 0.05).select("id", "weight")


@query("uniform_without_replacement", _hash_oracle("SELECT id FROM h ORDER BY v, id LIMIT 100"))
def uniform_without_replacement(spark: SparkSession, d: str) -> DataFrame:
    return sampling.smallest_hashes(dataset(spark, d, "line_star").parties[0].df.select("id"), 100)


# ---- coresets


@query("reg_coreset_docs", _reg_chain("docs", M, "reg").select(_COLLAPSED))
def reg_coreset_docs(spark: SparkSession, d: str) -> DataFrame:
    return _collapsed(coreset.regression_coreset(dataset(spark, d, "docs", standard=True), M).df)


@query("reg_coreset_line", _reg_chain("line_star", M, "reg").select(_COLLAPSED))
def reg_coreset_line(spark: SparkSession, d: str) -> DataFrame:
    return _collapsed(coreset.regression_coreset(dataset(spark, d, "line_star", standard=True), M).df)


@query("reg_coreset_docs_quality")
def reg_coreset_docs_quality(spark: SparkSession, d: str) -> DataFrame:
    """The label lives in another table and covers some rows: parties keep the common ids."""
    ds = dataset(spark, d, "docs_quality").align("inner")
    from vpcoreset.parties import standardize

    return _collapsed(coreset.regression_coreset(standardize(ds), 50).df)


def _km_coreset_query(title: str, fixture: str) -> None:
    chain, rel, blocks = _km_chain(fixture)
    chain.kmeans_scores(rel, blocks, K, STEPS)
    chain.coreset(chain.draws("scores", M, "km"), M)
    query(title, chain.select(_COLLAPSED))(
        lambda spark, d: _collapsed(coreset.kmeans_coreset(dataset(spark, d, fixture, standard=True, label=False), K, M, clusterer=_first).df))


_km_coreset_query("km_coreset_docs", "docs")
_km_coreset_query("km_coreset_emb", "emb3")


# ---- solvers and baselines


def _coefs(spark: SparkSession, names: list[str], theta: np.ndarray, digits: int = 6) -> DataFrame:
    return spark.createDataFrame([(n, float(round(t, digits))) for n, t in zip(names, theta, strict=True)], "feature string, coef double")


def _ridge_oracle(kind: str, digits: int = 5) -> str:
    chain = Chain()
    rel = chain.wide("docs3")
    lam, weight = "(SELECT 0.1 * count(*) FROM w)", "1.0"
    if kind == "coreset":
        chain.regression_scores(rel, columns("docs3"))
        c = chain.coreset(chain.draws("scores", M, "reg"), M)
    elif kind == "uniform":
        c = uniform(chain, rel, M, "uniform")
    if kind != "full":
        rel, weight = chain.add("rows", f"SELECT z.*, c.weight FROM z JOIN {c} c USING (id)"), "weight"
    inner = ridge3(chain, rel, ["digits", "dots", "punct"], "y", lam, weight)
    return chain.select(f"SELECT feature, round(coef, {digits}) AS coef FROM ({inner})")


def _reg(ds: VerticalDataset) -> ridge.Regularizer:
    return ridge.Regularizer(l2=0.1 * scores.row_count(ds.parties[0]))


@query("ridge_full_docs", _ridge_oracle("full"))
def ridge_full_docs(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    return _coefs(spark, ds.features, ridge.fit(ds.concat(), ds.features, ds.label, _reg(ds)), 5)


@query("ridge_on_coreset", _ridge_oracle("coreset"))
def ridge_on_coreset(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    return _coefs(spark, ds.features, coreset.solve_on_coreset(ds, coreset.regression_coreset(ds, M), coreset.ridge_on(_reg(ds))).model, 5)


@query("ridge_on_uniform", _ridge_oracle("uniform"))
def ridge_on_uniform(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    return _coefs(spark, ds.features, coreset.solve_on_coreset(ds, sampling.uniform_sample(ds, M), coreset.ridge_on(_reg(ds))).model, 5)


def _linear_oracle(fixture: str, l1: float, l2: float, digits: int) -> str:
    chain = Chain()
    rel = chain.wide(fixture)
    cols = [c for b in columns(fixture) for c in b if c != "y"]
    n = "(SELECT count(*) FROM w)"
    found = descent(chain, rel, cols, "y", f"{l1} * {n}", f"{l2} * {n}", 400) if l1 else gauss(chain, rel, cols, "y", f"{l2} * {n}")
    return chain.select(unpivot(cols, found, digits))


def _linear_query(title: str, fixture: str, l1: float = 0.0, l2: float = 0.1, digits: int = 5):
    @query(title, _linear_oracle(fixture, l1, l2, digits))
    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = dataset(spark, d, fixture, standard=True)
        n = scores.row_count(ds.parties[0])
        return _coefs(spark, ds.features, ridge.fit(ds.concat(), ds.features, ds.label, ridge.Regularizer(l2=l2 * n, l1=l1 * n)), digits)

    return run


_linear_query("ridge_full_line", "line_star")
_linear_query("ridge_full_docs_all", "docs")
_linear_query("lasso_full_docs", "docs", l1=0.2, l2=0.0, digits=3)
_linear_query("elastic_net_full_docs", "docs", l1=0.1, l2=0.05, digits=4)
_linear_query("least_squares_full_docs", "docs", l2=0.0, digits=4)


@query("ridge_full_emb")
def ridge_full_emb(spark: SparkSession, d: str) -> DataFrame:
    """All 64 columns; the optimality gap is the largest violation of the conditions of the minimum."""
    ds = dataset(spark, d, "emb3", standard=True)
    reg = _reg(ds)
    g, _ = gram(ds.concat(), [*ds.features, ds.label])
    theta = ridge.solve_gram(g[:-1, :-1], g[:-1, -1], reg)
    return _coefs(spark, ds.features, theta).withColumn("gap", F.lit(ridge.optimality_gap(g[:-1, :-1], g[:-1, -1], theta, reg)))


def _saga_query(title: str, kind: str):
    @query(title, _ridge_oracle(kind, 3))
    def run(spark: SparkSession, d: str) -> DataFrame:
        """Incremental gradients on a sample, run to a small gradient, end at the exact solution on it."""
        ds = dataset(spark, d, "docs3", standard=True)
        reg = _reg(ds)
        sample = sampling.uniform_sample(ds, M) if kind == "uniform" else coreset.regression_coreset(ds, M)
        rows = sample.materialize(ds).orderBy("id").toPandas()
        x, y, w = rows[ds.features].to_numpy(float), rows["y"].to_numpy(float), rows["weight"].to_numpy(float)
        return _coefs(spark, ds.features, saga.saga(x, y, w, reg.l2, passes=3_000, tol=1e-7).theta, 3)

    return run


_saga_query("saga_on_coreset", "coreset")
_saga_query("saga_on_uniform", "uniform")


@query("saga_full")
def saga_full(spark: SparkSession, d: str) -> DataFrame:
    """The incremental solver on all rows, unscaled and scaled by the columns' deviations, and on both samples: passes, steps, gradient, convergence.

    A cap of passes is part of the comparison; all rows are in.
    """
    out = []
    for name, standard in (("unscaled", False), ("scaled", True)):
        ds = dataset(spark, d, "docs", standard=standard).map(pin)
        n = int(scores.row_count(ds.parties[0]))
        found = saga.saga_blocks(ds.concat(), ds.features, ds.label, 0.1 * n, passes=60)
        out.append(("full", name, n, found.steps, found.steps // n, found.gradient, found.converged))
        for method, sample in (("coreset", coreset.regression_coreset(ds, 500)), ("uniform", sampling.uniform_sample(ds, 500))):
            rows = sample.materialize(ds).orderBy("id").toPandas()
            found = saga.saga(rows[ds.features].to_numpy(float), rows["y"].to_numpy(float), rows["weight"].to_numpy(float), 0.1 * n, passes=60)
            out.append((method, name, len(rows), found.steps, found.steps // len(rows), found.gradient, found.converged))
    return spark.createDataFrame(out, "method string, columns string, rows long, steps long, passes long, gradient double, converged boolean")


def _full_km_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    cols = [c for b in blocks for c in b]
    c, _ = chain.clusters("k", rel, cols, K, 3)
    return chain.select(_centers_sql(c, cols))


@query("kmeans_full_docs", _full_km_oracle())
def kmeans_full_docs(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs", standard=True, label=False)
    whole = pin(PartySpec("all", ds.concat(), tuple(ds.features)))
    return _centers_df(spark, kmeans.lloyd(whole, kmeans.first_centers(whole, K), 3), ds.features)


@query("kmeans_full_emb")
def kmeans_full_emb(spark: SparkSession, d: str) -> DataFrame:
    """Seeding by squared distance and Lloyd steps on all rows, the best of three starts."""
    ds = dataset(spark, d, "emb3", label=False)
    whole = pin(PartySpec("all", ds.concat(), tuple(ds.features)))
    (cost,), n = kmeans.costs_many(whole.df, ds.features, [kmeans.full_centers(whole, 10)])
    return spark.createDataFrame([(10, cost / n)], "k int, cost double")


def _plus_oracle() -> str:
    """Three seeds by the race, two Lloyd steps: the full k-means++ of one start, spelled out."""
    chain, rel, blocks = _km_chain("docs3")
    cols = [c for b in blocks for c in b]
    u = lambda i: f"-ln((CAST('0x' || substr(md5(concat_ws(':', 'plus-0', '{i}', r.id)), 1, 13) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496::DOUBLE)"
    named, d2 = ", ".join(cols), " + ".join(f"(r.{x} - c.{x}) * (r.{x} - c.{x})" for x in cols)
    at = chain.add("s0", f"SELECT {named}, 0 AS cell FROM {rel} r ORDER BY {u(0)}, id LIMIT 1")
    for i in range(1, 3):
        near = chain.add(f"m{i}", f"SELECT r.id, {', '.join(f'any_value(r.{x}) AS {x}' for x in cols)}, any_value({u(i)}) AS u, min({d2}) AS d2 FROM {rel} r CROSS JOIN {at} c GROUP BY r.id")
        at = chain.add(f"s{i}", f"SELECT {named}, cell FROM {at} UNION ALL SELECT {named}, {i} FROM (SELECT * FROM {near} WHERE d2 > 0 ORDER BY u / d2, id LIMIT 1)")
    c, a = chain.clusters("l", rel, cols, 3, 2, at)
    return chain.select(_centers_sql(c, cols))


@query("kmeans_plus_full_docs", _plus_oracle())
def kmeans_plus_full_docs(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True, label=False)
    whole = pin(PartySpec("all", ds.concat(), tuple(ds.features)))
    return _centers_df(spark, kmeans.full_centers(whole, 3, restarts=1, iterations=2, seed="plus"), ds.features)


@query("kmeans_spark_ml")
def kmeans_spark_ml(spark: SparkSession, d: str) -> DataFrame:
    """Parallel seeding of Spark's own library, as a cross-check."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    ds = dataset(spark, d, "emb3", label=False)
    rows = VectorAssembler(inputCols=ds.features, outputCol="features").transform(ds.concat())
    model = KMeans(k=10, seed=3, maxIter=10, initMode="k-means||").fit(rows)
    return spark.createDataFrame([(10, float(model.summary.trainingCost) / rows.count())], "k int, cost double")


def _km_sample_query(title: str, uniform_rows: bool):
    @query(title)
    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = dataset(spark, d, "docs", standard=True, label=False).map(pin)
        sample = sampling.uniform_sample(ds, M) if uniform_rows else coreset.kmeans_coreset(ds, 10, M)
        centers = coreset.solve_on_coreset(ds, sample, lambda x, y, w: kmeans.fit_weighted(x, w, 10)).model
        wide = ds.concat()
        return spark.createDataFrame([(M, objectives.kmeans_costs(wide, ds.features, [centers])[0] / wide.count())], "size int, cost double")

    return run


_km_sample_query("kmeans_on_coreset", False)
_km_sample_query("kmeans_on_uniform", True)


def _grid_oracle() -> str:
    chain, rel, blocks = _km_chain("emb3")
    cells = [chain.clusters(f"k{j}", rel, b, K, STEPS)[1] for j, b in enumerate(blocks)]
    return chain.select(f"SELECT a.cell AS cell_1, b.cell AS cell_2, c.cell AS cell_3, CAST(count(*) AS DOUBLE) AS w FROM {cells[0]} a JOIN {cells[1]} b USING (id) JOIN {cells[2]} c USING (id) GROUP BY 1, 2, 3")


@query("column_split_kmeans_cells", _grid_oracle())
def column_split_kmeans_cells(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "emb3", standard=True, label=False)
    return column_split.product_grid(column_split.party_cells(ds, [_first(p, K) for p in ds.parties]), 3)


@query("column_split_kmeans_full")
def column_split_kmeans_full(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "emb3", label=False)
    centers, wide = column_split.fit(ds, 10), ds.concat()
    return spark.createDataFrame([(10, objectives.kmeans_costs(wide, ds.features, [centers])[0] / wide.count())], "k int, cost double")


def _column_split_query(title: str, uniform_rows: bool):
    @query(title)
    def run(spark: SparkSession, d: str) -> DataFrame:
        ds = dataset(spark, d, "emb3", label=False)
        sample = sampling.uniform_sample(ds, M) if uniform_rows else coreset.kmeans_coreset(ds, 10, M)
        cuts = np.cumsum([0, *[len(p.features) for p in ds.parties]])
        solved = coreset.solve_on_coreset(ds, sample, lambda x, y, w: column_split.fit_arrays([x[:, a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)], w, 10), method="dimension", k=10, policy="table")
        wide = ds.concat()
        return spark.createDataFrame([(M, objectives.kmeans_costs(wide, ds.features, [solved.model])[0] / wide.count(), solved.ledger.total())], "size int, cost double, units long")

    return run


_column_split_query("column_split_on_coreset", False)
_column_split_query("column_split_on_uniform", True)


# ---- measures

THETAS = ((0.0, 0.0, 0.0), (0.2, 0.3, 0.1), (-0.5, 1.0, 0.0), (1.0, 1.0, 1.0))


def _theta_oracle() -> str:
    chain = Chain()
    rel = chain.wide("docs3")
    chain.regression_scores(rel, columns("docs3"))
    chain.coreset(chain.draws("scores", M, "reg"), M)
    parts = []
    for i, (a, b, c) in enumerate(THETAS):
        r2 = f"power({a} * digits + {b} * dots + {c} * punct - y, 2)"
        parts.append(f"SELECT {i} AS probe, (SELECT round(sum({r2}) / count(*), 5) FROM z) AS full_cost, (SELECT round(sum(weight * {r2}) / (SELECT count(*) FROM z), 5) FROM z JOIN coreset USING (id)) AS sample_cost")
    return chain.select(" UNION ALL ".join(parts))


@query("reg_cost_theta_grid", _theta_oracle())
def reg_cost_theta_grid(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    wide = ds.concat()
    n = wide.count()
    full = objectives.regression_costs(wide, ds.features, ds.label, THETAS)
    part = objectives.regression_costs(coreset.regression_coreset(ds, M).materialize(ds), ds.features, ds.label, THETAS, "weight")
    return spark.createDataFrame([(i, round(a / n, 5), round(b / n, 5)) for i, (a, b) in enumerate(zip(full, part, strict=True))], "probe int, full_cost double, sample_cost double")


def _center_grid_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    cols = [c for b in blocks for c in b]
    parts = []
    for i in (1, 2, K):
        _, a = chain.clusters(f"g{i}", rel, cols, i, 0)
        parts.append(f"SELECT {i} AS k, round(avg(d2), 5) AS cost FROM {a}")
    return chain.select(" UNION ALL ".join(parts))


@query("km_cost_centers_grid", _center_grid_oracle())
def km_cost_centers_grid(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs", standard=True, label=False)
    wide = ds.concat()
    whole = PartySpec("all", wide, tuple(ds.features))
    n = wide.count()
    costs = objectives.kmeans_costs(wide, ds.features, [kmeans.first_centers(whole, k) for k in (1, 2, K)])
    return spark.createDataFrame([(k, round(c / n, 5)) for k, c in zip((1, 2, K), costs, strict=True)], "k int, cost double")


@query("reg_eps_certificate", "SELECT true AS holds")
def reg_eps_certificate(spark: SparkSession, d: str) -> DataFrame:
    """No probe's error exceeds the certificate."""
    ds = dataset(spark, d, "docs3", standard=True)
    wide, part = ds.concat(), coreset.regression_coreset(ds, M).materialize(ds)
    eps = objectives.epsilon_certificate(wide, part, [*ds.features, ds.label])
    a = objectives.regression_costs(wide, ds.features, ds.label, THETAS)
    b = objectives.regression_costs(part, ds.features, ds.label, THETAS, "weight")
    return spark.createDataFrame([(all(abs(y - x) <= (eps + 1e-9) * x for x, y in zip(a, b, strict=True)),)], "holds boolean")


@query("reduction_bound")
def reduction_bound(spark: SparkSession, d: str) -> DataFrame:
    """Samples grow until the certificate eps is at most 1/3; then the sample's solution costs at most (1 + 3 eps) of the best, alpha being 1 for the exact solver.

    Reported: both sides of each bound, for the exact ridge and for an incremental solver of quality alpha on the sample.
    """
    ds = dataset(spark, d, "docs3", standard=True)
    reg, wide = _reg(ds), materialize(ds.concat(), "wide")
    table = materialize(scores.score_table(ds, scores.regression_scores), "scores")
    best = ridge.fit(wide, ds.features, ds.label, reg)
    out, m, cols = [], M, [*ds.features, ds.label]
    while True:
        part = materialize(sampling.two_level_sample(table, m, "reduce").materialize(ds), "rows")
        eps = objectives.epsilon_certificate(wide, part, cols)
        if eps <= 1 / 3 or m > 100 * M:
            break
        m *= 2
    rows = part.orderBy("id").toPandas()
    x, y, w = rows[ds.features].to_numpy(float), rows["y"].to_numpy(float), rows["weight"].to_numpy(float)
    on_sample = lambda t: float((w * (x @ t - y) ** 2).sum() + reg.value(t))
    exact = ridge.fit_arrays(x, y, w, reg)
    for solver, theta in (("ridge", exact), ("saga", saga.saga(x, y, w, reg.l2, passes=5, tol=0.0).theta)):
        alpha = on_sample(theta) / on_sample(exact)
        low, cost = objectives.regression_costs(wide, ds.features, ds.label, [best, theta], ridge=reg.l2)
        out.append((solver, m, eps, alpha, cost / low, planner.reduction_factor(min(eps, 1 / 3), alpha), bool(eps <= 1 / 3 and cost / low <= planner.reduction_factor(eps, alpha) * (1 + 1e-9))))
    return spark.createDataFrame(out, "solver string, m int, eps double, alpha double, ratio double, bound double, holds boolean")


def _reduction_oracle() -> str:
    chain = Chain()
    rel = chain.wide("docs3")
    chain.regression_scores(rel, columns("docs3"))
    c = chain.coreset(chain.draws("scores", M, "reg"), M)
    cols, lam = ["digits", "dots", "punct"], "(SELECT 0.1 * count(*) FROM w)"
    a = gauss(chain, rel, cols, "y", lam, name="best_t")
    b = gauss(chain, chain.add("rows", f"SELECT z.*, c.weight FROM z JOIN {c} c USING (id)"), cols, "y", lam, "weight", name="part_t")
    cost = lambda t: f"(SELECT sum(power({' + '.join(f'z.{x} * {t}.t{i}' for i, x in enumerate(cols))} - z.y, 2)) + any_value({lam} * ({' + '.join(f'{t}.t{i} * {t}.t{i}' for i in range(3))})) FROM z, {t})"
    return chain.select(f"SELECT round({cost(a)} / (SELECT count(*) FROM z), 6) AS best, round({cost(b)} / (SELECT count(*) FROM z), 6) AS found")


@query("reduction_costs", _reduction_oracle())
def reduction_costs(spark: SparkSession, d: str) -> DataFrame:
    """Cost a row on all rows, penalty included, of the best model and of the sample's exact solution."""
    ds = dataset(spark, d, "docs3", standard=True)
    reg, wide = _reg(ds), ds.concat()
    found = coreset.solve_on_coreset(ds, coreset.regression_coreset(ds, M), coreset.ridge_on(reg)).model
    a, b = objectives.regression_costs(wide, ds.features, ds.label, [ridge.fit(wide, ds.features, ds.label, reg), found], ridge=reg.l2)
    n = wide.count()
    return spark.createDataFrame([(round(a / n, 6), round(b / n, 6))], "best double, found double")


def _sensitivity_oracle(select: str) -> str:
    chain = Chain()
    rel = chain.wide("docs3")
    chain.leverage("s", rel, [c for b in columns("docs3") for c in b])
    chain.regression_scores(rel, columns("docs3"))
    return chain.select(select)


@query("sensitivity_reg", _sensitivity_oracle("SELECT id, round(lev * count(*) OVER (), 4) AS n_sensitivity FROM sl"))
def sensitivity_reg(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    n = scores.row_count(ds.parties[0])
    return assumptions.sensitivity_regression(ds).select("id", _r(F.col("sensitivity") * n, 4).alias("n_sensitivity"))


@query("zeta_reg", _sensitivity_oracle("SELECT round(max(lev / s), 5) AS zeta FROM sl JOIN (SELECT id, sum(score) AS s FROM scores GROUP BY 1) USING (id)"))
def zeta_reg(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    z = assumptions.zeta(assumptions.sensitivity_regression(ds), scores.score_table(ds, scores.regression_scores))
    return spark.createDataFrame([(round(z, 5),)], "zeta double")


@query("gamma_diag", "SELECT true AS in_range, true AS zeta_bounded")
def gamma_diag(spark: SparkSession, d: str) -> DataFrame:
    """0 < gamma <= 1 and zeta gamma^2 <= 1."""
    ds = dataset(spark, d, "docs3", standard=True)
    g = assumptions.gamma(ds)
    z = assumptions.zeta(assumptions.sensitivity_regression(ds), scores.score_table(ds, scores.regression_scores))
    return spark.createDataFrame([(0 < g <= 1 + 1e-9, z * g * g <= 1 + 1e-6)], "in_range boolean, zeta_bounded boolean")


@query("assumption_cases")
def assumption_cases(spark: SparkSession, d: str) -> DataFrame:
    """gamma where the assumption holds, where the label is nearly another party's, and on the hard instance; tau of the most important party where one party tells rows apart and where none does."""
    rows = [("regression", n, "gamma", assumptions.gamma(dataset(spark, d, n, standard=True))) for n in ("line_star", "line_planted", "line_rev", "docs")]
    rows.append(("regression", "hard", "gamma", assumptions.gamma(hard.hard_regression(spark, 2_000, 7))))
    for name, ds in (("emb2", dataset(spark, d, "emb2", label=False)), ("docs", dataset(spark, d, "docs", standard=True, label=False)), ("hard", hard.hard_kmeans(spark, 300, 77))):
        rows.append(("kmeans", name, "tau", float(assumptions.tau(ds).agg(F.min("tau")).collect()[0][0])))
    return spark.createDataFrame(rows, "task string, instance string, measure string, value double")


def _planted_oracle() -> str:
    chain = Chain()
    rel = chain.wide("line_planted")
    cols = [c for b in columns("line_planted") for c in b if c != "y"]
    return chain.select(unpivot(cols, gauss(chain, rel, cols, "y", "0.0"), 4))


@query("planted_model", _planted_oracle())
def planted_model(spark: SparkSession, d: str) -> DataFrame:
    """Least squares on a label that was made from known coefficients (in scaled columns) and a small noise finds them, up to the label's scale."""
    ds = dataset(spark, d, "line_planted", standard=True)
    return _coefs(spark, ds.features, ridge.fit(ds.concat(), ds.features, ds.label), 4)


def _tau_oracle(fixture: str, standard: bool) -> str:
    chain = Chain()
    rel = chain.wide(fixture, standard)
    blocks = [[c for c in b if c != "y"] for b in columns(fixture)]
    d = [" + ".join(f"(a.{c} - b.{c}) * (a.{c} - b.{c})" for c in block) for block in blocks]
    chain.add("pairs", f"SELECT {', '.join(f'{x} AS d{j}' for j, x in enumerate(d))} FROM {rel} a JOIN {rel} b ON a.id < b.id")
    full = " + ".join(f"d{j}" for j in range(len(blocks)))
    # A pair of equal blocks that differs elsewhere has an infinite ratio, a pair of equal rows has ratio 1.
    one = [f"SELECT 'p{j + 1}' AS party, max(CASE WHEN d{j} > 0 THEN ({full}) / d{j} WHEN {full} > 0 THEN 1e300 ELSE 1 END) AS t FROM pairs" for j in range(len(blocks))]
    chain.add("ratios", " UNION ALL ".join(one))
    return chain.select("SELECT party, t >= 1e300 AS unbounded, CASE WHEN t < 1e300 THEN round(t, 5) END AS tau, t = min(t) OVER () AND t < 1e300 AS important FROM ratios")


def _tau(ds: VerticalDataset) -> DataFrame:
    """tau of each party, and which one has the least: the party whose distances tell most about all."""
    found = assumptions.tau(ds)
    least = found.agg(F.min("tau")).collect()[0][0]
    bounded = F.col("tau") < float("inf")
    return found.select("party", (~bounded).alias("unbounded"), F.when(bounded, _r(F.col("tau"), 5)).alias("tau"), (bounded & (F.col("tau") == F.lit(least))).alias("important"))


@query("tau_pairs_exact", _tau_oracle("docs", True))
def tau_pairs_exact(spark: SparkSession, d: str) -> DataFrame:
    return _tau(dataset(spark, d, "docs", standard=True, label=False))


@query("tau_emb", _tau_oracle("emb2", False))
def tau_emb(spark: SparkSession, d: str) -> DataFrame:
    """Exact over all pairs of vectors, in broadcast blocks."""
    return _tau(dataset(spark, d, "emb2", label=False))


_PLANS = (("regression", 0.1, 0.1, 0.5, 9), ("regression", 0.2, 0.05, 0.9, 3))


@query("size_planner", "SELECT * FROM (VALUES " + ", ".join(
    [f"('regression', CAST(ceil(power({e}, -2) * power({g}, -2) * {n} * ({n} * {n} * ln(greatest({n} / power({g}, 2), 2)) + ln(1 / {dl}))) AS BIGINT))" for _, e, dl, g, n in _PLANS]
    + ["('kmeans', CAST(ceil(power(0.2, -2) * 90 * (6 * 10 * ln(90) + ln(1 / 0.1))) AS BIGINT))", "('robust_regression', CAST(ceil(power(0.5 * 0.35 * 3, -2) * power(3, 6)) AS BIGINT))", "('robust_kmeans', CAST(ceil(power(0.5 * 0.5, -2) * power(2, 5) * 4) AS BIGINT))"]) + ") t(task, size)")
def size_planner(spark: SparkSession, d: str) -> DataFrame:
    rows = [("regression", planner.plan_regression(e, dl, g, n)) for _, e, dl, g, n in _PLANS]
    rows += [("kmeans", planner.plan_kmeans(0.2, 0.1, 1.0, 3.0, 10, 3, 6)), ("robust_regression", planner.plan_robust_regression(0.5, 0.35, 3, 3)), ("robust_kmeans", planner.plan_robust_kmeans(0.5, 0.5, 2, 4))]
    return spark.createDataFrame(rows, "task string, size long")


# ---- robust, hard, private


def _cut(chain: Chain, beta: float) -> None:
    chain.add("ranked", "SELECT cost, row_number() OVER (ORDER BY cost) AS pos, count(*) OVER () AS n FROM costed")
    chain.add("cut", f"SELECT max(cost) AS c FROM ranked WHERE pos = n - CAST(floor({beta} * n) AS BIGINT)")
    chain.add("marked", "SELECT *, cost > (SELECT c FROM cut) AS outlier FROM costed")


def _outlier_oracle() -> str:
    chain = Chain()
    chain.wide("docs3")
    chain.add("costed", "SELECT id, power(0.2 * digits + 0.3 * dots + 0.1 * punct - y, 2) AS cost FROM z")
    _cut(chain, 0.05)
    return chain.select("SELECT id, round(cost, 5) AS cost, outlier FROM marked")


@query("robust_reg_outliers", _outlier_oracle())
def robust_reg_outliers(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs3", standard=True)
    marked = robust.largest_costs(ds.concat(), objectives.residual2(ds.features, ds.label, THETAS[1]), 0.05)
    return marked.select("id", _r(F.col("cost"), 5).alias("cost"), "outlier")


_ROBUST = """SELECT round((SELECT avg(outlier::INT) FROM marked), 5) AS share_rows, round((SELECT sum(draws * outlier::INT) / sum(draws) FROM coreset JOIN marked USING (id)), 5) AS share_draws,
round(abs((SELECT sum(weight * cost) FROM coreset JOIN marked USING (id) WHERE NOT outlier) - (SELECT sum(cost) FROM marked WHERE NOT outlier)) / (SELECT sum(cost) FROM marked), 4) AS error"""


def _robust_row(spark: SparkSession, found: dict) -> DataFrame:
    return spark.createDataFrame([(round(found["share_rows"], 5), round(found["share_draws"], 5), round(found["error"], 4))], "share_rows double, share_draws double, error double")


def _robust_reg_oracle() -> str:
    chain = Chain()
    chain.regression_scores(chain.wide("line_rev"), columns("line_rev"))
    chain.coreset(chain.draws("scores", 1000, "reg"), 1000)
    chain.add("costed", "SELECT id, y * y AS cost FROM z")
    _cut(chain, 0.05)
    return chain.select(_ROBUST)


@query("robust_reg_check", _robust_reg_oracle())
def robust_reg_check(spark: SparkSession, d: str) -> DataFrame:
    """A label that nearly lies in another party's span: without the costliest rows the sampled cost is close."""
    ds = dataset(spark, d, "line_rev", standard=True)
    marked = robust.largest_costs(ds.concat(), objectives.residual2(ds.features, ds.label, [0.0] * len(ds.features)), 0.05).select("id", "cost", "outlier")
    return _robust_row(spark, robust.robust_check(marked, coreset.regression_coreset(ds, 1000).df, 0.3, 0.2))


def _robust_km_oracle() -> str:
    chain, rel, blocks = _km_chain("docs")
    chain.kmeans_scores(rel, blocks, K, STEPS)
    chain.coreset(chain.draws("scores", 500, "km"), 500)
    _, a = chain.clusters("all", rel, [c for b in blocks for c in b], K, 0)
    chain.add("costed", f"SELECT id, d2 AS cost FROM {a}")
    _cut(chain, 0.05)
    return chain.select(_ROBUST)


@query("robust_km_check", _robust_km_oracle())
def robust_km_check(spark: SparkSession, d: str) -> DataFrame:
    ds = dataset(spark, d, "docs", standard=True, label=False)
    wide = ds.concat()
    centers = kmeans.first_centers(PartySpec("all", wide, tuple(ds.features)), K)
    marked = robust.largest_costs(wide, objectives.least_d2(ds.features, centers), 0.05).select("id", "cost", "outlier")
    return _robust_row(spark, robust.robust_check(marked, coreset.kmeans_coreset(ds, K, 500, clusterer=_first).df, 0.3, 0.5))


@query("robust_sizes")
def robust_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Error without the costliest rows as samples grow, beside the error with them: the planned size (c = 1) and multiples of it."""
    ds = dataset(spark, d, "docs", standard=True, label=False).map(pin)
    wide = materialize(ds.concat(), "wide")
    centers = kmeans.first_centers(PartySpec("all", wide, tuple(ds.features)), K)
    cost = objectives.least_d2(ds.features, centers)
    marked = materialize(robust.largest_costs(wide, cost, 0.05).select("id", "cost", "outlier"), "marked")
    table = materialize(scores.score_table(ds, lambda p: scores.kmeans_scores(p, K, clusterer=_first)), "scores")
    base = planner.plan_robust_kmeans(0.5, 0.5, 2, len(ds.features))
    out = []
    for m in (base, 2 * base, 4 * base):
        sample = sampling.two_level_sample(table, m, "robust").df
        kept, all_rows = robust.robust_check(marked, sample, 0.5, 0.5), robust.robust_check(marked.withColumn("outlier", F.lit(False)), sample, 0.5, 0.5)
        out.append((m, kept["share_rows"], kept["share_draws"], kept["error"], all_rows["error"]))
    return spark.createDataFrame(out, "m int, share_rows double, share_draws double, error double, error_with_all double")


@query("secure_sum_equals_plain", _reg_chain("docs").select("SELECT id, round(sum(q) / 1099511627776.0, 6) AS total FROM q GROUP BY id"))
def secure_sum_equals_plain(spark: SparkSession, d: str) -> DataFrame:
    """What the server adds up from masked scores."""
    quanta = sampling.quantize(_reg_table(spark, d))
    return privacy.secure_sum(quanta).select("id", _r(F.col("q") / F.lit(float(1 << 40))).alias("total"))


@query("masked_coreset", _reg_chain("docs").select(_COLLAPSED))
def masked_coreset(spark: SparkSession, d: str) -> DataFrame:
    """The sample with masked addition in round 3 is the sample without it."""
    return _collapsed(sampling.two_level_sample(_reg_table(spark, d), M, masked=True).df)


@query("masked_summands_uniform", "SELECT 3 AS parties, true AS spread, 0 AS equal")
def masked_summands_uniform(spark: SparkSession, d: str) -> DataFrame:
    """Masked scores of each party fill the range evenly (means near half of it, all eighths hit) and none equals its score."""
    quanta = sampling.quantize(_reg_table(spark, d))
    seen = privacy.masked_scores(quanta).join(quanta, ["id", "party"])
    eighth = (F.col("masked") / F.lit(float(privacy.MODULUS)) * 8).cast("int")
    per = seen.groupBy("party").agg(F.avg(F.col("masked") / F.lit(float(privacy.MODULUS))).alias("mean"), F.count_distinct(eighth).alias("hit"), F.sum((F.col("masked") == F.col("q")).cast("long")).alias("equal"))
    return per.agg(F.count(F.lit(1)).cast("int").alias("parties"), F.min((F.abs(F.col("mean") - 0.5) < 0.1) & (F.col("hit") == 8)).alias("spread"), F.sum("equal").cast("int").alias("equal"))


@query("malicious_party_share", "SELECT true AS drifts, true AS nearly_all")
def malicious_party_share(spark: SparkSession, d: str) -> DataFrame:
    """A party that inflates its total draws the sample to itself."""
    table = _reg_table(spark, d)
    share = lambda t: sum(1 for j in sampling.allocate_draws(sampling.store_quanta(t).party_totals, 1000, "lie") if j == 1) / 1000
    honest, some, much = share(table), share(privacy.inflate_party(table, 1, 3)), share(privacy.inflate_party(table, 1, 500))
    return spark.createDataFrame([(honest < some < much, much > 0.99)], "drifts boolean, nearly_all boolean")


def _order_ids(spark: SparkSession, d: str) -> tuple[DataFrame, int]:
    """Ids of the orders, and the last one, whose row is hidden."""
    ids = spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("id"))
    return ids, ids.agg(F.max("id")).collect()[0][0]


@query("hard_regression_hidden_row", """
WITH r AS (SELECT CASE WHEN o_orderkey % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0 END AS a, CASE WHEN o_orderkey = max(o_orderkey) OVER () THEN -1.0 ELSE 1.0 END AS flip FROM orders),
s AS (SELECT a, a * flip AS b, count(*) OVER () AS n, sum(a * a) OVER () AS aa, sum(flip * flip) OVER () AS bb FROM r),
t AS (SELECT a * a / aa + 1.0 / n AS score FROM s UNION ALL SELECT b * b / bb + 1.0 / n FROM s)
SELECT (SELECT sum((a - b) * (a - b)) FROM s) AS hidden_cost, (SELECT round(max(score) - min(score), 9) FROM t) AS score_spread, (SELECT sqrt(1 - abs(sum(a * b)) / count(*)) < 0.05 FROM s) AS gamma_small""")
def hard_regression_hidden_row(spark: SparkSession, d: str) -> DataFrame:
    """On the ids of the orders: one row carries all the cost of (1, -1), yet all scores are equal."""
    ds = hard.hard_regression_on(*_order_ids(spark, d))
    cost = ds.concat().agg(F.sum((F.col("a") - F.col("b")) * (F.col("a") - F.col("b"))).alias("hidden_cost"))
    spread = scores.score_table(ds, scores.regression_scores).agg(_r(F.max("score") - F.min("score"), 9).alias("score_spread"))
    return cost.crossJoin(spread).withColumn("gamma_small", F.lit(bool(assumptions.gamma(ds) < 0.05)))


@query("hard_kmeans_hidden_point", """
WITH p AS (SELECT CASE WHEN o_orderkey % 3 = 2 THEN 1.0::DOUBLE ELSE 0.0 END AS a, CASE WHEN o_orderkey % 3 = 1 THEN 1.0::DOUBLE ELSE 0.0 END AS b, o_orderkey = max(o_orderkey) OVER () AS hidden FROM orders),
q AS (SELECT 0 AS kept, a, b FROM p UNION ALL SELECT 1, CASE WHEN hidden THEN 1.0 ELSE a END, CASE WHEN hidden THEN 1.0 ELSE b END FROM p),
c AS (SELECT kept, sum(least(a * a + b * b, a * a + (b - 1) * (b - 1), (a - 1) * (a - 1) + b * b)) AS cost FROM q GROUP BY 1)
SELECT (SELECT cost FROM c WHERE kept = 0) AS cost_without, (SELECT cost FROM c WHERE kept = 1) AS cost_with""")
def hard_kmeans_hidden_point(spark: SparkSession, d: str) -> DataFrame:
    centers = np.array([[0.0, 0.0], [0.0, 1.0], [1.0, 0.0]])
    ids, last = _order_ids(spark, d)
    a, b = (objectives.kmeans_costs(hard.hard_kmeans_on(ids, row).concat(), ["a", "b"], [centers])[0] for row in (None, last))
    return spark.createDataFrame([(a, b)], "cost_without double, cost_with double")


# ---- communication


def _ledger(policy: str, m: int = 100):
    out = construction(m, [40, 35, 25], "coreset", policy)
    return out.extend(solving("transfer", m, [30, 30, 30], label=True, policy=policy))


def _docs_totals(spark: SparkSession, d: str) -> tuple[VerticalDataset, dict[int, int]]:
    """The documents as three parties, and the totals of their scores."""
    ds = dataset(spark, d, "docs", standard=True)
    return ds, sampling.store_quanta(scores.score_table(ds, scores.regression_scores)).party_totals


def _docs_ledger(spark: SparkSession, d: str, policy: str, m: int = 100):
    """Messages of a sample of the documents, with the draws that their scores give each party, and of moving its rows."""
    ds, totals = _docs_totals(spark, d)
    drawn = sampling.allocate_draws(totals, m, "sample")
    out = construction(m, [drawn.count(j) for j in totals], "coreset", policy)
    return out.extend(solving("transfer", m, [len(p.features) for p in ds.parties], label=True, policy=policy))


def _messages(select: str, policy: str, m: int = 100) -> str:
    """The same in SQL, a row for each message of one unit or of a moved row, from the draws themselves."""
    chain = _reg_chain("docs", m)
    width = sum(map(len, columns("docs")))
    if policy == "strict":
        chain.add("messages", f"""SELECT 1 AS round, 'construction' AS phase, 'server' AS dst, 'party_total' AS kind, 1 AS units FROM tot
UNION ALL SELECT 1, 'construction', 'party', 'draw_count', 1 FROM tot UNION ALL SELECT 2, 'construction', 'server', 'row_ids', 1 FROM par
UNION ALL SELECT 2, 'construction', 'party', 'row_ids', 1 FROM par, tot UNION ALL SELECT 3, 'construction', 'server', 'score', 1 FROM par, tot
UNION ALL SELECT 4, 'solving', 'server', 'rows', {width} FROM draws""")
    else:
        chain.add("messages", f"""SELECT 2 AS round, 'construction' AS phase, 'server' AS dst, 'row_ids' AS kind, 1 AS units FROM par, tot
UNION ALL SELECT 2, 'construction', 'party', 'row_ids', 1 FROM par, tot UNION ALL SELECT 3, 'construction', 'server', 'score', 1 FROM par, tot
UNION ALL SELECT 4, 'solving', 'server', 'rows', {width - 1} FROM draws""")
    return chain.select(select)


_BY_PHASE = "SELECT phase, CAST(sum(units) AS BIGINT) AS units FROM messages GROUP BY 1"


@query("ledger_strict", _messages(_BY_PHASE, "strict"))
def ledger_strict(spark: SparkSession, d: str) -> DataFrame:
    """Three parties, 100 draws: 7 m + 6 to build, 7 m to move the rows with their label."""
    return _docs_ledger(spark, d, "strict").to_df(spark).groupBy("phase").agg(F.sum("units").alias("units"))


@query("ledger_table_policy", _messages(_BY_PHASE, "table"))
def ledger_table_policy(spark: SparkSession, d: str) -> DataFrame:
    return _docs_ledger(spark, d, "table").to_df(spark).groupBy("phase").agg(F.sum("units").alias("units"))


@query("ledger_rollup", _messages("SELECT phase, round, sum(units)::BIGINT AS units FROM messages GROUP BY ROLLUP (phase, round)", "strict"))
def ledger_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _docs_ledger(spark, d, "strict").rollup(spark)


@query("ledger_server_view", _messages("SELECT count(*) AS unexpected FROM messages WHERE dst = 'server' AND phase = 'construction' AND kind NOT IN ('party_total', 'row_ids', 'score', 'masked_score')", "strict"))
def ledger_server_view(spark: SparkSession, d: str) -> DataFrame:
    """Nothing but totals, ids and scores reaches the server while a sample is built."""
    return _docs_ledger(spark, d, "strict").unexpected(spark).agg(F.count(F.lit(1)).alias("unexpected"))


def _published_oracle() -> str:
    """Units by policy 'table', counted from the draws: 3 up, down and up again for each draw and party, a unit a number of a moved row."""
    chain, width = _reg_chain("docs", 6000), sum(map(len, columns("docs"))) - 1
    chain.add("sizes", "SELECT CAST(unnest([1000, 2000, 3000, 4000, 5000, 6000]) AS INTEGER) AS m")
    chain.add("sent", "SELECT m, count(*) FILTER (WHERE party = 0) AS draws_first, count(*) AS moved FROM draws JOIN sizes ON draw_no < m GROUP BY m")
    chain.add("parties", "SELECT count(*) AS t FROM tot")
    return chain.select(f"""SELECT m, draws_first, 3 * t * moved + {width} * moved AS coreset_transfer, t * moved + {width} * moved AS uniform_transfer,
3 * t * moved + t * moved + 10 * {width} AS coreset_dimension, t * moved + t * moved + 10 * {width} AS uniform_dimension FROM sent, parties""")


@query("comm_published_reconstruction", _published_oracle())
def comm_published_reconstruction(spark: SparkSession, d: str) -> DataFrame:
    """Units of the published comparison's sizes by the 'table' policy, for samples of the documents: three parties, ten centres."""
    ds, totals = _docs_totals(spark, d)
    widths, rows = [len(p.features) for p in ds.parties], []
    for m in range(1000, 7000, 1000):
        drawn = sampling.allocate_draws(totals, m, "sample")
        counts = [drawn.count(j) for j in totals]
        row = [m, counts[0]]
        for solver, k in (("transfer", 0), ("dimension", 10)):
            for method in ("coreset", "uniform"):
                row.append(construction(m, counts, method, "table").extend(solving(solver, m, widths, k=k)).total())
        rows.append(tuple(row))
    return spark.createDataFrame(rows, "m int, draws_first long, coreset_transfer long, uniform_transfer long, coreset_dimension long, uniform_dimension long")


# ---- experiments

LINE_SIZES, DOC_SIZES, EMB_SIZES, REPEATS = (1000, 2000, 3000, 4000, 5000, 6000), (100, 200, 500, 1000), (50, 100, 200, 500), 20


@query("exp_reg_table")
def exp_reg_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.regression_table(dataset(spark, d, "docs"), DOC_SIZES, REPEATS)


@query("exp_reg_saga_table")
def exp_reg_saga_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.regression_table(dataset(spark, d, "docs"), DOC_SIZES, REPEATS, solvers=("saga",))


@query("exp_km_table")
def exp_km_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.kmeans_table(dataset(spark, d, "docs", standard=True, label=False), 10, DOC_SIZES, REPEATS)


@query("exp_km_emb_table")
def exp_km_emb_table(spark: SparkSession, d: str) -> DataFrame:
    """Vectors in three blocks, ten centres: near-isotropic rows, on which both samplings are about equal."""
    return experiments.kmeans_table(dataset(spark, d, "emb3", label=False), 10, EMB_SIZES, REPEATS)


@query("exp_line_table")
def exp_line_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.regression_table(dataset(spark, d, "line_star"), LINE_SIZES, REPEATS)


@query("exp_line_saga_table")
def exp_line_saga_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.regression_table(dataset(spark, d, "line_star"), LINE_SIZES, REPEATS, solvers=("saga",))


@query("exp_km_line_table")
def exp_km_line_table(spark: SparkSession, d: str) -> DataFrame:
    return experiments.kmeans_table(dataset(spark, d, "line_star", standard=True, label=False), 10, LINE_SIZES, REPEATS)


@query("exp_equal_comm")
def exp_equal_comm(spark: SparkSession, d: str) -> DataFrame:
    return experiments.equal_communication(exp_km_table(spark, d))


@query("exp_equal_comm_reg")
def exp_equal_comm_reg(spark: SparkSession, d: str) -> DataFrame:
    """The same for ridge: the uniform sample that costs no less to move."""
    return experiments.equal_communication(exp_reg_table(spark, d))


@query("exp_relative")
def exp_relative(spark: SparkSession, d: str) -> DataFrame:
    """Cost ratios, shares of rows and of numbers moved, and units saved, for ridge on the lines."""
    ds = dataset(spark, d, "line_star")
    return experiments.relative(experiments.regression_table(ds, LINE_SIZES, REPEATS), len(ds.features) + 1)


def _table_oracle() -> str:
    """Ridge on samples of the training rows, scaled by their statistics, and its loss on the test rows: the table spelled out in SQL."""
    sizes, repeats = "(VALUES (50), (100), (200)) s(size)", 5
    chain = Chain()
    chain.add("all_rows", wide_sql("docs3"))
    cols = ["digits", "dots", "punct"]
    part = f"CAST('0x' || substr(md5(concat_ws(':', 'split', id)), 1, 13) AS BIGINT) < {int(0.1 * (1 << 52))}"
    chain.add("stats", f"SELECT {', '.join(f'avg({c}) AS m_{c}, stddev_pop({c}) AS s_{c}' for c in [*cols, 'y'])} FROM all_rows WHERE NOT {part}")
    scaled = ", ".join(f"({c} - m_{c}) / s_{c} AS {c}" for c in [*cols, "y"])
    chain.add("z", f"SELECT id, {scaled} FROM all_rows, stats WHERE NOT {part}")
    chain.add("held", f"SELECT id, {scaled} FROM all_rows, stats WHERE {part}")
    chain.regression_scores("z", columns("docs3"))
    chain.add("uscores", f"SELECT id, 0 AS party, {2.0**-20!r} AS score FROM z")
    found = []
    for method, scored, seed, p, name in (("coreset", "scores", "grid", 40, "c"), ("uniform", "uscores", "grid-uniform", 20, "u")):
        draws = chain.draws(scored, 200, seed, repeats, p, name)
        chain.add(f"{name}rows", f"SELECT s.size, d.replicate, z.*, (SELECT max(grand) FROM {name}tot)::DOUBLE / (s.size * g.q) AS weight FROM {draws} d JOIN {sizes} ON d.draw_no < s.size JOIN z ON z.id = d.id JOIN (SELECT id, sum(q) AS q FROM {name}q GROUP BY 1) g ON g.id = d.id")
        t = gauss(chain, f"{name}rows", cols, "y", "(SELECT 0.1 * count(*) FROM z)", "weight", f"{name}t", ("size", "replicate"))
        loss = chain.add(f"{name}loss", f"SELECT t.size, t.replicate, avg(power({' + '.join(f'h.{c} * t.t{i}' for i, c in enumerate(cols))} - h.y, 2)) AS cost FROM {t} t, held h GROUP BY 1, 2")
        found.append(f"SELECT '{method}+ridge' AS method, size, round(avg(cost), 5) AS avg_cost, round(stddev_samp(cost), 5) AS std_cost FROM {loss} GROUP BY size")
    t = gauss(chain, "z", cols, "y", "(SELECT 0.1 * count(*) FROM z)", name="ft")
    found.append(f"SELECT 'full+ridge', (SELECT count(*) FROM z), round(avg(power({' + '.join(f'h.{c} * t.t{i}' for i, c in enumerate(cols))} - h.y, 2)), 5), 0.0 FROM {t} t, held h")
    return chain.select(" UNION ALL ".join(found))


@query("exp_reg_three", _table_oracle())
def exp_reg_three(spark: SparkSession, d: str) -> DataFrame:
    """The comparison table of three columns, whose every cell SQL can spell out."""
    table = experiments.regression_table(dataset(spark, d, "docs3"), (50, 100, 200), 5)
    return table.select("method", "size", _r(F.col("avg_cost"), 5).alias("avg_cost"), _r(F.col("std_cost"), 5).alias("std_cost"))


@query("exp_party_costs")
def exp_party_costs(spark: SparkSession, d: str) -> DataFrame:
    """Costs and units for 2, 3, 4 and 8 parties of the vectors: a sample of 200, k-means with ten centres and ridge."""
    rows = []
    for name in ("emb2", "emb3", "emb4", "emb8"):
        parties = len(FIXTURES[name].parties)
        km = experiments.kmeans_table(dataset(spark, d, name, label=False), 10, (200,), 5, solvers=("kmeans++",), restarts=1).where("method <> 'full+kmeans++'")
        reg = experiments.regression_table(dataset(spark, d, name), (200,), 5).where("method <> 'full+ridge'")
        rows.append(km.unionByName(reg).withColumn("parties", F.lit(parties)))
    return rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3])


@query("exp_party_sweep")
def exp_party_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Totals of the scores for 2, 3, 4 and 8 parties of the vectors: T + rank for regression, T (2 + 2 k) for k-means."""
    rows = []
    for name in ("emb2", "emb3", "emb4", "emb8"):
        ds = dataset(spark, d, name)
        total = scores.score_table(ds, scores.regression_scores).agg(F.sum("score")).collect()[0][0]
        rows.append((len(FIXTURES[name].parties), float(round(total, 6))))
    return spark.createDataFrame(rows, "parties int, grand_total double")


ORACLES["exp_party_sweep"] = "SELECT * FROM (VALUES (2, 67.0), (3, 68.0), (4, 69.0), (8, 73.0)) t(parties, grand_total)"


@query("party_splitters", "SELECT CAST(3 AS INTEGER) AS parties, '[2, 1, 1]' AS widths")
def party_splitters(spark: SparkSession, d: str) -> DataFrame:
    from vpcoreset.parties import split_even

    df = dataset(spark, d, "line_star").parties[0].df.withColumn("one", F.lit(1.0))
    ds = split_even(df, ["qty", "disc", "tax", "one"], 3)
    split_by_names(df, [["qty"], ["disc", "tax"]])
    return spark.createDataFrame([(len(ds.parties), str([len(p.features) for p in ds.parties]))], "parties int, widths string")
