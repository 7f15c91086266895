"""One query for each operator over its whole table, and the SQL twins of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset.llm import decontaminate, language_model, licenses, mixing, neighbours, ngram_join, pii, secrets, toxicity, warc
from vpcoreset.llm.common import table


def op1_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_model.score_documents(table(spark, sf_dir, "documents"))


def op2_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.ngram_join(table(spark, sf_dir, "documents"))


def op4_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.nearest(table(spark, sf_dir, "embeddings"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_round_trip(table(spark, sf_dir, "pages"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_secrets(table(spark, sf_dir, "documents"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.pareto_mix(table(spark, sf_dir, "documents"))


def mix_by_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mix with unequal inclusion inside a source: documents labelled of quality 1 at ten times the rate of those of 0, others between."""
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    rows = table(spark, sf_dir, "documents").join(labels, "doc_id", "left")
    weight = F.when(F.col("quality") == 1, 5.0).when(F.col("quality") == 0, 0.5).otherwise(1.0)
    return mixing.pareto_mix(rows.withColumn("importance", weight), importance="importance")


def op10_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.anonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), found_col="entities")


QUERIES = {f.__name__: f for f in (
    op1_language_model, op2_benchmark_leaks, op3_ngram_join, op4_nearest, op5_toxicity, op6_warc_archive, op7_secret_scan, op8_license_scan, op9_source_mix, op10_pii_surrogates, mix_by_quality)}
ORACLES = {"op6_warc_archive": warc.WARC_SQL, "op7_secret_scan": secrets.secrets_sql(), "op8_license_scan": licenses.licenses_sql(), "op9_source_mix": mixing.mix_sql(),
    "mix_by_quality": mixing.mix_sql("CASE quality WHEN 1 THEN 5.0 WHEN 0 THEN 0.5 ELSE 1.0 END", " LEFT JOIN (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY 1) USING (doc_id)")}
