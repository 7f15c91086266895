"""From raw documents to a training mix: five stages, each over all rows that the stage before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpcoreset.llm import decontaminate, mixing, ngram_join, pii, toxicity
from vpcoreset.llm.common import scratch, table


def toxic_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a toxic verdict."""
    return toxicity.reject_toxic(docs, table(spark, sf_dir, "labels"))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every group of near duplicates the document of the least id; of rows that repeat it the least one, rows without id stay."""
    grouped = ngram_join.ngram_join(docs)
    kept = grouped.where(F.col("class_id") == F.col("doc_id")).select("doc_id").distinct()
    named = docs.join(kept, "doc_id", "left_semi")
    rest = [c for c in docs.columns if c != "doc_id"]
    first = named.groupBy("doc_id").agg(F.min(F.struct(*rest)).alias("row")).select("doc_id", "row.*")
    return first.select(docs.columns).unionByName(docs.where(F.col("doc_id").isNull()))


def leaks_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share no passage with a benchmark item."""
    return decontaminate.drop_leaking(docs, table(spark, sf_dir, "benchmark"))


def surrogates_in(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The same documents with surrogates for personal data; n_chars is that of the new text."""
    out = pii.anonymise(docs)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in out.columns else out


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with the copies that the training mix takes of them."""
    return mixing.mix_documents(docs)


STAGES = [
    ("toxicity", toxic_out),
    ("near duplicates", one_of_each_group),
    ("benchmark decontamination", leaks_out),
    ("personal data", surrogates_in),
    ("source mix", mixed),
]

#: The first stage trains a model and the second and third search by hashes; SQL expresses none of them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = scratch(spark, "stage-" + name.replace(" ", "-"))
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
