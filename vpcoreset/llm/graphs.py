"""Connected components of an edge table by least labels with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import stored


def components(edges: DataFrame) -> DataFrame:
    """(node, label) of all nodes of (a, b) edges; label: the least node of the component.

    First every node hands its other neighbours below it to the least one, which leaves one edge a node and those between
    such least ones, whatever the number of parallel paths. Then each round takes the least label among neighbours and the
    label of the label, so paths shrink by halves. Every round is written to the shared folder; only a count of changes reaches the driver.
    """
    down = stored(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "edges-down")
    least = down.groupBy("a").agg(F.min("b").alias("least"))
    handed = down.join(least, "a").where("b <> least").select(F.col("b").alias("a"), F.col("least").alias("b"))
    few = stored(least.withColumnRenamed("least", "b").unionByName(handed).distinct(), "edges-few")
    both = stored(few.unionByName(few.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("b")).select("node", F.least("node", "b").alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        new = labels.join(near, "node").select("node", F.least("label", "near").alias("label"), F.col("label").alias("old"))
        far = labels.select(F.col("node").alias("label"), F.col("label").alias("far"))
        new = stored(new.join(far, "label").select("node", F.least("label", "far").alias("label"), "old"), "labels")
        if not new.where(F.col("label") != F.col("old")).limit(1).count():
            return new.select("node", "label")
        labels = new.select("node", "label")
