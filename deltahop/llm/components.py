"""Connected components of a link table, without bringing links to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.llm.workdir import drop_path, release, stored


def connected_components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links (a, b) of longs -> (node, comp) with comp the smallest node of the component; linked nodes only.

    Every round each node takes the smallest label among its neighbours, then the label of its label; minima are
    combined before each shuffle, so a hub costs one row per task. Rounds end when no label changes.
    """
    both = links.select(F.col("a").alias("u"), F.col("b").alias("v")).where("u <> v")
    edges, edge_path = stored(both.unionByName(both.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "cc-edges")
    labels, path = stored(edges.groupBy(F.col("u").alias("node")).agg(F.least(F.min("v"), F.min("u")).alias("comp")), "cc-labels")
    for _ in range(most_rounds):
        near = edges.join(labels.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node")).agg(F.min("comp").alias("near"))
        lower = labels.join(near, "node").select("node", "comp", F.least("comp", "near").alias("low"))
        of = labels.select(F.col("node").alias("low"), F.col("comp").alias("jump"))
        step, next_path = stored(lower.join(of, "low").select("node", F.least("low", "jump").alias("comp"), (F.least("low", "jump") < F.col("comp")).alias("moved")), "cc-labels")
        moved = step.where("moved").limit(1).count()
        drop_path(links.sparkSession, path)
        labels, path = step.select("node", "comp"), next_path
        if not moved:
            drop_path(links.sparkSession, edge_path)
            release(links.sparkSession)
            return labels
    raise RuntimeError("labels still change after the most rounds allowed")
