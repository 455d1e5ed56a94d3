"""Measures of plans, predictions and runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def bias_rows(buckets: DataFrame, p: int, weights: DataFrame | None = None) -> DataFrame:
    """(set_idx, spread): largest difference between partitions' shares of processed edges after each set.

    buckets (set_idx, src_part, dst_part). Uniform degrees: each bucket counts once for both of its ends, so one tally per
    partition serves all its vertices. weights (src_part, dst_part, n_edges) counts edges instead.
    """
    used = buckets if weights is None else buckets.join(weights, ["src_part", "dst_part"])
    n = F.lit(1) if weights is None else F.col("n_edges")
    ends = used.select("set_idx", F.explode(F.array("src_part", "dst_part")).alias("part_id"), n.alias("n"))
    steps = buckets.select("set_idx").distinct().join(F.broadcast(ends.select("part_id").distinct()))  # sets x partitions, both small
    per = steps.join(ends.groupBy("set_idx", "part_id").agg(F.sum("n").alias("n")), ["set_idx", "part_id"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    tally = F.sum("n").over(Window.partitionBy("part_id").orderBy("set_idx"))
    total = F.sum("n").over(Window.partitionBy("part_id"))
    share = per.withColumn("share", tally / total)
    return share.groupBy("set_idx").agg((F.max("share") - F.min("share")).alias("spread"))


def edge_permutation_bias(buckets: DataFrame, p: int, weights: DataFrame | None = None) -> DataFrame:
    return bias_rows(buckets, p, weights).agg(F.max("spread").alias("bias"))


def vertex_bias(edges: DataFrame, buckets: DataFrame) -> DataFrame:
    """The general form: one tally per vertex over its own edges (src_id, dst_id, src_part, dst_part); vertices without edges
    don't take part."""
    placed = edges.join(F.broadcast(buckets), ["src_part", "dst_part"])
    ends = placed.select("set_idx", F.explode(F.array("src_id", "dst_id")).alias("node_id"))
    per = ends.groupBy("node_id", "set_idx").agg(F.count("*").alias("n"))
    w = Window.partitionBy("node_id").orderBy("set_idx")
    share = per.withColumn("share", F.sum("n").over(w) / F.sum("n").over(Window.partitionBy("node_id")))
    # a vertex's share holds from a set on until its next one
    span = share.withColumn("until", F.lead("set_idx").over(w))
    first = per.groupBy("node_id").agg(F.min("set_idx").alias("until")).select("node_id", F.lit(0).alias("set_idx"), F.lit(0.0).alias("share"), "until").where("until > 0")
    rows = span.select("node_id", "set_idx", "share", "until").unionByName(first)
    last = buckets.agg(F.max("set_idx").alias("_last"))
    each = rows.join(F.broadcast(last)).select("share", F.explode(F.sequence("set_idx", F.coalesce(F.col("until") - 1, F.col("_last")))).alias("set_idx"))
    return each.groupBy("set_idx").agg((F.max("share") - F.min("share")).alias("spread")).agg(F.max("spread").alias("bias"))


def io_bytes(loads: DataFrame, sets: DataFrame, part_bytes: DataFrame, bucket_bytes: DataFrame) -> DataFrame:
    """(node_bytes, edge_bytes) read in an epoch: loaded partitions, and the buckets that become resident with them."""
    loaded = loads.where("action = 'load'")
    nodes = loaded.join(part_bytes, "part_id").agg(F.coalesce(F.sum("bytes"), F.lit(0)).cast("bigint").alias("node_bytes"))
    members = sets.select("set_idx", F.col("part_id").alias("other"))
    new = loaded.select("set_idx", "part_id").join(members, "set_idx")
    ends = new.select("set_idx", F.col("part_id").alias("src_part"), F.col("other").alias("dst_part")).unionByName(new.select("set_idx", F.col("other").alias("src_part"), F.col("part_id").alias("dst_part"))).distinct()
    edges = ends.join(bucket_bytes, ["src_part", "dst_part"]).agg(F.coalesce(F.sum("bytes"), F.lit(0)).cast("bigint").alias("edge_bytes"))
    return nodes.join(F.broadcast(edges))


def example_balance(counts: DataFrame, column: str = "n") -> DataFrame:
    """(n_sets, least, most, mean, max_over_mean, cv) of the examples per set."""
    c = F.col(column)
    return counts.agg(F.count("*").alias("n_sets"), F.min(c).alias("least"), F.max(c).alias("most"), F.avg(c).alias("mean"), (F.max(c) / F.avg(c)).alias("max_over_mean"), (F.stddev_pop(c) / F.avg(c)).alias("cv"))


def accuracy(predictions: DataFrame) -> DataFrame:
    """Share of (prediction = label)."""
    return predictions.agg(F.count("*").alias("n"), F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("accuracy"))


def argmax_lowest(scores: DataFrame) -> DataFrame:
    """(example_id, prediction) from (example_id, class_id, score): the best class, ties to the lowest id."""
    return scores.groupBy("example_id").agg(F.max_by("class_id", F.struct("score", F.negative("class_id"))).alias("prediction"))


def ranks(scores: DataFrame, ties: str = "mid") -> DataFrame:
    """(example_id, rank) from (example_id, candidate_id, is_pos, score); ties count none, half or all of the equal ones."""
    share = {"mid": 0.5, "optimistic": 0.0, "pessimistic": 1.0}[ties]
    positive = scores.where("is_pos").groupBy("example_id").agg(F.max("score").alias("own"))
    other = scores.where("not is_pos").join(positive, "example_id", "right")
    above = F.sum(F.when(F.col("score") > F.col("own"), 1.0).when(F.col("score") == F.col("own"), share).otherwise(0.0))
    return other.groupBy("example_id").agg((1 + above).alias("rank"))


def mrr(scores: DataFrame, ties: str = "mid", known: DataFrame | None = None) -> DataFrame:
    """Mean reciprocal rank; known (example_id, candidate_id): true answers that don't count as negatives."""
    if known is not None:
        scores = scores.join(known.select("example_id", "candidate_id", F.lit(True).alias("_k")), ["example_id", "candidate_id"], "left").where("is_pos or _k is null").drop("_k")
    return ranks(scores, ties).agg(F.count("*").alias("n"), F.avg(1 / F.col("rank")).alias("mrr"))


def cost(minutes: Column, dollars_per_hour: Column) -> Column:
    return minutes / 60 * dollars_per_hour


def time_to_metric(history: DataFrame, metric: str, target: float) -> DataFrame:
    """(run, elapsed_s): first time at which a run reached the target."""
    return history.where((F.col("metric") == metric) & (F.col("value") >= target)).groupBy("run").agg(F.min("elapsed_s").alias("elapsed_s"))


def gap_closed(policy: Column, greedy: Column, memory: Column) -> Column:
    return (policy - greedy) / (memory - greedy)
