"""Mini batches of a set's examples in random order."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop import hashing
from deltahop.operators.partitioning import ranked


def examples_of_sets(edges: DataFrame, buckets: DataFrame) -> DataFrame:
    """Edges (with src_part, dst_part) and the set that trains them; the plan has p*p rows, so it is broadcast."""
    return edges.join(F.broadcast(buckets), ["src_part", "dst_part"])


def exact_batches(edges: DataFrame, size: int, seed: int, epoch: int, by: list[str] | None = None) -> DataFrame:
    """Batches of exactly `size` examples in hash order within each group of `by` (e.g. set_idx)."""
    keyed = edges.withColumn("_key", hashing.priority(seed, epoch, F.col("src_id"), F.coalesce("rel_id", F.lit(0)), F.col("dst_id")))
    placed = ranked(keyed, F.substring("_key", 1, 2), ["_key", "src_id", "dst_id"], "_place", tuple(by or ()))
    return placed.withColumn("batch_id", F.floor(F.col("_place") / size)).drop("_key", "_place")


def hashed_batches(edges: DataFrame, n_batches: int, seed: int) -> DataFrame:
    """About equal batches without any sort: the batch is a hash of the edge."""
    return edges.withColumn("batch_id", F.pmod(hashing.mix(F.col("dst_id") + F.col("src_id"), seed), F.lit(n_batches)).cast("bigint"))
