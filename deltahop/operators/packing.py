"""Packed arrays of a delta sample, rows of layer inputs, and trimming after a layer.

Positions: vertex_ids holds group 0 (outermost) first and the targets last, ascending ids within a group; offsets are starts
without a final total.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltahop.operators.sampling import Sample


def positions(sample: Sample) -> DataFrame:
    """nodes with pos, the vertex's place in vertex_ids of its batch."""
    order = Window.partitionBy("batch_id").orderBy("delta_idx", "node_id")
    return sample.nodes.withColumn("pos", F.row_number().over(order) - 1)


def group_starts(sample: Sample) -> DataFrame:
    """(batch_id, delta_idx, group_start, n), empty groups included."""
    batches = sample.nodes.select("batch_id").distinct().withColumn("delta_idx", F.explode(F.sequence(F.lit(0), F.lit(sample.k))))
    n = sample.nodes.groupBy("batch_id", "delta_idx").agg(F.count("*").alias("n"))
    full = batches.join(n, ["batch_id", "delta_idx"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    start = F.sum("n").over(Window.partitionBy("batch_id").orderBy("delta_idx")) - F.col("n")
    return full.select("batch_id", "delta_idx", start.alias("group_start"), "n")


def neighbour_positions(sample: Sample) -> DataFrame:
    """(batch_id, node_id, node_pos, nbr_rank, nbr_id, repr_pos, nbr_pos): for each entry of nbr_ids its place (nbr_pos) and the
    row of the layer input that holds the neighbour (repr_pos)."""
    pos = positions(sample).select("batch_id", "node_id", "pos", "delta_idx")
    own = sample.nbrs.drop("delta_idx").join(pos.withColumnRenamed("pos", "node_pos"), ["batch_id", "node_id"])
    nbr = pos.select("batch_id", F.col("node_id").alias("nbr_id"), F.col("pos").alias("repr_pos"))
    place = F.row_number().over(Window.partitionBy("batch_id").orderBy("node_pos", "nbr_rank")) - 1
    return own.join(nbr, ["batch_id", "nbr_id"]).withColumn("nbr_pos", place).select("batch_id", "delta_idx", "node_id", "node_pos", "nbr_rank", "nbr_id", "repr_pos", "nbr_pos")


def neighbour_starts(sample: Sample) -> DataFrame:
    """(batch_id, node_id, nbr_start, n_nbrs) of every vertex outside group 0."""
    pos = positions(sample).where("delta_idx > 0")
    n = sample.nbrs.groupBy("batch_id", "node_id").agg(F.count("*").alias("n_nbrs"))
    full = pos.join(n, ["batch_id", "node_id"], "left").withColumn("n_nbrs", F.coalesce("n_nbrs", F.lit(0)))
    start = F.sum("n_nbrs").over(Window.partitionBy("batch_id").orderBy("pos")) - F.col("n_nbrs")
    return full.select("batch_id", "node_id", "pos", start.alias("nbr_start"), "n_nbrs")


def trim(sample: Sample, layer: int) -> Sample:
    """What layers after `layer` need: groups layer.. and the neighbours of groups above it."""
    return Sample(sample.nodes.where(F.col("delta_idx") >= layer), sample.nbrs.where(F.col("delta_idx") > layer), sample.k)


def pack(sample: Sample) -> DataFrame:
    """One row a batch: batch_id and five arrays. Batches of this form must fit a task; larger ones stay relational."""
    pos = positions(sample)
    ids = pos.groupBy("batch_id").agg(F.array_sort(F.collect_list(F.struct("pos", "node_id"))).alias("v"))
    starts = group_starts(sample).groupBy("batch_id").agg(F.array_sort(F.collect_list(F.struct("delta_idx", "group_start"))).alias("g"))
    if sample.nbrs is None:  # no hop: the targets alone
        none = F.expr("cast(array() as array<bigint>)")
        longs = lambda c: F.transform(c, lambda x: x.cast("bigint"))
        return ids.join(starts, "batch_id").select("batch_id", longs(F.col("g.group_start")).alias("group_starts"), longs(F.col("v.node_id")).alias("vertex_ids"), *(none.alias(c) for c in ("nbr_starts", "nbr_ids", "input_rows")))
    nbr = neighbour_positions(sample)
    offsets = neighbour_starts(sample).groupBy("batch_id").agg(F.array_sort(F.collect_list(F.struct("pos", "nbr_start"))).alias("o"))
    entries = nbr.groupBy("batch_id").agg(F.array_sort(F.collect_list(F.struct("nbr_pos", "nbr_id", "repr_pos"))).alias("n"))
    out = ids.join(starts, "batch_id").join(offsets, "batch_id", "left").join(entries, "batch_id", "left")
    longs = lambda c: F.coalesce(F.transform(c, lambda x: x.cast("bigint")), F.expr("cast(array() as array<bigint>)"))
    return out.select(
        "batch_id",
        longs(F.col("g.group_start")).alias("group_starts"),
        longs(F.col("v.node_id")).alias("vertex_ids"),
        longs(F.col("o.nbr_start")).alias("nbr_starts"),
        longs(F.col("n.nbr_id")).alias("nbr_ids"),
        longs(F.col("n.repr_pos")).alias("input_rows"),
    )


@dataclass
class Packed:
    """The five arrays of one batch in numpy."""

    group_starts: np.ndarray
    vertex_ids: np.ndarray
    nbr_starts: np.ndarray
    nbr_ids: np.ndarray
    input_rows: np.ndarray

    @classmethod
    def of(cls, row) -> Packed:
        return cls(*(np.asarray(row[c], np.int64) for c in ("group_starts", "vertex_ids", "nbr_starts", "nbr_ids", "input_rows")))

    @property
    def outputs(self) -> slice:
        """Rows of the layer input that are also outputs: all but the first group."""
        return slice(int(self.group_starts[1]) if len(self.group_starts) > 1 else 0, None)

    def lengths(self) -> np.ndarray:
        return np.diff(np.append(self.nbr_starts, len(self.nbr_ids)))

    def trimmed(self) -> Packed:
        """Without the first group and without the neighbour lists of the second."""
        starts = self.group_starts
        dropped = int(starts[1])
        second = int(starts[2]) - dropped if len(starts) > 2 else len(self.vertex_ids) - dropped
        cut = int(self.nbr_starts[second]) if second < len(self.nbr_starts) else len(self.nbr_ids)
        return Packed(starts[1:] - dropped, self.vertex_ids[dropped:], self.nbr_starts[second:] - cut, self.nbr_ids[cut:], self.input_rows[cut:] - dropped)


def segment_sum(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sums of consecutive rows; segment i begins at starts[i], an empty segment gives zeros."""
    ends = np.append(starts[1:], len(values))
    out = np.zeros((len(starts), *values.shape[1:]), values.dtype)
    full = np.flatnonzero(ends > starts)
    if len(full):
        out[full] = np.add.reduceat(values, starts[full], axis=0)
    return out
