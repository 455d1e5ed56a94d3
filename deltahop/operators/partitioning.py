"""Physical partitions of vertices, edge buckets, sorted adjacency, subgraphs of resident partitions.

The random partition of a vertex is a function of its id, so assigning it, or finding an edge's bucket, needs no join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltahop import hashing


def random_part(node: Column | str, p: int, seed: int) -> Column:
    return F.pmod(hashing.mix(F.col(node) if isinstance(node, str) else node, seed), F.lit(p)).cast("int")


def assign_partitions(nodes: DataFrame, p: int, seed: int = 0) -> DataFrame:
    return nodes.withColumn("part_id", random_part("node_id", p, seed))


def ranked(df: DataFrame, part: Column, order: list, name: str = "rank", by: tuple[str, ...] = ()) -> DataFrame:
    """Adds the 0-based place of each row in the given order, within groups of `by`. part: a non-decreasing function of the order,
    so that no task sorts more than the rows of one part; the counts of the parts before go through one small prefix sum."""
    keyed = df.withColumn("_s", part)
    counts = keyed.groupBy(*by, "_s").agg(F.count("*").alias("_n"))
    before = counts.select(*by, "_s", (F.sum("_n").over(Window.partitionBy(*(by or (F.lit(0),))).orderBy("_s")) - F.col("_n")).alias("_before"))
    within = F.row_number().over(Window.partitionBy(*by, "_s").orderBy(*order)) - 1
    return keyed.withColumn("_r", within).join(before, [*by, "_s"]).withColumn(name, (F.col("_before") + F.col("_r")).cast("bigint")).drop("_s", "_r", "_before")


def hash_ranked(nodes: DataFrame, seed, name: str = "rank", slices: int = 64) -> DataFrame:
    """Places in the order of (hash, node_id)."""
    key = hashing.mix(F.col("node_id"), seed)
    keyed = nodes.withColumn("_h", key)
    return ranked(keyed, F.floor(F.col("_h") * slices / hashing.MIX_PRIME).cast("int"), ["_h", "node_id"], name).drop("_h")


def assign_balanced(nodes: DataFrame, p: int, seed: int = 0, slices: int = 64) -> DataFrame:
    """Sizes differ by one at most: ranks in hash order, modulo p."""
    return hash_ranked(nodes, seed, "_rank", slices).withColumn("part_id", F.pmod("_rank", F.lit(p)).cast("int")).drop("_rank")


def assign_label_first(nodes: DataFrame, train: DataFrame, p: int, seed: int = 0, capacity: int | None = None) -> tuple[DataFrame, int]:
    """Training vertices fill partitions 0..k-1 in id order, the others go to k..p-1 at random. Returns (nodes, k)."""
    n_train = train.select("node_id").distinct().count()
    capacity = capacity or max(1, -(-nodes.count() // p))
    k = -(-n_train // capacity)
    if k >= p and n_train:
        raise ValueError("training vertices leave no partition for the others")
    placed = ranked(train.select("node_id").distinct(), F.floor(F.col("node_id") / (1 << 14)), ["node_id"], "_place")
    rest = F.lit(k) + random_part("node_id", p - k, seed)
    part = F.coalesce(F.floor(F.col("_place") / capacity).cast("int"), rest.cast("int"))
    return nodes.join(placed, "node_id", "left").withColumn("part_id", part).drop("_place"), k


def bucketed(edges: DataFrame, p: int, seed: int = 0) -> DataFrame:
    """Adds src_part and dst_part of the random assignment without any join."""
    return edges.withColumns({"src_part": random_part("src_id", p, seed), "dst_part": random_part("dst_id", p, seed)})


def bucketed_by(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """The same for any assignment (node_id, part_id), by two joins."""
    side = lambda end: parts.select(F.col("node_id").alias(f"{end}_id"), F.col("part_id").alias(f"{end}_part"))
    return edges.join(side("src"), "src_id").join(side("dst"), "dst_id")


def bucket_sizes(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src_part", "dst_part").agg(F.count("*").alias("n_edges"))


def adjacency(edges: DataFrame, direction: str = "out", relational: bool = False) -> DataFrame:
    """(node_id, nbr_id[, rel_id]) for outgoing, incoming, or undirected ('any') neighbours."""
    rel = ["rel_id"] if relational else []
    out = edges.select(F.col("src_id").alias("node_id"), F.col("dst_id").alias("nbr_id"), *rel)
    into = edges.select(F.col("dst_id").alias("node_id"), F.col("src_id").alias("nbr_id"), *rel)
    if direction == "any":
        return out.unionByName(into).distinct()
    return (out if direction == "out" else into).distinct()


def packed_adjacency(adj: DataFrame) -> DataFrame:
    """(node_id, nbrs) with sorted neighbour arrays."""
    return adj.groupBy("node_id").agg(F.array_sort(F.collect_list("nbr_id")).alias("nbrs"))


def adjacency_offsets(edges: DataFrame, direction: str) -> DataFrame:
    """(node_id, degree, start): where each vertex's edges begin in the edge list sorted by it.

    The running sum is over vertices of one slice of the id order, after a prefix sum over the slices.
    """
    end = "src_id" if direction == "out" else "dst_id"
    degree = edges.groupBy(F.col(end).alias("node_id")).agg(F.count("*").alias("degree"))
    sliced = degree.withColumn("_s", F.floor(F.col("node_id") / (1 << 14)))
    totals = sliced.groupBy("_s").agg(F.sum("degree").alias("_n"))
    before = totals.select("_s", (F.sum("_n").over(Window.partitionBy(F.lit(0)).orderBy("_s")) - F.col("_n")).alias("_before"))
    own = F.sum("degree").over(Window.partitionBy("_s").orderBy("node_id")) - F.col("degree")
    return sliced.withColumn("_own", own).join(before, "_s").select("node_id", "degree", (F.col("_before") + F.col("_own")).cast("bigint").alias("start"))


def induced(edges: DataFrame, parts: list[int]) -> DataFrame:
    """Edges whose ends are both in the resident partitions; on a partitioned store this prunes directories."""
    return edges.where(F.col("src_part").isin(parts) & F.col("dst_part").isin(parts))


def logical_groups(p: int, n_logical: int, epoch: int, seed: int) -> list[list[int]]:
    """Physical partitions in hash order, cut into runs whose sizes differ by one at most; data isn't moved."""
    order = sorted(range(p), key=lambda i: (hashing.mix_int(i, seed * 1009 + epoch), i))
    size, extra = divmod(p, n_logical)
    out, at = [], 0
    for g in range(n_logical):
        n = size + (g < extra)
        out.append(sorted(order[at : at + n]))
        at += n
    return out
