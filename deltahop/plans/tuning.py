"""Cost model and tuning rules for the numbers of physical and logical partitions and the buffer capacity."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.graphs import Graph


@dataclass(frozen=True)
class Overheads:
    node_bytes: float
    edge_bytes: float

    @classmethod
    def of(cls, n_nodes: int, n_edges: int, dim: int, bytes_per_edge: int) -> Overheads:
        return cls(n_nodes * dim * 4.0, float(n_edges * bytes_per_edge))

    def partition(self, p: int) -> float:
        return self.node_bytes / p

    def bucket(self, p: int) -> float:
        return self.edge_bytes / p**2


def choose_p(o: Overheads, block_bytes: float) -> int:
    """The most partitions whose smallest reads still fill a storage block."""
    return max(1, math.floor(min(o.node_bytes / block_bytes, math.sqrt(o.edge_bytes / block_bytes))))


def choose_c(o: Overheads, p: int, memory_bytes: float, reserve_bytes: float) -> int:
    """The largest buffer: c partitions and both sort orders of their c*c buckets below the memory; 0 if none fits."""
    fits = [c for c in range(1, p + 1) if c * o.partition(p) + 2 * c * c * o.bucket(p) + reserve_bytes < memory_bytes]
    return max(fits, default=0)


def choose_l(p: int, c: int, resident: int = 2) -> int:
    """Fewest logical partitions of which `resident` fit into c physical ones."""
    if c >= p:
        return 1
    n = math.ceil(resident * p / c)
    while n < p and resident * math.ceil(p / n) > c:
        n += 1
    return n


def autotune(o: Overheads, memory_bytes: float, block_bytes: float, reserve_bytes: float) -> dict[str, int]:
    p = choose_p(o, block_bytes)
    c = choose_c(o, p, memory_bytes, reserve_bytes)
    return {"p": p, "c": c, "l": choose_l(p, c) if c else p}


def epoch_cost(n_sets: int, p: int, alpha: float, per_set: float = 1.0) -> float:
    """Modelled epoch time: in proportion to the number of sets, and to p beyond alpha."""
    return n_sets * per_set * max(1.0, p / alpha)


def memory_estimate(graph: Graph, dim: int, bytes_per_edge: int, state_copies: int = 1) -> DataFrame:
    """(graph, n_nodes, n_edges, node_bytes, edge_bytes); learned features carry a second copy as optimiser state."""
    nodes, edges = graph.nodes.agg(F.count("*").alias("n_nodes")), graph.edges.agg(F.count("*").alias("n_edges"))
    both = nodes.join(F.broadcast(edges))  # one row each
    return both.select(F.lit(graph.name).alias("graph"), "n_nodes", "n_edges", (F.col("n_nodes") * dim * 4 * state_copies).alias("node_bytes"), (F.col("n_edges") * bytes_per_edge).alias("edge_bytes"))


def bias_trend(rows: DataFrame) -> DataFrame:
    """Slope of log(bias) over log(x) for each series (series, x, bias): the exponents of the trend model."""
    return rows.where("bias > 0").groupBy("series").agg(F.regr_slope(F.log("bias"), F.log("x")).alias("exponent"))
