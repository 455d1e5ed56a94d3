"""A facade over the modules: one object that holds a graph, its partitions and its choices."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltahop.graphs import Graph
from deltahop.operators import packing
from deltahop.operators import partitioning as part
from deltahop.operators import sampling as sp
from deltahop.plans import metrics, policy, tuning
from deltahop.train import Trainer


@dataclass
class Engine:
    graph: Graph
    parts: DataFrame | None = None
    p: int = 1
    label_parts: int = 0
    choices: dict = field(default_factory=dict)

    @classmethod
    def from_tables(cls, spark: SparkSession, sf_dir: str, name: str) -> Engine:
        return cls(Graph.from_tables(spark, sf_dir, name))

    def partition(self, p: int, how: str = "random", seed: int = 0, train: DataFrame | None = None) -> Engine:
        """how: random, balanced or label_first (with train)."""
        nodes = self.graph.nodes
        if how == "label_first":
            parts, k = part.assign_label_first(nodes, train, p, seed)
        else:
            parts, k = (part.assign_balanced if how == "balanced" else part.assign_partitions)(nodes, p, seed), 0
        return Engine(self.graph, parts, p, k, self.choices)

    def autotune(self, memory_bytes: float, block_bytes: float, dim: int, bytes_per_edge: int = 12, reserve_bytes: float = 0) -> dict[str, int]:
        o = tuning.Overheads.of(self.graph.nodes.count(), self.graph.edges.count(), dim, bytes_per_edge)
        self.choices = tuning.autotune(o, memory_bytes, block_bytes, reserve_bytes)
        return self.choices

    def plan(self, how: str, c: int, n_logical: int | None = None, epoch: int = 0, seed: int = 0, tie: str = "lowest") -> policy.Plan:
        """how: full, greedy, two_level, label_cache or cover."""
        n_logical = n_logical or tuning.choose_l(self.p, c)
        makers = {
            "full": lambda: policy.plan_full(self.p),
            "greedy": lambda: policy.plan_greedy(self.p, c, tie, seed),
            "two_level": lambda: policy.plan_two_level(self.p, n_logical, c, epoch, seed, tie),
            "label_cache": lambda: policy.plan_label_cache(self.label_parts, c, self.p, epoch, seed),
            "cover": lambda: policy.plan_random_cover(self.p, n_logical, c, epoch, seed),
        }
        return makers[how]()

    def resident(self, members: list[int]) -> Graph:
        """The subgraph of resident partitions."""
        return Graph(self.parts.where(F.col("part_id").isin(members)), part.induced(part.bucketed_by(self.graph.edges, self.parts), members), self.graph.name)

    def sample(self, targets: DataFrame, fanouts: list, direction: str = "any", sampler: str = "delta", salt: sp.Salt = sp.Salt()):
        """A Sample for 'delta'; tables of edges or vertices for 'layer_resample', 'path' and 'exact'."""
        adj = part.adjacency(self.graph.edges, direction)
        return {
            "delta": lambda: sp.delta_sample(targets, adj, fanouts, salt),
            "layer_resample": lambda: sp.layer_resample(targets, adj, fanouts, salt),
            "path": lambda: sp.path_sample(targets, adj, fanouts, salt),
            "exact": lambda: sp.khop_exact(targets, adj, len(fanouts)),
        }[sampler]()

    pack = staticmethod(packing.pack)


def evaluate(trainer: Trainer, params: dict, edges: DataFrame, h0: DataFrame, test: DataFrame) -> DataFrame:
    """(metric, value): accuracy of labelled vertices, or mean reciprocal rank of edges."""
    if trainer.model.head == "softmax":
        return metrics.accuracy(trainer.predict_nodes(params, edges, h0, test)).select(F.lit("accuracy").alias("metric"), F.col("accuracy").alias("value"))
    return trainer.rank_links(params, edges, h0, test).agg(F.avg(1 / F.col("rank")).alias("value")).select(F.lit("mrr").alias("metric"), "value")
