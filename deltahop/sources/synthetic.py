"""Synthetic graphs with hubs, as a plan over spark.range and as a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from deltahop import hashing

SCHEMA = "src_id bigint, rel_id int, dst_id bigint, edge_ts timestamp_ntz"


def hub_graph(spark: SparkSession, n_nodes: int, n_edges: int, exponent: float = 2.0, relations: int = 1, seed: int = 0, parts: int | None = None) -> DataFrame:
    """Edges with uniform sources; destination n * u**exponent, so low ids are hubs. Generated in the executors, no shuffle."""
    e = spark.range(0, n_edges, 1, parts) if parts else spark.range(n_edges)
    unit = lambda k: hashing.mix(F.col("id"), seed * 7 + k) / hashing.MIX_PRIME
    return e.select(
        F.floor(unit(1) * n_nodes).alias("src_id"),
        F.pmod(hashing.mix(F.col("id"), seed * 7 + 3), F.lit(relations)).cast("int").alias("rel_id"),
        F.floor(F.pow(unit(2), F.lit(exponent)) * n_nodes).alias("dst_id"),
        F.lit(None).cast("timestamp_ntz").alias("edge_ts"),
    )


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.nodes, self.edges = int(options.get("nodes", 1000)), int(options.get("edges", 10000))
        self.exponent, self.relations = float(options.get("exponent", 2.0)), int(options.get("relations", 1))
        self.seed, self.parts = int(options.get("seed", 0)), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.edges // self.parts)
        return [_Range(a, min(a + step, self.edges)) for a in range(0, self.edges, step)]

    def read(self, partition: _Range):
        prime, n = hashing.MIX_PRIME, self.nodes
        for i in range(partition.low, partition.high):
            a, b, c = (hashing.mix_int(i, self.seed * 7 + k) for k in (1, 2, 3))
            yield int(a / prime * n), c % self.relations, int((b / prime) ** self.exponent * n), None


class SyntheticGraph(DataSource):
    """spark.read.format('synthetic_graph').option('nodes', ..).option('edges', ..).load(); the edges equal hub_graph's."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_graph"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticGraph)
