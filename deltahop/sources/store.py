"""Partitioned storage of a graph, read by resident sets of partitions.

Edges: a directory per source partition, sorted by destination partition within files, so a bucket is a pruned directory
plus row groups skipped by statistics (p**2 directories would strain listing). Nodes: a directory per partition and version;
a set's partitions are written as a new version and read from there on, so a run that breaks off leaves the old ones whole.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from deltahop.graphs import Graph
from deltahop.operators.partitioning import assign_partitions, bucketed
from deltahop.operators.storage import drop, shared_path
from deltahop.plans.policy import Plan


@dataclass
class GraphStore:
    spark: SparkSession
    path: str
    p: int
    edge_schema: str = "src_id bigint, rel_id int, dst_id bigint, edge_ts timestamp_ntz, dst_part int, src_part int"
    version: dict[int, int] = field(default_factory=dict)
    node_schema: StructType | None = None
    log: list[tuple[int, int, str, int]] = field(default_factory=list)  # (set, partition, load or evict, bytes of its vertices)

    @classmethod
    def write(cls, graph: Graph, p: int, seed: int = 0, path: str | None = None, vectors: DataFrame | None = None) -> GraphStore:
        """vectors: (node_id, h[, s]) to keep with the vertices; the state s starts at zeros."""
        spark = graph.edges.sparkSession
        store = cls(spark, path or shared_path(spark, "graph"), p)
        edges = bucketed(graph.edges, p, seed).select("src_id", "rel_id", "dst_id", "edge_ts", "dst_part", "src_part")
        edges.repartition("src_part").sortWithinPartitions("src_part", "dst_part").write.partitionBy("src_part").parquet(f"{store.path}/edges")
        nodes = assign_partitions(graph.nodes, p, seed)
        if vectors is not None:
            vectors = vectors if "s" in vectors.columns else vectors.withColumn("s", F.transform("h", lambda x: x * 0.0))
            nodes = nodes.join(vectors, "node_id")
        store.update_nodes(nodes)
        return store

    def _folder(self, part: int) -> str:
        return f"{self.path}/nodes/v{self.version[part]}/part_id={part}"

    def _files(self, path: str):
        target = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return target, target.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def edges(self) -> DataFrame:
        return self.spark.read.schema(self.edge_schema).parquet(f"{self.path}/edges")

    def nodes(self) -> DataFrame:
        return self.nodes_of(sorted(self.version))

    def bucket(self, i: int, j: int) -> DataFrame:
        return self.edges().where((F.col("src_part") == i) & (F.col("dst_part") == j))

    def edges_of(self, parts: list[int]) -> DataFrame:
        """The subgraph of a resident set."""
        return self.edges().where(F.col("src_part").isin(parts) & F.col("dst_part").isin(parts))

    def nodes_of(self, parts: list[int]) -> DataFrame:
        """Vertices of the partitions, from the newest version of each; no other folder is listed or read."""
        out = None
        for v in sorted({self.version[q] for q in parts if q in self.version}):
            folders = [self._folder(q) for q in parts if self.version.get(q) == v]
            rows = self.spark.read.schema(self.node_schema).option("basePath", f"{self.path}/nodes/v{v}").parquet(*folders)
            out = rows if out is None else out.unionByName(rows)
        return out

    def node_bytes(self, part: int) -> int:
        if part not in self.version:  # a partition without vertices has no folder
            return 0
        target, files = self._files(self._folder(part))
        return int(files.getContentSummary(target).getLength())

    def move_to(self, x: int, before: list[int], now: list[int]) -> None:
        """Log what a change of the resident set reads and lets go."""
        self.log += [(x, q, "evict", 0) for q in before if q not in now] + [(x, q, "load", self.node_bytes(q)) for q in now if q not in before]

    def update_nodes(self, nodes: DataFrame) -> None:
        """Replace the partitions that `nodes` holds, and no others."""
        fresh = max(self.version.values(), default=-1) + 1
        self.node_schema = nodes.schema  # saves reading the footers
        nodes.repartition("part_id").write.partitionBy("part_id").parquet(f"{self.path}/nodes/v{fresh}")
        target, files = self._files(f"{self.path}/nodes/v{fresh}")
        for status in files.listStatus(target):
            name = status.getPath().getName()
            if name.startswith("part_id="):
                part = int(name[8:])
                if part in self.version:
                    drop(self.spark, self._folder(part))
                self.version[part] = fresh


def write_plan(spark: SparkSession, plan: Plan, path: str | None = None) -> str:
    """Write a plan's tables (sets, buckets, loads) for other programs; returns the folder."""
    path = path or shared_path(spark, "plan")
    for name, rows in (("sets", plan.sets_df(spark)), ("buckets", plan.buckets_df(spark)), ("loads", plan.loads_df(spark))):
        rows.coalesce(1).write.mode("overwrite").parquet(f"{path}/{name}")
    return path


def read_plan(spark: SparkSession, path: str) -> dict[str, DataFrame]:
    return {name: spark.read.parquet(f"{path}/{name}") for name in ("sets", "buckets", "loads")}


def write_metrics(rows: DataFrame, path: str) -> None:
    """Put rows (run, epoch, elapsed_s, metric, value) in place of those of the same runs; other runs stay."""
    rows.repartition("run").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run").parquet(path)


def write_bucketed(edges: DataFrame, name: str, n: int = 8) -> DataFrame:
    """A table bucketed and sorted by source, which later joins and aggregations on src_id read without an exchange."""
    edges.write.mode("overwrite").bucketBy(n, "src_id").sortBy("src_id").saveAsTable(name)
    return edges.sparkSession.table(name)


def text_round_trip(edges: DataFrame, kind: str, path: str | None = None) -> DataFrame:
    """Write plain edges (src_id, rel_id, dst_id) as csv, json, orc or text and read them back with a fixed schema."""
    spark = edges.sparkSession
    path = path or shared_path(spark, f"edges-{kind}")
    schema = "src_id bigint, rel_id int, dst_id bigint"
    plain = edges.select("src_id", "rel_id", "dst_id")
    if kind == "text":
        plain.select(F.concat_ws("\t", "src_id", "rel_id", "dst_id").alias("value")).write.text(path)
        parts = F.split("value", "\t")
        return spark.read.text(path).select(parts[0].cast("bigint").alias("src_id"), parts[1].cast("int").alias("rel_id"), parts[2].cast("bigint").alias("dst_id"))
    plain.write.format(kind).save(path)
    return spark.read.format(kind).schema(schema).load(path)
