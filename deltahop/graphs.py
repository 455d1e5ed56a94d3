"""Graphs built from the given tables. Typed vertex id = raw id * 16 + type code; edges are (src_id, rel_id, dst_id, edge_ts)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltahop.operators.partitioning import ranked

# Type codes and relation ids.
TYPES = {"customer": 0, "part": 1, "supplier": 2, "nation": 3, "region": 4, "document": 5, "token": 6, "page": 7, "target": 8, "item": 9, "vector": 10}
RELATIONS = {"part_supplier": 6, "customer_nation": 7, "supplier_nation": 8, "nation_region": 9}

EDGE_SCHEMA = T.StructType([T.StructField("src_id", T.LongType()), T.StructField("rel_id", T.IntegerType()), T.StructField("dst_id", T.LongType()), T.StructField("edge_ts", T.TimestampNTZType())])
NODE_SCHEMA = T.StructType([T.StructField("node_id", T.LongType()), T.StructField("node_type", T.IntegerType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def typed(raw, kind: str) -> Column:
    return (F.col(raw) if isinstance(raw, str) else raw).cast("bigint") * 16 + TYPES[kind]


def _edges(df: DataFrame, src: Column, rel, dst: Column, ts: Column | None = None) -> DataFrame:
    return df.select(src.alias("src_id"), (rel if isinstance(rel, Column) else F.lit(rel)).cast("int").alias("rel_id"), dst.alias("dst_id"), (ts if ts is not None else F.lit(None)).cast("timestamp_ntz").alias("edge_ts"))


@dataclass
class Graph:
    """nodes (node_id, node_type) and edges (src_id, rel_id, dst_id, edge_ts)."""

    nodes: DataFrame
    edges: DataFrame
    name: str = ""

    @classmethod
    def from_edges(cls, edges: DataFrame, name: str = "") -> Graph:
        """Nodes are the ends of the edges; both ends go through one aggregation."""
        ends = edges.select(F.explode(F.array("src_id", "dst_id")).alias("node_id")).distinct()
        return cls(ends.withColumn("node_type", F.pmod("node_id", F.lit(16)).cast("int")), edges, name)

    @classmethod
    def from_tables(cls, spark: SparkSession, sf_dir: str, name: str) -> Graph:
        return cls.from_edges(BUILDERS[name](spark, sf_dir), name)


def relation_id() -> Column:
    """0-5 for the six pairs of return flag (A, N, R) and line status (F, O)."""
    return (F.instr(F.lit("ANR"), F.col("l_returnflag")) - 1) * 2 + F.instr(F.lit("FO"), F.col("l_linestatus")) - 1


def customer_part_edges(spark, sf_dir, relational: bool = True, distinct: bool = True) -> DataFrame:
    """distinct=False: an edge for every line, for those that tell equal ones apart themselves."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_returnflag", "l_linestatus")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    edges = _edges(joined, typed("o_custkey", "customer"), relation_id() if relational else 0, typed("l_partkey", "part"))
    return edges.distinct() if distinct else edges


def part_supplier_edges(spark, sf_dir, distinct: bool = True) -> DataFrame:
    edges = _edges(table(spark, sf_dir, "lineitem"), typed("l_partkey", "part"), RELATIONS["part_supplier"], typed("l_suppkey", "supplier"))
    return edges.distinct() if distinct else edges


def geo_edges(spark, sf_dir) -> DataFrame:
    customer, supplier, nation = (table(spark, sf_dir, t) for t in ("customer", "supplier", "nation"))
    return (
        _edges(customer, typed("c_custkey", "customer"), RELATIONS["customer_nation"], typed("c_nationkey", "nation"))
        .unionByName(_edges(supplier, typed("s_suppkey", "supplier"), RELATIONS["supplier_nation"], typed("s_nationkey", "nation")))
        .unionByName(_edges(nation, typed("n_nationkey", "nation"), RELATIONS["nation_region"], typed("n_regionkey", "region")))
    )


def trade_edges(spark, sf_dir) -> DataFrame:
    return customer_part_edges(spark, sf_dir).unionByName(part_supplier_edges(spark, sf_dir)).unionByName(geo_edges(spark, sf_dir))


def trade_core_edges(spark, sf_dir, distinct: bool = True) -> DataFrame:
    """Customer-part and part-supplier edges without relations, for the sampling sweeps."""
    return customer_part_edges(spark, sf_dir, False, distinct).unionByName(part_supplier_edges(spark, sf_dir, distinct).withColumn("rel_id", F.lit(0)))


def copurchase_edges(spark, sf_dir, distinct: bool = True) -> DataFrame:
    """Part pairs of one order, both directions. An order has few lines, so the self join is linear in them. distinct=False: one direction
    alone, and a pair for every order."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = lines.withColumnRenamed("l_partkey", "other")
    pairs = lines.join(other, "l_orderkey").where("l_partkey <> other" if distinct else "l_partkey < other").select("l_partkey", "other")
    pairs = pairs.distinct() if distinct else pairs
    return _edges(pairs, typed("l_partkey", "part"), 0, typed("other", "part"))


def document_tokens(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return docs.select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("token")).where("token <> ''").distinct()


def doctoken_edges(spark, sf_dir, hashed: bool = False) -> DataFrame:
    """Document -> token. Token ids: rank among all tokens (small inputs), or 59 bits of a hash (`hashed`, any size)."""
    pairs = document_tokens(spark, sf_dir)
    if hashed:
        token = F.shiftrightunsigned(F.xxhash64("token"), 5)
        return _edges(pairs, typed("doc_id", "document"), 0, typed(token, "token"))
    ids = ranked(pairs.select("token").distinct(), F.substring("token", 1, 2), ["token"], "token_id")  # a prefix follows the order
    return _edges(pairs.join(ids, "token"), typed("doc_id", "document"), 0, typed("token_id", "token"))


def page_links(spark, sf_dir) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "html")
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))


def hyperlink_edges(spark, sf_dir, hashed: bool = False) -> DataFrame:
    links = page_links(spark, sf_dir).distinct()
    if hashed:
        return _edges(links, typed("page_id", "page"), 0, typed(F.shiftrightunsigned(F.xxhash64("href"), 5), "target"))
    ids = ranked(links.select("href").distinct(), F.substring("href", 1, 40), ["href"], "target_id")
    return _edges(links.join(ids, "href"), typed("page_id", "page"), 0, typed("target_id", "target"))


def knn_edges(spark, sf_dir, k: int = 10, block: int = 4096) -> DataFrame:
    """Top k by inner product, ties by id. All vectors are compared in blocks of about `block` queries against blocks of as many vectors;
    a pair of blocks gives k rows a query."""
    import numpy as np
    import pandas as pd

    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    blocks = max(1, -(-vectors.count() // block))
    left = vectors.withColumn("qb", F.pmod("vec_id", F.lit(blocks)).cast("int")).withColumn("vb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("query", F.lit(True))
    right = vectors.withColumn("vb", F.pmod("vec_id", F.lit(blocks)).cast("int")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("query", F.lit(False))

    def nearest(group: pd.DataFrame) -> pd.DataFrame:
        q, v = group[group["query"]], group[~group["query"]].sort_values("vec_id")
        if not len(q) or not len(v):
            return pd.DataFrame({"src": [], "dst": [], "score": []}).astype({"src": "int64", "dst": "int64", "score": "float64"})
        a, b = np.stack(q["embedding"]).astype(np.float64), np.stack(v["embedding"]).astype(np.float64)
        score = np.round(a @ b.T, 9)
        score[q["vec_id"].to_numpy()[:, None] == v["vec_id"].to_numpy()[None]] = -np.inf
        top = np.argsort(-score, axis=1, kind="stable")[:, : k]
        rows = np.repeat(np.arange(len(q)), top.shape[1])
        out = pd.DataFrame({"src": q["vec_id"].to_numpy()[rows], "dst": v["vec_id"].to_numpy()[top.ravel()], "score": score[rows, top.ravel()]})
        return out[np.isfinite(out["score"])]

    near = left.unionByName(right).groupBy("qb", "vb").applyInPandas(nearest, "src bigint, dst bigint, score double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("score"), "dst"))
    return _edges(near.withColumn("rank", rank).where(F.col("rank") <= k), typed("src", "vector"), 0, typed("dst", "vector"))


def event_edges(spark, sf_dir) -> DataFrame:
    """User -> item of props.k, with the event type as relation and the event's time."""
    kinds = ["click", "error", "purchase", "signup", "view"]
    events = table(spark, sf_dir, "events")
    item = F.get_json_object("props", "$.k").cast("bigint")
    rel = F.coalesce(F.array_position(F.array(*map(F.lit, kinds)), F.col("event_type")), F.lit(0))
    return _edges(events, typed("user_id", "customer"), rel, typed(item, "item"), F.col("ts"))


BUILDERS = {"trade": trade_edges, "trade_core": trade_core_edges, "geo": geo_edges, "copurchase": copurchase_edges, "doctoken": doctoken_edges, "hyperlink": hyperlink_edges, "knn": knn_edges, "event": event_edges}
