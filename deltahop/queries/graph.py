"""Graph preparation and storage."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltahop import graphs
from deltahop.operators import partitioning as part
from deltahop.plans import tuning
from deltahop.queries.registry import COPURCHASE, CUST_PART, DOCTOKEN, GEO, HYPERLINK, TRADE, TRADE_CORE, mix, query
from deltahop.sources import store

NODES = f"SELECT src_id AS node_id FROM ({TRADE}) UNION SELECT dst_id FROM ({TRADE})"
PART = lambda c, p=16, seed=3: f"CAST({mix(c, seed)} % {p} AS INTEGER)"


def trade(spark, sf_dir):
    return graphs.Graph.from_tables(spark, sf_dir, "trade")


PLAIN = ("src_id", "rel_id", "dst_id")
for _name, _sql in {"trade": TRADE, "copurchase": COPURCHASE, "hyperlink": HYPERLINK, "doctoken": DOCTOKEN, "geo": GEO}.items():
    query(f"graph_{_name}_edges", _sql)(lambda spark, sf_dir, name=_name: graphs.BUILDERS[name](spark, sf_dir).select(*PLAIN))

query(
    "graph_knn_edges",
    """WITH s AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS score FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)
SELECT src * 16 + 10 AS src_id, 0 AS rel_id, dst * 16 + 10 AS dst_id FROM s QUALIFY row_number() OVER (PARTITION BY src ORDER BY score DESC, dst) <= 10""",
)(lambda spark, sf_dir: graphs.knn_edges(spark, sf_dir).select(*PLAIN))

query(
    "graph_event_edges",
    """SELECT user_id * 16 AS src_id, CAST(coalesce(list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type), 0) AS INTEGER) AS rel_id,
CAST(json_extract_string(props, '$.k') AS BIGINT) * 16 + 9 AS dst_id, ts AS edge_ts FROM events""",
)(lambda spark, sf_dir: graphs.event_edges(spark, sf_dir))


@query("part_random_sizes", f"SELECT {PART('node_id')} AS part_id, count(*) AS n FROM ({NODES}) GROUP BY 1")
def part_random_sizes(spark, sf_dir):
    return part.assign_partitions(trade(spark, sf_dir).nodes, 16, 3).groupBy("part_id").agg(F.count("*").alias("n"))


@query("part_balanced_sizes", f"SELECT CAST((row_number() OVER (ORDER BY {mix('node_id', 3)}, node_id) - 1) % 16 AS INTEGER) AS part_id, node_id FROM ({NODES})")
def part_balanced_sizes(spark, sf_dir):
    return part.assign_balanced(trade(spark, sf_dir).nodes, 16, 3).select("part_id", "node_id")


TRAIN = f"SELECT node_id FROM ({NODES}) WHERE {mix('node_id', 5)} % 20 = 0"


@query(
    "part_label_first",
    f"""WITH n AS ({NODES}), t AS ({TRAIN}), cap AS (SELECT ceil(count(*) / 16.0) AS c FROM n), k AS (SELECT CAST(ceil((SELECT count(*) FROM t) / (SELECT c FROM cap)) AS INTEGER) AS k),
r AS (SELECT node_id, row_number() OVER (ORDER BY node_id) - 1 AS r FROM t)
SELECT n.node_id, CAST(CASE WHEN r.r IS NOT NULL THEN floor(r.r / (SELECT c FROM cap)) ELSE (SELECT k FROM k) + {mix('n.node_id', 3)} % (16 - (SELECT k FROM k)) END AS INTEGER) AS part_id FROM n LEFT JOIN r USING (node_id)""",
)
def part_label_first(spark, sf_dir):
    from deltahop import hashing

    nodes = trade(spark, sf_dir).nodes
    train = nodes.where(F.pmod(hashing.mix(F.col("node_id"), 5), F.lit(20)) == 0)
    return part.assign_label_first(nodes, train, 16, 3)[0].select("node_id", "part_id")


@query("edge_bucket_sizes", f"SELECT {PART('src_id')} AS src_part, {PART('dst_id')} AS dst_part, count(*) AS n_edges FROM ({TRADE}) GROUP BY ALL")
def edge_bucket_sizes(spark, sf_dir):
    return part.bucket_sizes(part.bucketed(graphs.trade_edges(spark, sf_dir), 16, 3))


@query("edge_bucket_sizes_joined", f"SELECT {PART('src_id')} AS src_part, {PART('dst_id')} AS dst_part, count(*) AS n_edges FROM ({TRADE}) GROUP BY ALL")
def edge_bucket_sizes_joined(spark, sf_dir):
    g = trade(spark, sf_dir)
    return part.bucket_sizes(part.bucketed_by(g.edges, part.assign_partitions(g.nodes, 16, 3)))


@query("store_roundtrip", f"SELECT src_id, rel_id, dst_id FROM ({TRADE}) WHERE {PART('src_id')} IN (1, 5, 9) AND {PART('dst_id')} IN (1, 5, 9)")
def store_roundtrip(spark, sf_dir):
    g = trade(spark, sf_dir)
    held = store.GraphStore.write(g, 16, 3)
    return held.edges_of([1, 5, 9]).select(*PLAIN)


@query("scan_pruned_bucket", f"SELECT src_id, rel_id, dst_id FROM ({TRADE}) WHERE {PART('src_id', 4)} = 2 AND {PART('dst_id', 4)} = 3")
def scan_pruned_bucket(spark, sf_dir):
    held = store.GraphStore.write(trade(spark, sf_dir), 4, 3)
    return held.bucket(2, 3).select(*PLAIN)


for _d, _end in (("out", "src_id"), ("in", "dst_id")):
    query(f"adj_offsets_{_d}", f"SELECT {_end} AS node_id, count(*) AS degree, CAST(sum(count(*)) OVER (ORDER BY {_end}) - count(*) AS BIGINT) AS start FROM ({TRADE}) GROUP BY 1")(
        lambda spark, sf_dir, d=_d: part.adjacency_offsets(graphs.trade_edges(spark, sf_dir), d)
    )


@query("induced_subgraph_count", f"SELECT count(*) AS n_edges, count(DISTINCT src_id) AS n_src FROM ({TRADE}) WHERE {PART('src_id')} IN (0, 3, 7, 8) AND {PART('dst_id')} IN (0, 3, 7, 8)")
def induced_subgraph_count(spark, sf_dir):
    inside = part.induced(part.bucketed(graphs.trade_edges(spark, sf_dir), 16, 3), [0, 3, 7, 8])
    return inside.agg(F.count("*").alias("n_edges"), F.countDistinct("src_id").alias("n_src"))


@query(
    "logical_group_sizes",
    f"""WITH o AS (SELECT i, ntile(8) OVER (ORDER BY {mix('i', '(11 * 1009 + e)')}, i) - 1 AS g, e FROM range(30) p(i), (VALUES (0)) t(e)),
o1 AS (SELECT i, ntile(8) OVER (ORDER BY {mix('i', '(11 * 1009 + e)')}, i) - 1 AS g, e FROM range(30) p(i), (VALUES (1)) t(e))
SELECT CAST(e AS INTEGER) AS epoch, CAST(i AS INTEGER) AS part_id, CAST(g AS INTEGER) AS logical_id FROM (SELECT * FROM o UNION ALL SELECT * FROM o1)""",
)
def logical_group_sizes(spark, sf_dir):
    rows = [(e, i, g) for e in (0, 1) for g, members in enumerate(part.logical_groups(30, 8, e, 11)) for i in members]
    return spark.createDataFrame(rows, "epoch int, part_id int, logical_id int")


_GRAPHS = {"trade": (TRADE, 50, 12, 2), "copurchase": (COPURCHASE, 2, 8, 1), "hyperlink": (HYPERLINK, 50, 16, 2), "doctoken": (DOCTOKEN, 16, 8, 1)}


@query(
    "graph_memory_table",
    " UNION ALL ".join(
        f"SELECT '{n}' AS graph, v AS n_nodes, e AS n_edges, CAST(v * {d} * 4 * {c} AS BIGINT) AS node_bytes, CAST(e * {b} AS BIGINT) AS edge_bytes FROM (SELECT count(*) AS e, (SELECT count(*) FROM (SELECT src_id FROM ({s}) UNION SELECT dst_id FROM ({s}))) AS v FROM ({s}))"
        for n, (s, d, b, c) in _GRAPHS.items()
    ),
)
def graph_memory_table(spark, sf_dir):
    out = None
    for name, (_, d, b, c) in _GRAPHS.items():
        row = tuning.memory_estimate(graphs.Graph.from_tables(spark, sf_dir, name), d, b, c)
        out = row if out is None else out.unionByName(row)
    return out
