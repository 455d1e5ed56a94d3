"""Samples, baselines and packed arrays. The oracles build the hops as a chain of common table expressions.

Every customer, or every part, is a target: an epoch of batches of 1000 targets in one plan.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from deltahop import graphs
from deltahop.operators import packing
from deltahop.operators import partitioning as part
from deltahop.operators import sampling as s
from deltahop.operators.storage import stored
from deltahop.queries.registry import ADJ, TRADE, TRADE_CORE, mix, query

BATCH = 1000  # targets
TYPE = {"core": (graphs.trade_core_edges, "any"), "copurchase": (graphs.copurchase_edges, "out")}


def adjacency(spark, sf_dir, name):
    build, direction = TYPE[name]
    return part.adjacency(build(spark, sf_dir), direction)


def targets(spark, sf_dir, name):
    raw = graphs.table(spark, sf_dir, "customer" if name == "core" else "part")
    key = "c_custkey" if name == "core" else "p_partkey"
    node = graphs.typed(key, "customer" if name == "core" else "part")
    return raw.select(F.floor(F.col(key) / BATCH).cast("int").alias("batch_id"), node.alias("node_id"))


def lists(spark, sf_dir, name):
    """The adjacency as lists for samplers that write no hop."""
    return s.lists_of(TYPE[name][0](spark, sf_dir, distinct=False), "any", targets(spark, sf_dir, name))


def sql_targets(name):
    key, base, code = ("c_custkey", "customer", 0) if name == "core" else ("p_partkey", "part", 1)
    return f"SELECT CAST(floor({key} / {BATCH}) AS INTEGER) AS batch_id, {key} * 16 + {code} AS node_id FROM {base}"


def sql_hop(frontier: str, adj: str, fanout: int | None, hop: int | None = None, rel: bool = False) -> str:
    h = f", {hop}" if hop is not None else ""
    r, rc = (", a.rel_id", ", rel_id") if rel else ("", "")
    limit = f" WHERE nbr_rank <= {fanout}" if fanout is not None else ""
    return f"""SELECT * FROM (SELECT f.batch_id, f.node_id, a.nbr_id{r}, row_number() OVER (PARTITION BY f.batch_id, f.node_id ORDER BY md5(concat_ws(':', 7, 0, f.batch_id{h}, f.node_id, a.nbr_id{r})), a.nbr_id{r}) AS nbr_rank
FROM {frontier} f JOIN {adj} a ON a.node_id = f.node_id){limit}"""


def sql_delta(name, fanouts, adj=None, start=None) -> str:
    """CTEs adj, d<k>..d0 (batch_id, node_id) and e<k>..e1 (batch_id, node_id, nbr_id, nbr_rank)."""
    k = len(fanouts)
    out = [f"adj AS MATERIALIZED ({adj or ADJ[name]})", f"d{k} AS MATERIALIZED (SELECT DISTINCT batch_id, node_id FROM ({start or sql_targets(name)}))"]
    for i, f in zip(range(k, 0, -1), fanouts, strict=True):
        seen = " UNION ALL ".join(f"SELECT batch_id, node_id FROM d{j}" for j in range(k, i - 1, -1))
        out.append(f"e{i} AS MATERIALIZED ({sql_hop(f'd{i}', 'adj', f)})")
        out.append(f"d{i - 1} AS MATERIALIZED (SELECT DISTINCT batch_id, nbr_id AS node_id FROM e{i} EXCEPT ({seen}))")
    nodes = " UNION ALL ".join(f"SELECT batch_id, {i} AS delta_idx, node_id, CAST({fanouts[k - i] if i else 'NULL'} AS INTEGER) AS fanout FROM d{i}" for i in range(k, -1, -1))
    nbrs = " UNION ALL ".join(f"SELECT batch_id, {i} AS delta_idx, node_id, nbr_rank, nbr_id FROM e{i}" for i in range(k, 0, -1)) or "SELECT 0 AS batch_id, 0 AS delta_idx, 0 AS node_id, 0 AS nbr_rank, 0 AS nbr_id WHERE false"
    return "WITH " + ", ".join(out) + f", nodes AS MATERIALIZED ({nodes}), nbrs AS MATERIALIZED ({nbrs}) "


def delta(spark, sf_dir, name, fanouts, adj=None, hops=True):
    own = adj if adj is not None else (adjacency if hops else lists)(spark, sf_dir, name)
    return s.delta_sample(targets(spark, sf_dir, name), own, fanouts, hops=hops)


HOP_COLS = ("batch_id", "node_id", "nbr_rank", "nbr_id")
_DIRECTED = {d: f"SELECT DISTINCT {a} AS node_id, {b} AS nbr_id FROM ({TRADE_CORE})" for d, a, b in (("out", "src_id", "dst_id"), ("in", "dst_id", "src_id"))}
_PARTS = sql_targets("copurchase")


def part_targets(spark, sf_dir):
    return targets(spark, sf_dir, "copurchase")


for _d in ("out", "in"):
    query(f"one_hop_{_d}", f"WITH t AS ({_PARTS}), adj AS ({_DIRECTED[_d]}) {sql_hop('t', 'adj', 10)}")(
        lambda spark, sf_dir, d=_d: s.one_hop(part_targets(spark, sf_dir), part.adjacency(graphs.trade_core_edges(spark, sf_dir), d), 10)
    )

query("one_hop_both", f"WITH t AS ({_PARTS}), i AS ({_DIRECTED['in']}), o AS ({_DIRECTED['out']}) SELECT *, 0 AS side FROM ({sql_hop('t', 'i', 6)}) UNION ALL SELECT *, 1 FROM ({sql_hop('t', 'o', 4)})")(
    lambda spark, sf_dir: s.one_hop_both(part_targets(spark, sf_dir), part.adjacency(graphs.trade_core_edges(spark, sf_dir), "out"), part.adjacency(graphs.trade_core_edges(spark, sf_dir), "in"), 6, 4)
)

query("one_hop_relational", f"WITH t AS ({sql_targets('core')}), adj AS (SELECT DISTINCT src_id AS node_id, dst_id AS nbr_id, rel_id FROM ({TRADE})) {sql_hop('t', 'adj', 8, rel=True)}")(
    lambda spark, sf_dir: s.one_hop(targets(spark, sf_dir, "core"), part.adjacency(graphs.trade_edges(spark, sf_dir), "out", relational=True), 8)
)

for _k, _name, _f in ((2, "core", [10, 10]), (3, "copurchase", [20, 20, 20])):
    query(f"delta_nodes_k{_k}", sql_delta(_name, _f) + "SELECT * FROM nodes")(lambda spark, sf_dir, n=_name, f=_f: delta(spark, sf_dir, n, f, hops=False).nodes)
query("delta_edges_k2", sql_delta("core", [10, 10]) + "SELECT * FROM nbrs")(lambda spark, sf_dir: delta(spark, sf_dir, "core", [10, 10]).nbrs.select("batch_id", "delta_idx", "node_id", "nbr_rank", "nbr_id"))

STATS = "SELECT n.batch_id, n_nodes, coalesce(n_edges, 0) AS n_edges FROM (SELECT batch_id, count(*) AS n_nodes FROM nodes GROUP BY 1) n LEFT JOIN (SELECT batch_id, count(*) AS n_edges FROM nbrs GROUP BY 1) e USING (batch_id)"
query("delta_batched_sizes", sql_delta("core", [10, 10]) + STATS)(lambda spark, sf_dir: s.sample_stats(delta(spark, sf_dir, "core", [10, 10])))
query("delta_effective_fanout", sql_delta("core", [12, 6, 3]) + "SELECT n.delta_idx, n.fanout, count(*) AS n_nodes, CAST(sum(coalesce(c, 0)) AS BIGINT) AS n_nbrs FROM nodes n LEFT JOIN (SELECT batch_id, node_id, count(*) AS c FROM nbrs GROUP BY ALL) e USING (batch_id, node_id) GROUP BY ALL")(
    lambda spark, sf_dir: s.sampled_counts(delta(spark, sf_dir, "core", [12, 6, 3], hops=False)).groupBy("delta_idx", "fanout").agg(F.count("*").alias("n_nodes"), F.sum("c").alias("n_nbrs"))
)
query("fresh_frontier", sql_delta("core", [10]) + "SELECT * FROM d0")(
    lambda spark, sf_dir: (lambda t: s.fresh_frontier(s.one_hop(t, adjacency(spark, sf_dir, "core"), 10), t))(targets(spark, sf_dir, "core"))
)
query("delta_full_k2", sql_delta("core", [None, None]).replace("CAST(None AS INTEGER)", "CAST(NULL AS INTEGER)") + STATS)(lambda spark, sf_dir: s.sample_stats(delta(spark, sf_dir, "core", [None, None], hops=False)))
query("delta_k0", f"SELECT DISTINCT batch_id, 0 AS delta_idx, node_id, CAST(NULL AS INTEGER) AS fanout FROM ({sql_targets('core')})")(lambda spark, sf_dir: delta(spark, sf_dir, "core", []).nodes)

_IN = "(0, 1, 2, 3)"
_RESIDENT = f"SELECT * FROM ({TRADE_CORE}) WHERE {mix('src_id', 3)} % 8 IN {_IN} AND {mix('dst_id', 3)} % 8 IN {_IN}"
_RESIDENT_ADJ = f"SELECT src_id AS node_id, dst_id AS nbr_id FROM ({_RESIDENT}) UNION SELECT dst_id, src_id FROM ({_RESIDENT})"


@query("delta_in_buffer", sql_delta("core", [10, 10], adj=_RESIDENT_ADJ) + STATS)
def delta_in_buffer(spark, sf_dir):
    inside = part.induced(part.bucketed(graphs.trade_core_edges(spark, sf_dir), 8, 3), [0, 1, 2, 3])
    return s.sample_stats(delta(spark, sf_dir, "core", [10, 10], part.adjacency(inside, "any")))


_FULL, _HELD = sql_delta("core", [10, 10]) + STATS, sql_delta("core", [10, 10], adj=_RESIDENT_ADJ) + STATS


@query("in_buffer_share", f"SELECT f.batch_id, f.n_nodes AS full_nodes, f.n_edges AS full_edges, b.n_nodes AS buffer_nodes, b.n_edges AS buffer_edges FROM ({_FULL}) f JOIN ({_HELD}) b USING (batch_id)")
def in_buffer_share(spark, sf_dir):
    """Size of each batch over the whole graph and over half of its partitions."""
    full = s.sample_stats(delta(spark, sf_dir, "core", [10, 10])).select("batch_id", F.col("n_nodes").alias("full_nodes"), F.col("n_edges").alias("full_edges"))
    return full.join(delta_in_buffer(spark, sf_dir).select("batch_id", F.col("n_nodes").alias("buffer_nodes"), F.col("n_edges").alias("buffer_edges")), "batch_id")


_POS = "pos AS (SELECT *, row_number() OVER (PARTITION BY batch_id ORDER BY delta_idx, node_id) - 1 AS pos FROM nodes)"
query(
    "delta_packed_offsets",
    sql_delta("core", [10, 10]).rstrip() + f", {_POS} SELECT p.batch_id, p.node_id, p.pos, CAST(sum(coalesce(c, 0)) OVER (PARTITION BY p.batch_id ORDER BY p.pos) - coalesce(c, 0) AS BIGINT) AS nbr_start, coalesce(c, 0) AS n_nbrs FROM pos p LEFT JOIN (SELECT batch_id, node_id, count(*) AS c FROM nbrs GROUP BY ALL) e USING (batch_id, node_id) WHERE p.delta_idx > 0",
)(lambda spark, sf_dir: packing.neighbour_starts(delta(spark, sf_dir, "core", [10, 10])))
query(
    "delta_group_starts",
    sql_delta("core", [10, 10]) + "SELECT b.batch_id, g.delta_idx, CAST(sum(coalesce(c, 0)) OVER (PARTITION BY b.batch_id ORDER BY g.delta_idx) - coalesce(c, 0) AS BIGINT) AS group_start, coalesce(c, 0) AS n FROM (SELECT DISTINCT batch_id FROM nodes) b JOIN (VALUES (0), (1), (2)) g(delta_idx) ON true LEFT JOIN (SELECT batch_id, delta_idx, count(*) AS c FROM nodes GROUP BY ALL) USING (batch_id, delta_idx)",
)(lambda spark, sf_dir: packing.group_starts(delta(spark, sf_dir, "core", [10, 10])))
_INPUT = f", {_POS} SELECT n.batch_id, n.node_id, o.pos AS node_pos, n.nbr_rank, n.nbr_id, r.pos AS repr_pos FROM nbrs n JOIN pos o ON o.batch_id = n.batch_id AND o.node_id = n.node_id JOIN pos r ON r.batch_id = n.batch_id AND r.node_id = n.nbr_id"
query("delta_input_rows", sql_delta("core", [10, 10]).rstrip() + _INPUT)(lambda spark, sf_dir: packing.neighbour_positions(delta(spark, sf_dir, "core", [10, 10])).select("batch_id", "node_id", "node_pos", "nbr_rank", "nbr_id", "repr_pos"))
query("delta_trim_after_layer1", sql_delta("core", [10, 10]).rstrip() + ", pos AS (SELECT *, row_number() OVER (PARTITION BY batch_id ORDER BY delta_idx, node_id) - 1 AS pos FROM nodes WHERE delta_idx >= 1) SELECT n.batch_id, n.node_id, o.pos AS node_pos, n.nbr_rank, n.nbr_id, r.pos AS repr_pos FROM nbrs n JOIN pos o ON o.batch_id = n.batch_id AND o.node_id = n.node_id JOIN pos r ON r.batch_id = n.batch_id AND r.node_id = n.nbr_id WHERE n.delta_idx > 1")(
    lambda spark, sf_dir: packing.neighbour_positions(packing.trim(delta(spark, sf_dir, "core", [10, 10]), 1)).select("batch_id", "node_id", "node_pos", "nbr_rank", "nbr_id", "repr_pos")
)


def sql_resample(name, fanouts, layer_salt=True) -> str:
    out = [f"adj AS MATERIALIZED ({ADJ[name]})", f"f0 AS MATERIALIZED (SELECT DISTINCT batch_id, node_id FROM ({sql_targets(name)}))"]
    for h, f in enumerate(fanouts):
        out.append(f"e{h} AS MATERIALIZED ({sql_hop(f'f{h}', 'adj', f, h if layer_salt else None)})")
        out.append(f"f{h + 1} AS MATERIALIZED (SELECT batch_id, node_id FROM f{h} UNION SELECT batch_id, nbr_id FROM e{h})")
    return "WITH " + ", ".join(out) + " "


def _both_sql(fanouts) -> str:
    """The delta sample over incoming and outgoing neighbours of the trade graph, up to f of each."""
    k = len(fanouts)
    out = [f"i AS MATERIALIZED ({_DIRECTED['in']})", f"o AS MATERIALIZED ({_DIRECTED['out']})", f"d{k} AS MATERIALIZED (SELECT DISTINCT batch_id, node_id FROM ({sql_targets('core')}))"]
    for h, f in zip(range(k, 0, -1), fanouts, strict=True):
        seen = " UNION ALL ".join(f"SELECT batch_id, node_id FROM d{j}" for j in range(k, h - 1, -1))
        out.append(f"e{h} AS MATERIALIZED (SELECT * FROM ({sql_hop(f'd{h}', 'i', f)}) UNION ALL SELECT batch_id, node_id, nbr_id, nbr_rank + {f} FROM ({sql_hop(f'd{h}', 'o', f)}))")
        out.append(f"d{h - 1} AS MATERIALIZED (SELECT DISTINCT batch_id, nbr_id AS node_id FROM e{h} EXCEPT ({seen}))")
    return "WITH " + ", ".join(out) + " " + " UNION ALL ".join(f"SELECT batch_id, {h} AS delta_idx, node_id, nbr_rank, nbr_id FROM e{h}" for h in range(k, 0, -1))


@query("delta_edges_in_and_out", _both_sql([6, 4]))
def delta_edges_in_and_out(spark, sf_dir):
    edges = graphs.trade_core_edges(spark, sf_dir)
    found = s.delta_sample(targets(spark, sf_dir, "core"), (part.adjacency(edges, "in"), part.adjacency(edges, "out")), [6, 4])
    return found.nbrs.select("batch_id", "delta_idx", "node_id", "nbr_rank", "nbr_id")


for _k, _name, _f in ((2, "core", [10, 10]), (3, "copurchase", [20, 20, 20])):
    query(f"layer_resample_k{_k}", sql_resample(_name, _f) + " UNION ALL ".join(f"SELECT batch_id, {h} AS hop, node_id, nbr_rank, nbr_id FROM e{h}" for h in range(_k)))(
        lambda spark, sf_dir, n=_name, f=_f: s.layer_resample(targets(spark, sf_dir, n), lists(spark, sf_dir, n), f, hops=False).select("batch_id", "hop", "node_id", "nbr_rank", "nbr_id")
    )


def sql_path(name, fanouts, dedupe=False) -> str:
    out = [f"adj AS MATERIALIZED ({ADJ[name]})", f"f0 AS MATERIALIZED (SELECT DISTINCT batch_id, node_id, CAST(1 AS BIGINT) AS n_paths FROM ({sql_targets(name)}))"]
    for h, f in enumerate(fanouts):
        out.append(f"e{h} AS MATERIALIZED (SELECT e.batch_id, e.node_id, e.nbr_id, f.n_paths FROM ({sql_hop(f'f{h}', 'adj', f, h)}) e JOIN f{h} f ON f.batch_id = e.batch_id AND f.node_id = e.node_id)")
        out.append(f"f{h + 1} AS MATERIALIZED (SELECT batch_id, nbr_id AS node_id, CAST({'1' if dedupe else 'sum(n_paths)'} AS BIGINT) AS n_paths FROM e{h} GROUP BY ALL)")
    return "WITH " + ", ".join(out) + " "


query("path_sample_dedupe_k2", sql_path("core", [10, 10], True) + "SELECT *, 0 AS hop FROM e0 UNION ALL SELECT *, 1 FROM e1")(lambda spark, sf_dir: s.path_sample(targets(spark, sf_dir, "core"), adjacency(spark, sf_dir, "core"), [10, 10], dedupe=True))
query("path_sample_k2", sql_path("core", [10, 10]) + "SELECT *, 0 AS hop FROM e0 UNION ALL SELECT *, 1 FROM e1")(lambda spark, sf_dir: s.path_sample(targets(spark, sf_dir, "core"), adjacency(spark, sf_dir, "core"), [10, 10]))

query(
    "khop_exact_k2",
    f"WITH adj AS MATERIALIZED ({ADJ['core']}), a AS ({sql_targets('core')}), b AS (SELECT DISTINCT a.batch_id, adj.nbr_id AS node_id FROM a JOIN adj USING (node_id) EXCEPT SELECT batch_id, node_id FROM a), c AS (SELECT DISTINCT b.batch_id, adj.nbr_id AS node_id FROM b JOIN adj USING (node_id) EXCEPT (SELECT batch_id, node_id FROM a UNION SELECT batch_id, node_id FROM b)) SELECT *, 0 AS dist FROM a UNION ALL SELECT *, 1 FROM b UNION ALL SELECT *, 2 FROM c",
)(lambda spark, sf_dir: s.khop_exact(targets(spark, sf_dir, "core"), adjacency(spark, sf_dir, "core"), 2))


def _sweep_sql(name, f):
    """One chain for k = 4 gives the counts of every smaller k: hops are the same from the targets outwards."""
    d, r, p = sql_delta(name, [f] * 4)[5:].rstrip(), sql_resample(name, [f] * 4)[5:].rstrip(), sql_path(name, [f] * 4)[5:].rstrip()
    r = r[r.index("f0 AS") :].replace("f0", "rf0").replace("f1", "rf1").replace("f2", "rf2").replace("f3", "rf3").replace("f4", "rf4").replace("e0", "re0").replace("e1", "re1").replace("e2", "re2").replace("e3", "re3")
    p = p[p.index("f0 AS") :].replace("f0", "pf0").replace("f1", "pf1").replace("f2", "pf2").replace("f3", "pf3").replace("f4", "pf4").replace("e0", "pe0").replace("e1", "pe1").replace("e2", "pe2").replace("e3", "pe3")
    rows = []
    for k in range(1, 5):
        dn = " + ".join(f"(SELECT count(*) FROM d{i})" for i in range(4, 3 - k, -1))
        de = " + ".join(f"(SELECT count(*) FROM e{i})" for i in range(4, 4 - k, -1))
        re = " + ".join(f"(SELECT count(*) FROM re{h})" for h in range(k))
        pe = " + ".join(f"(SELECT sum(n_paths) FROM pe{h})" for h in range(k))
        rows.append(f"SELECT '{name}' AS graph, {k} AS k, {dn} AS delta_nodes, {de} AS delta_edges, (SELECT count(*) FROM rf{k}) AS resample_nodes, {re} AS resample_edges, CAST({pe} AS BIGINT) AS path_edges")
    return f"WITH {d}, {r}, {p} " + " UNION ALL ".join(rows)


def sample_sizes(spark, sf_dir, name, fanout, most=4):
    """(graph, k, ...) unique vertices and edges of the three samplers for k = 1..most."""
    held, start = lists(spark, sf_dir, name), targets(spark, sf_dir, name)
    drawn = s.sampled_counts(s.delta_sample(start, held, [fanout] * most, hops=False)).groupBy("delta_idx").agg(F.count("*").alias("n"), F.sum("c").alias("c"))
    depths = spark.range(1, most + 1).select(F.col("id").cast("int").alias("k"))
    met = most - F.col("delta_idx")  # the depth from which on a group's vertices are there; their neighbours are one later
    total = lambda since, n: F.coalesce(F.sum(F.when(since <= F.col("k"), F.col(n))), F.lit(0))
    delta_all = depths.join(F.broadcast(drawn), how="left").groupBy("k").agg(total(met, "n").alias("delta_nodes"), total(met + 1, "c").alias("delta_edges"))
    return delta_all.join(s.resample_path_counts(start, held, [fanout] * most), "k").withColumn("graph", F.lit(name))


query("sample_size_sweep", _sweep_sql("core", 10))(lambda spark, sf_dir: sample_sizes(spark, sf_dir, "core", 10))
query("sample_size_sweep_copurchase", _sweep_sql("copurchase", 20))(lambda spark, sf_dir: sample_sizes(spark, sf_dir, "copurchase", 20))

_IND = "SELECT batch_id AS sample_id, node_id, string_agg(CAST(nbr_id AS VARCHAR), ',' ORDER BY nbr_id) AS members FROM e GROUP BY ALL"


@query("subset_diversity", f"WITH adj AS ({ADJ['core']}), f AS (SELECT b.batch_id, t.node_id FROM ({sql_targets('core')}) t, (SELECT unnest(range(6)) AS batch_id) b), e AS ({sql_hop('f', 'adj', 5)}), m AS ({_IND}) SELECT node_id, count(*) AS n_samples, count(DISTINCT members) AS n_subsets FROM m GROUP BY 1")
def subset_diversity(spark, sf_dir):
    f = targets(spark, sf_dir, "core").select("node_id", F.explode(F.sequence(F.lit(0), F.lit(5))).alias("batch_id"))
    return s.subset_diversity(s.one_hop(f, adjacency(spark, sf_dir, "core"), 5).withColumnRenamed("batch_id", "sample_id"))

