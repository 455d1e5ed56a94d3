"""Policies, their measures, and tuning. Oracles get the sequence of resident sets as a VALUES table and redo the rest."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltahop import graphs, hashing
from deltahop.operators import partitioning as part
from deltahop.operators.storage import shared_path, stored
from deltahop.plans import batching, metrics, policy, tuning
from deltahop.queries.graph import NODES, PART
from deltahop.sources import store
from deltahop.queries.registry import CUST_PART_PLAIN, ORACLES, TRADE, TRADE_CORE, mix, query

P, C, L = 16, 4, 8
GREEDY = policy.plan_greedy(P, C)
TWO = policy.plan_two_level(P, L, C, epoch=0, seed=3)
TWO_EAGER = policy.plan_two_level(P, L, C, epoch=0, seed=3, assign="eager")


def values(rows, names: str) -> str:
    return f"(SELECT * FROM (VALUES {', '.join(str(tuple(r)) for r in rows)}) v({names}))"


def sets_sql(plan) -> str:
    return values([(i, q) for i, m in enumerate(plan.sets) for q in m], "set_idx, part_id")


def _pairs(plan) -> str:
    return f"(SELECT a.part_id AS src_part, b.part_id AS dst_part, a.set_idx FROM {sets_sql(plan)} a JOIN {sets_sql(plan)} b USING (set_idx))"


def eager_sql(plan) -> str:
    return f"SELECT src_part, dst_part, min(set_idx) AS set_idx FROM {_pairs(plan)} GROUP BY ALL"


def deferred_sql(plan, epoch=0, seed=3) -> str:
    return f"SELECT src_part, dst_part, set_idx FROM {_pairs(plan)} QUALIFY row_number() OVER (PARTITION BY src_part, dst_part ORDER BY md5(concat_ws(':', {seed}, {epoch}, src_part, dst_part, set_idx)), set_idx) = 1"


query("plan_full_memory", f"SELECT CAST(0 AS INTEGER) AS set_idx, CAST(i AS INTEGER) AS src_part, CAST(j AS INTEGER) AS dst_part FROM range({P}) a(i), range({P}) b(j)")(lambda spark, sf_dir: policy.plan_full(P).buckets_df(spark))
query("greedy_sets_lowest")(lambda spark, sf_dir: GREEDY.sets_df(spark))
query("two_level_sets")(lambda spark, sf_dir: TWO.sets_df(spark))
PHYSICAL = policy.plan_greedy(P, C, assign="deferred", seed=3)
query("plan_physical_deferred", deferred_sql(PHYSICAL))(lambda spark, sf_dir: PHYSICAL.buckets_df(spark))
query("plan_random_cover")(lambda spark, sf_dir: policy.plan_random_cover(P, L, C, 0, 3).sets_df(spark))
SIZES = f"SELECT {PART('src_id')} AS src_part, {PART('dst_id')} AS dst_part, count(*) AS n_edges FROM ({TRADE_CORE}) GROUP BY ALL"


def sizes(spark, sf_dir, p: int = P):
    return part.bucket_sizes(part.bucketed(graphs.trade_core_edges(spark, sf_dir), p, 3))


def placed_sql(assigned: str) -> str:
    return f"SELECT src_part, dst_part, set_idx, n_edges FROM ({assigned}) JOIN ({SIZES}) USING (src_part, dst_part)"


def placed(buckets, spark, sf_dir):
    """The trade graph's edges by bucket and the set that trains them."""
    return sizes(spark, sf_dir).join(F.broadcast(buckets), ["src_part", "dst_part"]).select("src_part", "dst_part", "set_idx", "n_edges")


query("assign_eager", placed_sql(eager_sql(GREEDY)))(lambda spark, sf_dir: placed(policy.assign_eager_df(GREEDY.sets_df(spark)), spark, sf_dir))
query("assign_deferred", placed_sql(deferred_sql(TWO)))(lambda spark, sf_dir: placed(policy.assign_deferred_df(TWO.sets_df(spark), 0, 3), spark, sf_dir))
query("assign_two_level_eager", placed_sql(eager_sql(TWO_EAGER)))(lambda spark, sf_dir: placed(TWO_EAGER.buckets_df(spark), spark, sf_dir))
query("plan_label_cache", f"SELECT CAST(0 AS INTEGER) AS set_idx, CAST(i AS INTEGER) AS part_id FROM (SELECT i FROM range(3) t(i) UNION ALL (SELECT i FROM range(3, {P}) t(i) ORDER BY {mix('i', '(3 * 1009 + 2)')}, i LIMIT 4))")(
    lambda spark, sf_dir: policy.plan_label_cache(3, 7, P, epoch=2, seed=3).sets_df(spark)
)


@query("assign_nodes", f"SELECT CAST(min(s.set_idx) AS INTEGER) AS set_idx, node_id FROM ({NODES}) JOIN {sets_sql(TWO)} s ON s.part_id = {PART('node_id')} GROUP BY node_id")
def assign_nodes(spark, sf_dir):
    nodes = part.assign_partitions(graphs.Graph.from_tables(spark, sf_dir, "trade").nodes, P, 3)
    return policy.assign_nodes(nodes, TWO.sets_df(spark))


@query("plan_table_sink", deferred_sql(TWO))
def plan_table_sink(spark, sf_dir):
    return store.read_plan(spark, store.write_plan(spark, TWO))["buckets"].select("src_part", "dst_part", "set_idx")


def loads_sql(plan) -> str:
    return f"""SELECT set_idx, part_id, 'load' AS action FROM {sets_sql(plan)} s WHERE NOT EXISTS (SELECT 1 FROM {sets_sql(plan)} o WHERE o.part_id = s.part_id AND o.set_idx = s.set_idx - 1)
UNION ALL SELECT set_idx + 1, part_id, 'evict' FROM {sets_sql(plan)} s WHERE set_idx < {len(plan.sets) - 1} AND NOT EXISTS (SELECT 1 FROM {sets_sql(plan)} o WHERE o.part_id = s.part_id AND o.set_idx = s.set_idx + 1)"""


for _n, _plan in (("greedy", GREEDY), ("two_level", TWO)):
    query(f"plan_load_counts_{_n}", f"SELECT set_idx, action, count(*) AS n FROM ({loads_sql(_plan)}) GROUP BY ALL")(lambda spark, sf_dir, p=_plan: p.loads_df(spark).groupBy("set_idx", "action").agg(F.count("*").alias("n")))


@query("batch_sizes", f"WITH x AS (SELECT src_id, dst_id, row_number() OVER (ORDER BY md5(concat_ws(':', 7, 0, src_id, 0, dst_id)), src_id, dst_id) AS r FROM ({CUST_PART_PLAIN})) SELECT CAST(floor((r - 1) / 1000) AS BIGINT) AS batch_id, count(*) AS n FROM x GROUP BY 1")
def batch_sizes(spark, sf_dir):
    edges = graphs.customer_part_edges(spark, sf_dir, relational=False)
    return batching.exact_batches(edges, 1000, 7, 0).groupBy("batch_id").agg(F.count("*").alias("n"))


@query("batch_sizes_hashed", f"SELECT CAST({mix('dst_id + src_id', 7)} % 60 AS BIGINT) AS batch_id, count(*) AS n FROM ({CUST_PART_PLAIN}) GROUP BY 1")
def batch_sizes_hashed(spark, sf_dir):
    edges = graphs.customer_part_edges(spark, sf_dir, relational=False)
    return batching.hashed_batches(edges, 60, 7).groupBy("batch_id").agg(F.count("*").alias("n"))


def bias_sql(assigned: str, p: int = P, weight: str | None = None) -> str:
    n = "1" if weight is None else "w.n_edges"
    join = "" if weight is None else f"JOIN ({weight}) w USING (src_part, dst_part)"
    return f"""WITH a AS ({assigned}), e AS (SELECT set_idx, src_part AS part_id, {n} AS n FROM a {join} UNION ALL SELECT set_idx, dst_part, {n} FROM a {join}),
g AS (SELECT s.set_idx, p.part_id, coalesce(sum(e.n), 0) AS n FROM (SELECT DISTINCT set_idx FROM a) s CROSS JOIN (SELECT DISTINCT part_id FROM e) p LEFT JOIN e ON e.set_idx = s.set_idx AND e.part_id = p.part_id GROUP BY ALL),
t AS (SELECT set_idx, CAST(sum(n) OVER (PARTITION BY part_id ORDER BY set_idx) AS DOUBLE) / CAST(sum(n) OVER (PARTITION BY part_id) AS DOUBLE) AS share FROM g)
SELECT round(max(d), 9) AS bias FROM (SELECT max(share) - min(share) AS d FROM t GROUP BY set_idx)"""


def rounded(df):
    return df.select(F.round("bias", 9).alias("bias"))


# Uniform degrees: each bucket that holds edges of the trade graph counts once.
query("bias_uniform_eager", bias_sql(placed_sql(eager_sql(GREEDY))))(lambda spark, sf_dir: rounded(metrics.edge_permutation_bias(placed(GREEDY.buckets_df(spark), spark, sf_dir), P)))
query("bias_uniform_deferred", bias_sql(placed_sql(deferred_sql(TWO))))(lambda spark, sf_dir: rounded(metrics.edge_permutation_bias(placed(TWO.buckets_df(spark), spark, sf_dir), P)))
query("bias_partition_edges", bias_sql(deferred_sql(TWO), weight=SIZES))(
    lambda spark, sf_dir: rounded(metrics.edge_permutation_bias(TWO.buckets_df(spark), P, part.bucket_sizes(part.bucketed(graphs.trade_core_edges(spark, sf_dir), P, 3))))
)


@query(
    "bias_empirical",
    f"""WITH a AS ({deferred_sql(TWO)}), x AS (SELECT set_idx, src_id, dst_id FROM (SELECT *, {PART('src_id')} AS src_part, {PART('dst_id')} AS dst_part FROM ({TRADE_CORE})) JOIN a USING (src_part, dst_part)),
e AS (SELECT set_idx, src_id AS node_id FROM x UNION ALL SELECT set_idx, dst_id FROM x), c AS (SELECT set_idx, node_id, count(*) AS n FROM e GROUP BY ALL),
g AS (SELECT s.set_idx, v.node_id, coalesce(c.n, 0) AS n FROM (SELECT DISTINCT set_idx FROM a) s CROSS JOIN (SELECT DISTINCT node_id FROM e) v LEFT JOIN c ON c.set_idx = s.set_idx AND c.node_id = v.node_id),
t AS (SELECT set_idx, CAST(sum(n) OVER (PARTITION BY node_id ORDER BY set_idx) AS DOUBLE) / CAST(sum(n) OVER (PARTITION BY node_id) AS DOUBLE) AS share FROM g)
SELECT round(max(d), 9) AS bias FROM (SELECT max(share) - min(share) AS d FROM t GROUP BY set_idx)""",
)
def bias_empirical(spark, sf_dir):
    return rounded(metrics.vertex_bias(part.bucketed(graphs.trade_core_edges(spark, sf_dir), P, 3), TWO.buckets_df(spark)))


NODE_BYTES = f"SELECT {PART('node_id')} AS part_id, count(*) * 200 AS bytes FROM ({NODES}) GROUP BY 1"


@query(
    "io_bytes_epoch",
    f"""WITH l AS (SELECT set_idx, part_id FROM ({loads_sql(TWO)}) WHERE action = 'load'), nb AS ({NODE_BYTES}), eb AS (SELECT src_part, dst_part, n_edges * 12 AS bytes FROM ({SIZES})),
e AS (SELECT l.set_idx, l.part_id AS src_part, s.part_id AS dst_part FROM l JOIN {sets_sql(TWO)} s USING (set_idx) UNION SELECT l.set_idx, s.part_id, l.part_id FROM l JOIN {sets_sql(TWO)} s USING (set_idx))
SELECT CAST((SELECT sum(bytes) FROM l JOIN nb USING (part_id)) AS BIGINT) AS node_bytes, CAST((SELECT sum(bytes) FROM e JOIN eb USING (src_part, dst_part)) AS BIGINT) AS edge_bytes""",
)
def io_bytes_epoch(spark, sf_dir):
    g = graphs.Graph.from_tables(spark, sf_dir, "trade")
    nodes = part.assign_partitions(g.nodes, P, 3).groupBy("part_id").agg((F.count("*") * 200).alias("bytes"))
    sizes = part.bucket_sizes(part.bucketed(graphs.trade_core_edges(spark, sf_dir), P, 3)).select("src_part", "dst_part", (F.col("n_edges") * 12).alias("bytes"))
    return metrics.io_bytes(TWO.loads_df(spark), TWO.sets_df(spark), nodes, sizes)


query("num_sets", f"SELECT 'greedy' AS plan, count(DISTINCT set_idx) AS n FROM {sets_sql(GREEDY)} UNION ALL SELECT 'two_level', count(DISTINCT set_idx) FROM {sets_sql(TWO)}")(
    lambda spark, sf_dir: GREEDY.sets_df(spark).withColumn("plan", F.lit("greedy")).unionByName(TWO.sets_df(spark).withColumn("plan", F.lit("two_level"))).groupBy("plan").agg(F.countDistinct("set_idx").alias("n"))
)


@query("smallest_read", f"SELECT least((SELECT min(bytes) FROM ({NODE_BYTES})), (SELECT min(n_edges) * 12 FROM ({SIZES}))) AS min_read")
def smallest_read(spark, sf_dir):
    g = graphs.Graph.from_tables(spark, sf_dir, "trade")
    a = part.assign_partitions(g.nodes, P, 3).groupBy("part_id").agg((F.count("*") * 200).alias("bytes")).select("bytes")
    b = part.bucket_sizes(part.bucketed(graphs.trade_core_edges(spark, sf_dir), P, 3)).select((F.col("n_edges") * 12).alias("bytes"))
    return a.unionByName(b).agg(F.min("bytes").alias("min_read"))


_BAL = "SELECT '{n}' AS plan, count(*) AS n_sets, CAST(min(n) AS BIGINT) AS least, CAST(max(n) AS BIGINT) AS most, round(avg(n), 6) AS mean, round(max(n) / avg(n), 6) AS max_over_mean, round(stddev_pop(n) / avg(n), 6) AS cv FROM (SELECT set_idx, CAST(sum(n_edges) AS BIGINT) AS n FROM ({a}) JOIN ({s}) USING (src_part, dst_part) GROUP BY 1)"


@query("example_balance", _BAL.format(n="greedy", a=eager_sql(GREEDY), s=SIZES) + " UNION ALL " + _BAL.format(n="two_level", a=deferred_sql(TWO), s=SIZES))
def example_balance(spark, sf_dir):
    sizes = part.bucket_sizes(part.bucketed(graphs.trade_core_edges(spark, sf_dir), P, 3))
    out = None
    for name, plan in (("greedy", GREEDY), ("two_level", TWO)):
        counts = plan.buckets_df(spark).join(sizes, ["src_part", "dst_part"]).groupBy("set_idx").agg(F.sum("n_edges").alias("n"))
        row = metrics.example_balance(counts).select(F.lit(name).alias("plan"), "n_sets", "least", "most", *(F.round(c, 6).alias(c) for c in ("mean", "max_over_mean", "cv")))
        out = row if out is None else out.unionByName(row)
    return out


@query("coverage_check", f"WITH a AS ({deferred_sql(TWO)}) SELECT count(*) AS n_edges, CAST(sum(CASE WHEN n = 1 THEN 0 ELSE 1 END) AS BIGINT) AS violations FROM (SELECT e.src_id, e.dst_id, e.rel_id, count(a.set_idx) AS n FROM (SELECT *, {PART('src_id')} AS src_part, {PART('dst_id')} AS dst_part FROM ({TRADE})) e LEFT JOIN a USING (src_part, dst_part) GROUP BY ALL)")
def coverage_check(spark, sf_dir):
    edges = part.bucketed(graphs.trade_edges(spark, sf_dir), P, 3)
    n = edges.join(F.broadcast(TWO.buckets_df(spark)), ["src_part", "dst_part"], "left").groupBy("src_id", "rel_id", "dst_id").agg(F.count("set_idx").alias("n"))
    return n.agg(F.count("*").alias("n_edges"), F.sum(F.when(F.col("n") == 1, 0).otherwise(1)).alias("violations"))


# ---- predictions and costs

_CLASS = "SELECT c_custkey AS example_id, k AS class_id, (c_custkey * 7 + k * 13) % 11 AS score FROM customer, range(5) t(k)"


@query("accuracy_multiclass", f"WITH p AS (SELECT example_id, class_id AS prediction FROM ({_CLASS}) QUALIFY row_number() OVER (PARTITION BY example_id ORDER BY score DESC, class_id) = 1) SELECT count(*) AS n, round(avg(CASE WHEN prediction = example_id % 5 THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM p")
def accuracy_multiclass(spark, sf_dir):
    rows = graphs.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("example_id"), F.explode(F.sequence(F.lit(0), F.lit(4))).alias("class_id"))
    scores = rows.withColumn("score", (F.col("example_id") * 7 + F.col("class_id") * 13) % 11)
    best = metrics.argmax_lowest(scores).withColumn("label", F.col("example_id") % 5)
    return metrics.accuracy(best).select("n", F.round("accuracy", 9).alias("accuracy"))


# Hourly prices of the machines that serve purchases and all other events.
RATES = {"purchase": 12.24, "other": 3.06}


@query("cost_per_epoch", f"SELECT event_type AS run, round(us / 60000000.0::DOUBLE, 6) AS minutes, round(us / 60000000.0::DOUBLE / 60 * CASE WHEN event_type = 'purchase' THEN {RATES['purchase']}::DOUBLE ELSE {RATES['other']}::DOUBLE END, 6) AS dollars FROM (SELECT event_type, CAST(sum(us) AS BIGINT) AS us FROM (SELECT user_id, event_type, epoch_us(max(ts)) - epoch_us(min(ts)) AS us FROM events GROUP BY ALL) GROUP BY 1)")
def cost_per_epoch(spark, sf_dir):
    """Cost of the time between each user's first and last event of a type, at the hourly price of the type's machine."""
    us = F.unix_micros(F.max("ts").cast("timestamp")) - F.unix_micros(F.min("ts").cast("timestamp"))
    spent = graphs.table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(us.alias("us")).groupBy(F.col("event_type").alias("run")).agg(F.sum("us").alias("us"))
    minutes = F.col("us").cast("double") / 60000000.0
    rate = F.when(F.col("run") == "purchase", RATES["purchase"]).otherwise(RATES["other"])
    return spent.select("run", F.round(minutes, 6).alias("minutes"), F.round(metrics.cost(minutes, rate), 6).alias("dollars"))


RUNS = [(run, e, 10.0 * e + k, "accuracy", round(1 - 0.5 ** (e * (k + 1)), 4)) for k, run in enumerate(("memory", "disk")) for e in range(1, 11)]
query("time_to_accuracy", f"SELECT run, CAST(min(elapsed_s) AS DOUBLE) AS elapsed_s FROM {values(RUNS, 'run, epoch, elapsed_s, metric, value')} WHERE metric = 'accuracy' AND value >= 0.95 GROUP BY run")(
    lambda spark, sf_dir: metrics.time_to_metric(spark.createDataFrame(RUNS, "run string, epoch int, elapsed_s double, metric string, value double"), "accuracy", 0.95)
)


@query("metric_table_sink", f"SELECT run, CAST(epoch AS INTEGER) AS epoch, CAST(elapsed_s AS DOUBLE) AS elapsed_s, metric, CAST(value AS DOUBLE) AS value FROM {values(RUNS, 'run, epoch, elapsed_s, metric, value')}")
def metric_table_sink(spark, sf_dir):
    """Two runs written one after the other, the first one twice."""
    path, schema = shared_path(spark, "metrics"), "run string, epoch int, elapsed_s double, metric string, value double"
    for run in ("memory", "disk", "memory"):
        store.write_metrics(spark.createDataFrame([r for r in RUNS if r[0] == run], schema), path)
    return spark.read.parquet(path).select("run", "epoch", "elapsed_s", "metric", "value")


# Published reciprocal ranks (model and graph, memory, two-level, greedy).
RANKS = [("DistMult small KG", 0.2533, 0.2659, 0.2431), ("DistMult KG A", 0.7249, 0.7220, 0.7189), ("DistMult KG B", 0.3941, 0.4071, 0.3951), ("SAGE small KG", 0.2825, 0.2736, 0.2369), ("SAGE KG A", 0.7342, 0.7123, 0.6976), ("SAGE KG B", 0.4658, 0.4078, 0.4080), ("GAT small KG", 0.2869, 0.2341, 0.2076), ("GAT KG A", 0.7418, 0.7053, 0.6860)]
query("gap_closed", f"SELECT run, round((CAST(two AS DOUBLE) - greedy) / (CAST(mem AS DOUBLE) - greedy), 6) AS closed FROM {values(RANKS, 'run, mem, two, greedy')}")(
    lambda spark, sf_dir: spark.createDataFrame(RANKS, "run string, mem double, two double, greedy double").select("run", F.round(metrics.gap_closed(F.col("two"), F.col("greedy"), F.col("mem")), 6).alias("closed"))
)

# ---- tuning

DIM, EDGE, BLOCK, CPU, RESERVE = 50, 12, 4096, 400000, 50000
# Blocks and memories for graphs of a few hundred vertices up to a few million.
_GRID = [(BLOCK, CPU), (1024, 400000), (16384, 900000), (4096, 2000000), (4096, 8000000), (65536, 64000000), (1048576, 600000000)]
_OVER = f"SELECT CAST((SELECT count(*) FROM ({NODES})) AS DOUBLE) * {DIM} * 4 AS no, CAST((SELECT count(*) FROM ({TRADE})) AS DOUBLE) * {EDGE} AS eo"
_WITH_OVER = f"WITH o AS MATERIALIZED ({_OVER}) "


def trade_overheads(spark, sf_dir) -> tuning.Overheads:
    """Bytes of the trade graph's vertices and edges."""
    g = graphs.Graph.from_tables(spark, sf_dir, "trade")
    return tuning.Overheads.of(g.nodes.count(), g.edges.count(), DIM, EDGE)


def _tuned(spark, sf_dir, name: str):
    o = trade_overheads(spark, sf_dir)
    return spark.createDataFrame([(b, m, tuning.autotune(o, m, b, RESERVE)[name]) for b, m in _GRID], "block int, memory int, value int")


@query("autotune_overheads", _WITH_OVER + "SELECT p AS p, round(no / p, 6) AS partition_bytes, round(eo / (p * p), 6) AS bucket_bytes FROM o, (VALUES (1), (4), (18)) t(p)")
def autotune_overheads(spark, sf_dir):
    o = trade_overheads(spark, sf_dir)
    return spark.createDataFrame([(p, round(o.partition(p), 6), round(o.bucket(p), 6)) for p in (1, 4, 18)], "p int, partition_bytes double, bucket_bytes double")


_P_SQL = f"SELECT block, memory, CAST(greatest(1, floor(least(no / block, sqrt(eo / block)))) AS INTEGER) AS p FROM o, {values(_GRID, 'block, memory')} g"
query("autotune_p", _WITH_OVER + f"SELECT block, memory, p AS value FROM ({_P_SQL})")(lambda spark, sf_dir: _tuned(spark, sf_dir, "p"))
_C_SQL = f"SELECT block, memory, p, CAST(coalesce(max(c) FILTER (WHERE c * (no / p) + 2 * c * c * (eo / (p * p)) + {RESERVE} < memory), 0) AS INTEGER) AS c FROM (SELECT *, unnest(range(1, p + 1)) AS c FROM ({_P_SQL}), o) GROUP BY block, memory, p"
query("autotune_c", _WITH_OVER + f"SELECT block, memory, c AS value FROM ({_C_SQL})")(lambda spark, sf_dir: _tuned(spark, sf_dir, "c"))
query(
    "autotune_l",
    _WITH_OVER + f"SELECT block, memory, CAST(CASE WHEN c = 0 THEN p WHEN c >= p THEN 1 ELSE min(n) FILTER (WHERE n >= ceil(2.0 * p / c) AND (n >= p OR 2 * ceil(p::DOUBLE / n) <= c)) END AS INTEGER) AS value FROM (SELECT *, unnest(range(1, 2 * p + 1)) AS n FROM ({_C_SQL})) GROUP BY block, memory, p, c",
)(lambda spark, sf_dir: _tuned(spark, sf_dir, "l"))


def sweep_rows(tie: str = "lowest", seeds=(3,), ps=(8, 16, 32), assign: str = "deferred") -> list[tuple]:
    """(p, l, seed, plan) of two-level plans with c = p / 4 over all numbers of groups that fit the buffer in pairs."""
    out = []
    for p in ps:
        for n in (d for d in range(2, p + 1) if p % d == 0 and 2 * (p // d) <= p // 4):
            out += [(p, n, s, policy.plan_two_level(p, n, p // 4, 0, s, tie, assign)) for s in seeds]
    return out


SWEEP = sweep_rows()


@query("policy_sweep", f"SELECT p, l, count(DISTINCT set_idx) AS n_sets, round(max(d), 9) AS bias FROM (SELECT p, l, set_idx, max(share) - min(share) AS d FROM (SELECT p, l, set_idx, CAST(sum(n) OVER (PARTITION BY p, l, part_id ORDER BY set_idx) AS DOUBLE) / CAST(sum(n) OVER (PARTITION BY p, l, part_id) AS DOUBLE) AS share FROM (SELECT s.p, s.l, s.set_idx, q.part_id, count(e.x) AS n FROM (SELECT DISTINCT p, l, set_idx FROM b) s JOIN (SELECT DISTINCT p, l, src_part AS part_id FROM b) q USING (p, l) LEFT JOIN (SELECT p, l, set_idx, src_part AS part_id, 1 AS x FROM b UNION ALL SELECT p, l, set_idx, dst_part, 1 FROM b) e ON e.p = s.p AND e.l = s.l AND e.set_idx = s.set_idx AND e.part_id = q.part_id GROUP BY ALL)) GROUP BY ALL) GROUP BY ALL".replace(
    "SELECT p, l, count(", "WITH b AS " + values([(p, n, x, i, j) for p, n, _, plan in SWEEP for (i, j), x in plan.buckets.items()], "p, l, set_idx, src_part, dst_part") + " SELECT p, l, count(", 1))
def policy_sweep(spark, sf_dir):
    """Number of sets and bias for every p and l: both grow with l, the bias falls with p at a fixed l."""
    return sweep_bias(sweep_buckets(spark))


def sweep_buckets(spark) -> DataFrame:
    return spark.createDataFrame([(p, n, x, i, j) for p, n, _, plan in SWEEP for (i, j), x in plan.buckets.items()], "p int, l int, set_idx int, src_part int, dst_part int")


def sweep_bias(rows: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """(p, l, n_sets, bias) of the plans' buckets; weights (p, src_part, dst_part, n_edges) counts edges instead of buckets."""
    used = rows.withColumn("n_edges", F.lit(1)) if weights is None else rows.join(weights, ["p", "src_part", "dst_part"])
    ends = used.select("p", "l", "set_idx", "n_edges", F.explode(F.array("src_part", "dst_part")).alias("part_id")).groupBy("p", "l", "set_idx", "part_id").agg(F.sum("n_edges").alias("n"))
    full = rows.select("p", "l", "set_idx").distinct().join(ends.select("p", "l", "part_id").distinct(), ["p", "l"])
    per = full.join(ends, ["p", "l", "set_idx", "part_id"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    w = Window.partitionBy("p", "l", "part_id")
    share = per.withColumn("share", F.sum("n").over(w.orderBy("set_idx")) / F.sum("n").over(w))
    spread = share.groupBy("p", "l", "set_idx").agg((F.max("share") - F.min("share")).alias("d"))
    return spread.groupBy("p", "l").agg(F.countDistinct("set_idx").alias("n_sets"), F.round(F.max("d"), 9).alias("bias"))


READ_BLOCK = 65536


@query("epoch_cost_model", _WITH_OVER + f", a AS (SELECT CAST(greatest(1, floor(least(no / {READ_BLOCK}, sqrt(eo / {READ_BLOCK})))) AS DOUBLE) AS alpha FROM o) SELECT p, l, count(DISTINCT set_idx) * greatest(1.0::DOUBLE, p / alpha) AS cost FROM {values([(p, n, x) for p, n, _, plan in SWEEP for x in range(len(plan.sets))], 'p, l, set_idx')}, a GROUP BY p, l, alpha")
def epoch_cost_model(spark, sf_dir):
    """Modelled epoch cost of the sweep's plans on the trade graph, whose size tells beyond how many partitions reads shrink below a block."""
    alpha = choose_alpha(trade_overheads(spark, sf_dir), READ_BLOCK)
    return spark.createDataFrame([(p, n, tuning.epoch_cost(len(plan.sets), p, alpha)) for p, n, _, plan in SWEEP], "p int, l int, cost double")


_SWEEP_P = sorted({p for p, *_ in SWEEP})
_SWEEP_SIZES = " UNION ALL ".join(f"SELECT {p} AS p, {PART('src_id', p)} AS src_part, {PART('dst_id', p)} AS dst_part, count(*) AS n_edges FROM g GROUP BY ALL" for p in _SWEEP_P)
_SWEEP_BUCKETS = values([(p, n, x, i, j) for p, n, _, plan in SWEEP for (i, j), x in plan.buckets.items()], "p, l, set_idx, src_part, dst_part")


@query(
    "bias_trend_fit",
    f"""WITH g AS MATERIALIZED ({TRADE_CORE}), b AS {_SWEEP_BUCKETS}, w AS ({_SWEEP_SIZES}), u AS (SELECT * FROM b JOIN w USING (p, src_part, dst_part)),
e AS (SELECT p, l, set_idx, part_id, sum(n_edges) AS n FROM (SELECT p, l, set_idx, src_part AS part_id, n_edges FROM u UNION ALL SELECT p, l, set_idx, dst_part, n_edges FROM u) GROUP BY ALL),
f AS (SELECT s.p, s.l, s.set_idx, q.part_id, coalesce(e.n, 0) AS n FROM (SELECT DISTINCT p, l, set_idx FROM b) s JOIN (SELECT DISTINCT p, l, part_id FROM e) q ON q.p = s.p AND q.l = s.l LEFT JOIN e ON e.p = s.p AND e.l = s.l AND e.set_idx = s.set_idx AND e.part_id = q.part_id),
t AS (SELECT p, l, set_idx, CAST(sum(n) OVER (PARTITION BY p, l, part_id ORDER BY set_idx) AS DOUBLE) / CAST(sum(n) OVER (PARTITION BY p, l, part_id) AS DOUBLE) AS share FROM f),
s AS (SELECT p, l, round(max(d), 9) AS bias FROM (SELECT p, l, set_idx, max(share) - min(share) AS d FROM t GROUP BY ALL) GROUP BY ALL)
SELECT 'p' AS series, round(regr_slope(ln(bias), ln(p)), 6) AS exponent FROM s WHERE l = 8 UNION ALL SELECT 'l', round(regr_slope(ln(bias), ln(l)), 6) FROM s WHERE p = 32""",
)
def bias_trend_fit(spark, sf_dir):
    """Exponents of the bias measured on the trade graph's edges, over p at eight groups, and over l at 32 partitions."""
    edges = graphs.trade_core_edges(spark, sf_dir).withColumn("p", F.explode(F.array(*map(F.lit, _SWEEP_P))))
    place = lambda c: F.pmod(hashing.mix(F.col(c), 3), F.col("p")).cast("int").alias(c.replace("_id", "_part"))
    rows = sweep_bias(sweep_buckets(spark), edges.select("p", place("src_id"), place("dst_id")).groupBy("p", "src_part", "dst_part").agg(F.count("*").alias("n_edges")))
    series = lambda name, kept: rows.where(kept).select(F.lit(name).alias("series"), F.col(name).cast("double").alias("x"), "bias")
    return tuning.bias_trend(series("p", "l = 8").unionByName(series("l", "p = 32"))).select("series", F.round("exponent", 6).alias("exponent"))


def scan_points(o: tuning.Overheads, memory: float, block: float, reserve: float) -> list[tuple[int, int, int, bool]]:
    """(p, l, c, tuned): the tuned point, and points around it with fewer, more or larger partitions and groups that fit the memory."""
    best = tuning.autotune(o, memory, block, reserve)
    points = {(best["p"], best["l"], best["c"]): True}
    for p in sorted({max(4, best["p"] // 4), max(4, best["p"] // 2), best["p"], 2 * best["p"]}):
        most = tuning.choose_c(o, p, memory, reserve)
        for c in sorted({max(2, most // 2), most}):
            if 2 <= c <= most:
                least = tuning.choose_l(p, c)
                for n in sorted({least, min(p, 2 * least), p}):
                    points.setdefault((p, n, c), False)
    return [(*key, tuned) for key, tuned in sorted(points.items())]


def tuning_scan(spark, sf_dir, seed: int = 3) -> DataFrame:
    """Sets, loads, bias, bytes read, smallest read and modelled cost of the tuned (p, l, c) and the points around it, on the trade graph
    with a buffer for a third of its partitions. place: by modelled cost, equal ones by bias."""
    g = graphs.Graph(stored(graphs.Graph.from_tables(spark, sf_dir, "trade").nodes, "nodes"), stored(graphs.trade_edges(spark, sf_dir).select("src_id", "dst_id"), "edges"), "trade")
    n_nodes, n_edges = g.nodes.count(), g.edges.count()
    o = tuning.Overheads.of(n_nodes, n_edges, DIM, EDGE)
    memory, block = 1.02 * (o.node_bytes / 3 + 2 * o.edge_bytes / 9), o.edge_bytes / 256
    rows = []
    for p, n, c, tuned in scan_points(o, memory, block, 0):
        try:
            plan = policy.plan_two_level(p, n, c, 0, seed)
        except ValueError:  # two of these groups don't fit
            continue
        sizes = part.assign_partitions(g.nodes, p, seed).groupBy("part_id").agg((F.count("*") * DIM * 4).alias("bytes"))
        buckets = part.bucket_sizes(part.bucketed(g.edges, p, seed)).select("src_part", "dst_part", (F.col("n_edges") * EDGE).alias("bytes"))
        sizes, buckets = stored(sizes, "sizes"), stored(buckets, "buckets")
        io = metrics.io_bytes(plan.loads_df(spark), plan.sets_df(spark), sizes, buckets).first()
        least = min(sizes.agg(F.min("bytes")).first()[0], buckets.agg(F.min("bytes")).first()[0])
        bias = metrics.edge_permutation_bias(plan.buckets_df(spark), p).first().bias
        rows.append((p, n, c, tuned, len(plan.sets), plan.n_loads, float(bias), io.node_bytes + io.edge_bytes, int(least), tuning.epoch_cost(len(plan.sets), p, choose_alpha(o, block))))
    scan = spark.createDataFrame(rows, "p int, l int, c int, tuned boolean, n_sets int, n_loads int, bias double, io_bytes bigint, min_read bigint, epoch_cost double")
    return scan.withColumn("place", F.rank().over(Window.orderBy("epoch_cost", "bias")))


def choose_alpha(o: tuning.Overheads, block: float) -> float:
    """Partitions beyond which reads get smaller than a block."""
    return float(tuning.choose_p(o, block))


query("tuning_scan")(tuning_scan)
