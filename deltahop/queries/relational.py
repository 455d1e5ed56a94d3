"""Scans, sources, joins, aggregations, windows and set operations around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from deltahop import graphs, hashing
from deltahop.graphs import table
from deltahop.queries.registry import COPURCHASE, CUST_PART_PLAIN, TRADE, TRADE_CORE, mix, query
from deltahop.sources import store

R = lambda c, n=4: F.round(c, n)
DEGREE = f"SELECT src_id AS node_id, count(*) AS degree FROM ({TRADE_CORE}) GROUP BY 1"


def degree(spark, sf_dir):
    return graphs.trade_core_edges(spark, sf_dir).groupBy(F.col("src_id").alias("node_id")).agg(F.count("*").alias("degree"))


def t(name):
    return lambda spark, sf_dir: table(spark, sf_dir, name)


# ---- scans and sources

query("scan_orders", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'")(lambda s, d: table(s, d, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey"))
query("scan_filtered_lineitem", "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity > 45 AND l_shipdate >= TIMESTAMP '1997-01-01'")(
    lambda s, d: table(s, d, "lineitem").where((F.col("l_quantity") > 45) & (F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz"))).select("l_partkey", "l_suppkey")
)
for _k in ("csv", "json", "orc", "text"):
    query(f"{_k}_edge_roundtrip", COPURCHASE)(lambda s, d, k=_k: store.text_round_trip(graphs.copurchase_edges(s, d), k))

# ---- projection and filters

query("project_edge_features", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS weight, l_partkey * 16 + 1 AS part FROM lineitem")(
    lambda s, d: table(s, d, "lineitem").select("l_orderkey", "l_linenumber", R(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("weight"), graphs.typed("l_partkey", "part").alias("part"))
)
query("filter_edges_predicate", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_discount >= 0.05")(lambda s, d: table(s, d, "lineitem").where(F.col("l_quantity").between(10, 12) & (F.col("l_discount") >= 0.05)).select("l_orderkey", "l_partkey"))
query("filter_in_list", "SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")(lambda s, d: table(s, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY")).select("c_custkey"))
query("filter_like_part", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%ring%' OR regexp_matches(p_brand, '#1[0-9]$')")(lambda s, d: table(s, d, "part").where(F.col("p_name").like("%ring%") | F.col("p_brand").rlike("#1[0-9]$")).select("p_partkey", "p_name"))
query("case_degree_class", f"SELECT CASE WHEN degree >= 60 THEN 'hub' WHEN degree >= 30 THEN 'mid' ELSE 'low' END AS kind, count(*) AS n FROM ({DEGREE}) GROUP BY 1")(
    lambda s, d: degree(s, d).groupBy(F.when(F.col("degree") >= 60, "hub").when(F.col("degree") >= 30, "mid").otherwise("low").alias("kind")).agg(F.count("*").alias("n"))
)

# ---- joins

query("join_edges_nodes", "SELECT c_mktsegment, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1")(
    lambda s, d: table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
)
query("join_broadcast_nation", "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")(
    lambda s, d: table(s, d, "supplier").join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))
)
query("join_left_degree", f"SELECT c_custkey, coalesce(degree, 0) AS degree FROM customer LEFT JOIN ({DEGREE}) ON node_id = c_custkey * 16")(
    lambda s, d: table(s, d, "customer").join(degree(s, d), F.col("node_id") == graphs.typed("c_custkey", "customer"), "left").select("c_custkey", F.coalesce("degree", F.lit(0)).alias("degree"))
)
query("join_right_orders", "SELECT o_orderkey, c_name FROM (SELECT * FROM customer WHERE c_acctbal > 0) RIGHT JOIN orders ON c_custkey = o_custkey")(
    lambda s, d: table(s, d, "customer").where("c_acctbal > 0").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "right").select("o_orderkey", "c_name")
)
query("join_full_parts", "SELECT a.k AS left_key, b.k AS right_key FROM (SELECT p_partkey AS k FROM part WHERE p_size < 20) a FULL JOIN (SELECT p_partkey AS k FROM part WHERE p_size > 10) b ON a.k = b.k")(
    lambda s, d: table(s, d, "part").where("p_size < 20").select(F.col("p_partkey").alias("left_key")).join(table(s, d, "part").where("p_size > 10").select(F.col("p_partkey").alias("right_key")), F.col("left_key") == F.col("right_key"), "full")
)
query("join_semi_resident", f"SELECT src_id, dst_id FROM ({CUST_PART_PLAIN}) WHERE src_id / 16 IN (SELECT c_custkey FROM customer WHERE c_nationkey < 5)")(
    lambda s, d: graphs.customer_part_edges(s, d, False).join(table(s, d, "customer").where("c_nationkey < 5").select(graphs.typed("c_custkey", "customer").alias("src_id")), "src_id", "left_semi").select("src_id", "dst_id")
)
query("join_anti_isolated", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate >= TIMESTAMP '1998-06-01')")(
    lambda s, d: table(s, d, "customer").join(table(s, d, "orders").where("o_orderdate >= timestamp_ntz'1998-06-01'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")
)
query("join_cross_negatives", "SELECT n_nationkey, r_regionkey, n_regionkey = r_regionkey AS is_pos FROM nation CROSS JOIN region")(
    lambda s, d: table(s, d, "nation").crossJoin(F.broadcast(table(s, d, "region"))).select("n_nationkey", "r_regionkey", (F.col("n_regionkey") == F.col("r_regionkey")).alias("is_pos"))
)


@query("join_range_price_band", "SELECT a.p_partkey AS part, count(*) AS n FROM part a JOIN part b ON b.p_retailprice BETWEEN a.p_retailprice - 0.5 AND a.p_retailprice + 0.5 AND a.p_partkey <> b.p_partkey GROUP BY 1")
def join_range_price_band(s, d):
    """A range join as sums over price windows: a bin of the band's width and the two beside it hold all that a price can meet, so each
    row goes to three bins and running sums count its band there, in time linear in the rows however many share a price."""
    band = lambda by: F.expr(f"sum(m) OVER (PARTITION BY {by} ORDER BY p_retailprice RANGE BETWEEN 0.5D PRECEDING AND 0.5D FOLLOWING)")
    parts = table(s, d, "part").where("p_retailprice IS NOT NULL").groupBy("p_partkey", "p_retailprice").agg(F.count("*").alias("m"))
    own = parts.withColumn("own", band("p_partkey"))  # rows of the same key are no pairs
    home = F.floor(F.col("p_retailprice") / 0.5)
    prices = parts.groupBy("p_retailprice").agg(F.sum("m").alias("m"))
    binned = prices.withColumn("bin", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda k: home + k)))
    near = binned.withColumn("near", band("bin")).where(F.col("bin") == home).select("p_retailprice", "near")
    n = own.join(near, "p_retailprice").groupBy(F.col("p_partkey").alias("part")).agg(F.sum(F.col("m") * (F.col("near") - F.col("own"))).alias("n"))
    return n.where("n > 0")


@query(
    "join_asof_last_event",
    "SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT max(event_id) AS event_id, user_id, ts FROM events WHERE event_type = 'view' GROUP BY user_id, ts) v ON p.user_id = v.user_id AND p.ts >= v.ts",
)
def join_asof_last_event(s, d):
    """The last view at or before each purchase: both kinds in one order per user, the last view carried forward."""
    e = table(s, d, "events").where(F.col("event_type").isin("purchase", "view")).select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "last_view")


@query("join_interval_click_purchase", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts < c.ts + INTERVAL 1 HOUR")
def join_interval_click_purchase(s, d):
    """Time bins of one hour make the interval join an equi join: a purchase is in the click's bin or the next one."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("h"))
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t1"), "h")
    return c.join(p, ["user_id", "h"]).where("t1 >= t0 and t1 < t0 + interval 1 hour").select("click", "purchase")


query("join_lateral_top_line", "SELECT o_orderkey, l.l_partkey FROM orders, LATERAL (SELECT l_partkey FROM lineitem WHERE l_orderkey = o_orderkey ORDER BY l_extendedprice DESC, l_partkey LIMIT 1) l")(
    lambda s, d: table(s, d, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.max_by("l_partkey", F.struct("l_extendedprice", F.negative("l_partkey"))).alias("l_partkey")).join(table(s, d, "orders").select("o_orderkey"), "o_orderkey")
)
query("join_nullsafe", "SELECT count(*) AS n FROM (SELECT nullif(c_nationkey % 5, 0) AS k FROM customer) a JOIN (SELECT nullif(s_nationkey % 5, 0) AS k FROM supplier) b ON a.k IS NOT DISTINCT FROM b.k")(
    lambda s, d: table(s, d, "customer").select(F.expr("nullif(c_nationkey % 5, 0) as a")).groupBy("a").agg(F.count("*").alias("x")).join(table(s, d, "supplier").select(F.expr("nullif(s_nationkey % 5, 0) as b")).groupBy("b").agg(F.count("*").alias("y")), F.col("a").eqNullSafe(F.col("b"))).agg(F.sum(F.col("x") * F.col("y")).alias("n"))
)

# ---- aggregation

query("agg_degree", DEGREE)(degree)


@query("agg_degree_salted", DEGREE)
def agg_degree_salted(s, d):
    """Two steps for hubs: partial counts per salt, then their sums."""
    e = graphs.trade_core_edges(s, d).withColumn("salt", F.pmod(F.xxhash64("dst_id"), F.lit(16)))
    return e.groupBy("src_id", "salt").agg(F.count("*").alias("n")).groupBy(F.col("src_id").alias("node_id")).agg(F.sum("n").alias("degree"))


query("agg_sorted_neighbour_list", f"SELECT src_id AS node_id, string_agg(CAST(dst_id AS VARCHAR), ',' ORDER BY dst_id) AS nbrs FROM ({CUST_PART_PLAIN}) GROUP BY 1")(
    lambda s, d: graphs.customer_part_edges(s, d, False).groupBy(F.col("src_id").alias("node_id")).agg(F.array_join(F.array_sort(F.collect_list("dst_id")), ",").alias("nbrs"))
)
query("agg_distinct_nbrs", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders_ FROM lineitem GROUP BY 1")(lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders_")))
query("agg_approx_nbrs")(lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.countDistinct("l_partkey").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("sketch")))
query("agg_percentile", "SELECT p_type, quantile_cont(p_retailprice, 0.5) AS median FROM part GROUP BY 1")(lambda s, d: table(s, d, "part").groupBy("p_type").agg(F.percentile("p_retailprice", 0.5).alias("median")))
query("agg_grouping_sets_rel", "SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")(
    lambda s, d: table(s, d, "lineitem").groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], "l_returnflag", "l_linestatus").agg(F.grouping_id().cast("bigint").alias("g"), F.count("*").alias("n"))
)
query("agg_rollup_geo", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")(
    lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))
)
query("agg_cube_flag_status", "SELECT l_returnflag, l_linestatus, CAST(sum(l_linenumber) AS BIGINT) AS total FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.sum("l_linenumber").alias("total")))
query("agg_having_hubs", f"SELECT * FROM ({DEGREE}) WHERE degree > 60")(lambda s, d: degree(s, d).where("degree > 60"))
query("agg_filter_clause", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS closed, count(*) AS n FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("closed"), F.count("*").alias("n")))
query("agg_max_by_order", "SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS largest FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("largest")))
query("agg_stats_price", "SELECT p_type, round(stddev_samp(p_retailprice), 4) AS sd, round(corr(p_retailprice, p_size), 6) AS r, bool_and(p_size > 0) AS all_sized FROM part GROUP BY 1")(
    lambda s, d: table(s, d, "part").groupBy("p_type").agg(R(F.stddev_samp("p_retailprice")).alias("sd"), R(F.corr("p_retailprice", "p_size"), 6).alias("r"), F.bool_and(F.col("p_size") > 0).alias("all_sized"))
)
query("agg_pivot_segment", "SELECT c_nationkey, count(*) FILTER (WHERE c_mktsegment = 'BUILDING') AS BUILDING, count(*) FILTER (WHERE c_mktsegment = 'MACHINERY') AS MACHINERY FROM customer GROUP BY 1")(
    lambda s, d: table(s, d, "customer").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count("c_custkey")).na.fill(0)
)

# ---- windows

W = Window
query("win_rank_parts", "SELECT p_partkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.rank().over(W.partitionBy("p_brand").orderBy("p_size")).alias("rk"), F.dense_rank().over(W.partitionBy("p_brand").orderBy("p_size")).alias("dr"), F.row_number().over(W.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("rn"))
)
query("win_percent_rank", "SELECT s_suppkey, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)")(
    lambda s, d: table(s, d, "supplier").select("s_suppkey", R(F.percent_rank().over(W.partitionBy("s_nationkey").orderBy("s_acctbal")), 8).alias("pr"), R(F.cume_dist().over(W.partitionBy("s_nationkey").orderBy("s_acctbal")), 8).alias("cd"))
)
query("win_ntile_customers", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS INTEGER) AS q FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", F.ntile(4).over(W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias("q")))
query("win_lag_events", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda s, d: table(s, d, "events").select("event_id", F.lag("event_type").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("before"), F.lead("event_type").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("after"))
)
_WF = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
query("win_first_last_order", f"SELECT o_orderkey, first_value(o_orderkey) OVER {_WF} AS first_order, last_value(o_orderkey) OVER {_WF} AS last_order, nth_value(o_orderkey, 2) OVER {_WF} AS second_order FROM orders")(
    lambda s, d: (lambda w: table(s, d, "orders").select("o_orderkey", F.first("o_orderkey").over(w).alias("first_order"), F.last("o_orderkey").over(w).alias("last_order"), F.nth_value("o_orderkey", 2).over(w).alias("second_order")))(
        W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    )
)
query("win_running_degree", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(sum(1) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM lineitem")(
    lambda s, d: table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.sum(F.lit(1)).over(W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice").rowsBetween(W.unboundedPreceding, 0)).alias("running"))
)
query("win_moving_avg_events", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS m FROM events")(lambda s, d: table(s, d, "events").select("event_id", R(F.avg("value").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("m")))
query("win_range_7d", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 7 DAYS PRECEDING AND CURRENT ROW) AS n FROM orders")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", F.expr("count(*) over (partition by o_custkey order by o_orderdate range between interval 7 days preceding and current row)").alias("n"))
)

# ---- sorts, limits, sets

query("sort_top_degree", f"SELECT * FROM ({DEGREE}) ORDER BY degree DESC, node_id LIMIT 25")(lambda s, d: degree(s, d).orderBy(F.desc("degree"), "node_id").limit(25))
query("limit_offset_orders", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")(lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey").offset(40).limit(20))
query("topk_per_nation", "SELECT c_nationkey, c_custkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")(
    lambda s, d: table(s, d, "customer").withColumn("r", F.row_number().over(W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))).where("r <= 3").select("c_nationkey", "c_custkey")
)
_A, _B = "SELECT l_partkey AS k FROM lineitem WHERE l_suppkey < 20", "SELECT l_partkey AS k FROM lineitem WHERE l_suppkey BETWEEN 10 AND 30"
_ab = lambda s, d: (table(s, d, "lineitem").where("l_suppkey < 20").select(F.col("l_partkey").alias("k")), table(s, d, "lineitem").where("l_suppkey between 10 and 30").select(F.col("l_partkey").alias("k")))
for _n, _op, _f in (
    ("union_edges", "UNION", lambda a, b: a.union(b).distinct()),
    ("union_all_edges", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("intersect_nbrs", "INTERSECT", lambda a, b: a.intersect(b)),
    ("intersect_all_parts", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("except_delta", "EXCEPT", lambda a, b: a.subtract(b)),
    ("except_all_parts", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(_n, f"({_A}) {_op} ({_B})")(lambda s, d, f=_f: f(*_ab(s, d)))


# ---- subqueries, reshaping, sampling, nulls


def view(s, d, *names):
    for n in names:
        table(s, d, n).createOrReplaceTempView(f"dh_{n}")


@query("subq_scalar_avg", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
def subq_scalar_avg(s, d):
    view(s, d, "part")
    return s.sql("SELECT p_partkey FROM dh_part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM dh_part)")


@query("subq_exists_orders", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)")
def subq_exists_orders(s, d):
    view(s, d, "customer", "orders")
    return s.sql("SELECT c_custkey FROM dh_customer c WHERE EXISTS (SELECT 1 FROM dh_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)")


_REC = "WITH RECURSIVE walk(node_id, dist) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT {e}.dst_id, walk.dist + 1 FROM walk JOIN {e} ON {e}.src_id = walk.node_id WHERE walk.dist < 3) SELECT DISTINCT node_id, dist FROM walk"


@query("khop_recursive", "WITH RECURSIVE geo AS ({g}), walk(node_id, dist) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT geo.dst_id, walk.dist + 1 FROM walk JOIN geo ON geo.src_id = walk.node_id WHERE walk.dist < 3) SELECT DISTINCT node_id, dist FROM walk".format(g="SELECT c_custkey * 16 AS src_id, CAST(c_nationkey AS BIGINT) * 16 + 3 AS dst_id FROM customer UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 16 + 3, CAST(n_regionkey AS BIGINT) * 16 + 4 FROM nation"))
def khop_recursive(s, d):
    graphs.geo_edges(s, d).createOrReplaceTempView("dh_geo")
    return s.sql(_REC.format(e="dh_geo"))


query("explode_embedding_dims", "SELECT vec_id, CAST(unnest(range(64)) AS INTEGER) AS dim, round(CAST(unnest(embedding) AS DOUBLE), 6) AS v FROM embeddings")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "v")).select("vec_id", "dim", R(F.col("v").cast("double"), 6).alias("v"))
)
query("unpivot_prices", "SELECT p_partkey, name, value FROM (SELECT p_partkey, CAST(p_size AS DOUBLE) AS size, p_retailprice AS price FROM part) UNPIVOT (value FOR name IN (size, price))")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value")
)
query("sample_hash_edges", f"SELECT src_id, dst_id FROM ({CUST_PART_PLAIN}) WHERE {mix('src_id * 31 + dst_id', 9)} % 10 = 0")(lambda s, d: graphs.customer_part_edges(s, d, False).where(F.pmod(hashing.mix(F.col("src_id") * 31 + F.col("dst_id"), 9), F.lit(10)) == 0).select("src_id", "dst_id"))
query("sample_stratified_labels", f"SELECT doc_id, lang FROM documents WHERE {mix('doc_id', 4)} % 100 < CASE lang WHEN 'en' THEN 10 ELSE 40 END")(
    lambda s, d: table(s, d, "documents").where(F.pmod(hashing.mix(F.col("doc_id"), 4), F.lit(100)) < F.when(F.col("lang") == "en", 10).otherwise(40)).select("doc_id", "lang")
)
query("dedupe_latest_event", "SELECT user_id, event_type, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts DESC, event_id DESC) = 1")(
    lambda s, d: table(s, d, "events").groupBy("user_id", "event_type").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))
)
__all__ = ["TRADE"]
