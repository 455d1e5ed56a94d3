"""Scalar functions by family, and user-defined functions of every kind."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from deltahop import functions as fn
from deltahop import graphs
from deltahop.graphs import table
from deltahop.operators import partitioning as part
from deltahop.queries.registry import CUST_PART_PLAIN, query

R = F.round

query("fn_string_tokens", "SELECT p_partkey, upper(trim(p_name)) AS u, split_part(p_name, ' ', 1) AS w, substring(p_type, 2, 3) AS s, length(p_name) AS n, lpad(CAST(p_size AS VARCHAR), 4, '0') AS z, instr(p_name, 'g') AS i, replace(p_brand, '#', '-') AS b, concat_ws('/', p_brand, p_type) AS c FROM part")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("u"), F.split("p_name", " ")[0].alias("w"), F.substring("p_type", 2, 3).alias("s"), F.length("p_name").cast("bigint").alias("n"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("z"), F.instr("p_name", "g").cast("bigint").alias("i"), F.regexp_replace("p_brand", "#", "-").alias("b"), F.concat_ws("/", "p_brand", "p_type").alias("c"))
)
query("fn_url_parts", "SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_extract(url, '^https?://([^/]*)', 1) AS host, length(regexp_extract_all(html, '<p>')) AS n FROM pages")(
    lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("url", "^(https?)://", 1).alias("scheme"), F.regexp_extract("url", "^https?://([^/]*)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit("<p>"), 0)).cast("bigint").alias("n"))
)
query("fn_levenshtein_parts", "SELECT a.p_partkey, levenshtein(a.p_name, b.p_name) AS far FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 1")(
    lambda s, d: (lambda p: p.join(p.select((F.col("p_partkey") - 1).alias("p_partkey"), F.col("p_name").alias("other")), "p_partkey").select("p_partkey", F.levenshtein("p_name", "other").cast("bigint").alias("far")))(table(s, d, "part").select("p_partkey", "p_name"))
)
query("fn_date_edges", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, year(o_orderdate) AS y, quarter(o_orderdate) AS q, month(o_orderdate) AS mo, dayofweek(o_orderdate) + 1 AS dow, o_orderdate + INTERVAL 10 DAYS AS later, datediff('day', DATE '1992-01-01', o_orderdate::DATE) AS days FROM orders")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.year("o_orderdate").cast("bigint").alias("y"), F.quarter("o_orderdate").cast("bigint").alias("q"), F.month("o_orderdate").cast("bigint").alias("mo"), F.dayofweek("o_orderdate").cast("bigint").alias("dow"), (F.col("o_orderdate") + F.expr("interval 10 days")).alias("later"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"))
)
query("fn_event_hour", "SELECT hour(ts) AS h, count(*) AS n, max(epoch_us(ts)) AS last FROM events GROUP BY 1")(
    lambda s, d: table(s, d, "events").groupBy(F.hour("ts").cast("bigint").alias("h")).agg(F.count("*").alias("n"), F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("last"))
)
query("fn_math_scores", "SELECT p_partkey, p_partkey % 7 AS m, floor(p_retailprice / 10)::BIGINT AS f, ceil(p_retailprice / 10)::BIGINT AS c, round(sqrt(p_retailprice), 6) AS r, round(exp(p_size / 50.0), 6) AS e, round(ln(p_retailprice), 6) AS l, round(pow(p_size, 1.5), 5) AS p, greatest(p_size, 20) AS g, sign(p_size - 25)::INTEGER AS s, p_partkey & 12 AS b FROM part")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.pmod("p_partkey", F.lit(7)).alias("m"), F.floor(F.col("p_retailprice") / 10).alias("f"), F.ceil(F.col("p_retailprice") / 10).alias("c"), R(F.sqrt("p_retailprice"), 6).alias("r"), R(F.exp(F.col("p_size") / 50.0), 6).alias("e"), R(F.log("p_retailprice"), 6).alias("l"), R(F.pow("p_size", F.lit(1.5)), 5).alias("p"), F.greatest("p_size", F.lit(20)).alias("g"), F.signum(F.col("p_size") - 25).cast("int").alias("s"), F.col("p_partkey").bitwiseAND(12).alias("b"))
)
_V = lambda s, d: table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
_VS = "SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings"
query("fn_array_dot", f"SELECT vec_id, round(list_inner_product(v, v), 8) AS dot FROM ({_VS})")(lambda s, d: _V(s, d).select("vec_id", R(F.aggregate(F.transform("v", lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 8).alias("dot")))
query("fn_array_norm", f"SELECT vec_id, round(list_sum(list_transform(v, lambda x: abs(x))), 7) AS l1, round(list_max(v), 7) AS top FROM ({_VS})")(lambda s, d: _V(s, d).select("vec_id", R(F.aggregate("v", F.lit(0.0), lambda a, x: a + F.abs(x)), 7).alias("l1"), R(F.array_max("v"), 7).alias("top")))
query("fn_array_cosine", f"SELECT a.vec_id, round(list_cosine_similarity(a.v, b.v), 7) AS c FROM ({_VS}) a JOIN ({_VS}) b ON b.vec_id = a.vec_id + 1")(
    lambda s, d: (lambda dot, v: v.join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("w")), "vec_id").select("vec_id", R(dot("v", "w") / F.sqrt(dot("v", "v") * dot("w", "w")), 7).alias("c")))(lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda t, x: t + x), _V(s, d))
)
query("fn_array_overlap", f"WITH n AS (SELECT src_id, list(dst_id ORDER BY dst_id) AS l FROM ({CUST_PART_PLAIN}) GROUP BY 1) SELECT a.src_id, len(list_intersect(a.l, b.l)) AS common, len(list_filter(a.l, lambda x: x % 32 = 1)) AS even, a.l[1] AS first, a.l[len(a.l)] AS last FROM n a JOIN n b ON b.src_id = a.src_id + 16")(
    lambda s, d: (lambda n: n.join(n.select((F.col("src_id") - 16).alias("src_id"), F.col("l").alias("m")), "src_id").select("src_id", F.size(F.array_intersect("l", "m")).cast("bigint").alias("common"), F.size(F.filter("l", lambda x: x % 32 == 1)).cast("bigint").alias("even"), F.element_at("l", 1).alias("first"), F.element_at("l", -1).alias("last")))(
        graphs.customer_part_edges(s, d, False).groupBy("src_id").agg(F.array_sort(F.collect_list("dst_id")).alias("l"))
    )
)
query("fn_map_rel_counts", "SELECT l_suppkey, string_agg(l_returnflag || '=' || n, ',' ORDER BY l_returnflag) AS counts FROM (SELECT l_suppkey, l_returnflag, count(*) AS n FROM lineitem GROUP BY ALL) WHERE l_returnflag <> 'N' GROUP BY 1")(
    lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey", "l_returnflag").agg(F.count("*").alias("n")).groupBy("l_suppkey").agg(F.map_from_entries(F.collect_list(F.struct("l_returnflag", "n"))).alias("m")).withColumn("m", F.map_filter("m", lambda k, v: k != "N")).select(
        "l_suppkey", F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.element_at(F.col("m"), k).cast("string"))), ",").alias("counts")
    )
)
query("fn_json_item", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, json_keys(props)[1] AS name FROM events")(
    lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"), F.json_object_keys("props")[0].alias("name"))
)
query("fn_struct_edge", "SELECT l_orderkey, l_linenumber, l_partkey, l_partkey * 16 + 1 AS src, l_suppkey * 16 + 2 AS dst FROM lineitem")(
    lambda s, d: table(s, d, "lineitem").withColumn("e", F.struct(graphs.typed("l_partkey", "part").alias("src"))).withColumn("e", F.col("e").withField("dst", graphs.typed("l_suppkey", "supplier"))).select("l_orderkey", "l_linenumber", "l_partkey", "e.src", "e.dst")
)
query("fn_null_handling", "SELECT c_custkey, coalesce(nullif(c_nationkey % 3, 0), -1) AS a, CASE WHEN nullif(c_nationkey % 3, 0) IS NULL THEN 'none' ELSE 'some' END AS b FROM customer")(
    lambda s, d: table(s, d, "customer").withColumn("k", F.expr("nullif(c_nationkey % 3, 0)")).select("c_custkey", F.coalesce("k", F.lit(-1)).alias("a"), F.nvl2("k", F.lit("some"), F.lit("none")).alias("b"))
)
query("fn_cast_decimal", "SELECT p_partkey, CAST(CAST(p_retailprice AS DECIMAL(18,4)) * 3 AS VARCHAR) AS x, TRY_CAST(p_name AS INTEGER) AS bad, CAST(p_size AS VARCHAR) AS t FROM part")(
    lambda s, d: table(s, d, "part").select("p_partkey", (F.col("p_retailprice").cast("decimal(18,4)") * 3).cast("string").alias("x"), F.col("p_name").try_cast("int").alias("bad"), F.col("p_size").cast("string").alias("t"))
)
query("fn_priority_hash", "SELECT c_custkey, md5(concat_ws(':', 7, 0, c_custkey)) AS p, sha256(c_name) AS s FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", F.md5(F.concat_ws(":", F.lit(7), F.lit(0), "c_custkey")).alias("p"), F.sha2("c_name", 256).alias("s")))

# ---- user-defined functions

query("udf_priority", "SELECT c_custkey, md5(concat_ws(':', 7, c_custkey)) AS p FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", fn.priority_text(F.concat_ws(":", F.lit(7), "c_custkey")).alias("p")))
query("udf_vec_norm", f"SELECT vec_id, round(sqrt(list_inner_product(v, v)), 7) AS norm FROM ({_VS})")(lambda s, d: _V(s, d).select("vec_id", R(fn.vector_norm("v"), 7).alias("norm")))
query("map_score_candidates", f"SELECT vec_id, CAST(q AS INTEGER) AS query, round(v[q + 1] - v[q + 2], 7) AS score FROM ({_VS}), range(3) t(q)")(
    lambda s, d: fn.score_candidates(_V(s, d), np.eye(64)[:3] - np.eye(64)[1:4]).select("vec_id", "query", R("score", 7).alias("score"))
)


@query("cogroup_vector_update", "SELECT v.vec_id AS node_id, round(v.h - 0.5 * coalesce(g.g, 0), 6) AS h FROM (SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS h FROM embeddings) v LEFT JOIN (SELECT user_id AS vec_id, sum(value) AS g FROM events GROUP BY 1) g USING (vec_id)")
def cogroup_vector_update(s, d):
    vectors = _V(s, d).select(F.col("vec_id").alias("node_id"), F.slice("v", 1, 1).alias("h"))
    grads = table(s, d, "events").select(F.col("user_id").alias("node_id"), F.array("value").alias("g"))
    return fn.apply_sparse_updates(vectors, grads, 0.5).select("node_id", R(F.col("h")[0], 6).alias("h"))


query("udaf_vec_sum", "SELECT label, CAST(unnest(range(64)) AS INTEGER) AS dim, round(unnest(t), 6) AS total FROM (SELECT label, list(x ORDER BY k) AS t FROM (SELECT label, k, sum(x) AS x FROM (SELECT label, unnest(range(64)) AS k, unnest(embedding::DOUBLE[]) AS x FROM embeddings) GROUP BY ALL) GROUP BY 1)")(
    lambda s, d: table(s, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v")).groupBy("label").agg(fn.vector_sum("v").alias("t")).select("label", F.posexplode("t").alias("dim", "total")).select("label", "dim", R("total", 6).alias("total"))
)


@query("udtf_khop", f"SELECT src_id, dst_id AS node_id, 1 AS dist FROM ({CUST_PART_PLAIN})")
def udtf_khop(s, d):
    adj = part.adjacency(graphs.customer_part_edges(s, d, False), "out")
    part.packed_adjacency(adj).select(F.col("node_id").alias("src_id"), "nbrs").createOrReplaceTempView("dh_packed")
    s.udtf.register("khop_expand", fn.KhopExpand)
    return s.sql("SELECT src_id, k.node_id, k.dist FROM dh_packed, LATERAL khop_expand(nbrs, 1) k")


@query("sqlfn_dot", f"SELECT vec_id, round(list_inner_product(v, v), 7) AS dot, md5(concat_ws(':', 7, vec_id, vec_id + 1)) AS p FROM ({_VS})")
def sqlfn_dot(s, d):
    fn.register_sql(s)
    _V(s, d).createOrReplaceTempView("dh_vectors")
    return s.sql("SELECT vec_id, round(dh_dot(v, v), 7) AS dot, dh_priority(7, vec_id, vec_id + 1) AS p FROM dh_vectors")
