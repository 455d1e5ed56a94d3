"""Layers, decoders, negatives and losses. Features are small integers, so sums are exact in both engines."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from deltahop import graphs, hashing
from deltahop.operators import layers, packed_layers, packing
from deltahop.operators import sampling as s
from deltahop.plans import metrics
from deltahop.queries.registry import mix, query
from deltahop.queries.sampling import delta, sql_delta

D = 2
X = "[CAST(node_id % 7 AS DOUBLE), CAST(node_id % 11 AS DOUBLE)]"


def features(nodes):
    return nodes.select("batch_id", "node_id", F.array((F.col("node_id") % 7).cast("double"), (F.col("node_id") % 11).cast("double")).alias("h"))


def flat(df, d=D, digits=None):
    cols = [(F.round(F.col("h")[i], digits) if digits else F.col("h")[i]).alias(f"h{i}") for i in range(d)]
    return df.select("batch_id", "node_id", *cols)


FAN = [10, 10]
BASE = sql_delta("core", FAN).rstrip() + ", x0 AS (SELECT batch_id, node_id, CAST(node_id % 7 AS DOUBLE) AS h0, CAST(node_id % 11 AS DOUBLE) AS h1 FROM nodes)"


def _sql_add(src, dst, least):
    return f", {dst} AS (SELECT n.batch_id, n.node_id, x.h0 + coalesce(a.h0, 0) AS h0, x.h1 + coalesce(a.h1, 0) AS h1 FROM nodes n JOIN {src} x USING (batch_id, node_id) LEFT JOIN (SELECT e.batch_id, e.node_id, sum(y.h0) AS h0, sum(y.h1) AS h1 FROM nbrs e JOIN {src} y ON y.batch_id = e.batch_id AND y.node_id = e.nbr_id WHERE e.delta_idx >= {least} GROUP BY ALL) a ON a.batch_id = n.batch_id AND a.node_id = n.node_id WHERE n.delta_idx >= {least})"


def sample(spark, sf_dir):
    return delta(spark, sf_dir, "core", FAN)


def outputs(x, i=1):
    return x.nodes.where(F.col("delta_idx") >= i), x.nbrs.where(F.col("delta_idx") >= i)


@query("agg_add_layer1", BASE + _sql_add("x0", "x1", 1) + " SELECT * FROM x1")
def agg_add_layer1(spark, sf_dir):
    x = sample(spark, sf_dir)
    return flat(layers.additive_layer(*outputs(x), features(x.nodes), D))


for _n in ("agg_add_2layer", "forward_2layer_add"):
    query(_n, BASE + _sql_add("x0", "x1", 1) + _sql_add("x1", "x2", 2) + " SELECT * FROM x2")(
        lambda spark, sf_dir: (lambda x: flat(layers.forward(x, features(x.nodes), lambda i, nodes, nbrs, h: layers.additive_layer(nodes, nbrs, h, D))))(sample(spark, sf_dir))
    )


@query("gather_repr", BASE + " SELECT e.batch_id, e.node_id, e.nbr_id, y.h0, y.h1 FROM nbrs e JOIN x0 y ON y.batch_id = e.batch_id AND y.node_id = e.nbr_id")
def gather_repr(spark, sf_dir):
    x = sample(spark, sf_dir)
    return layers.gather(x.nbrs, features(x.nodes)).select("batch_id", "node_id", "nbr_id", F.col("hn")[0].alias("h0"), F.col("hn")[1].alias("h1"))


@query("segment_sum", "SELECT o_custkey AS node_id, CAST(sum(o_orderkey % 97) AS BIGINT) AS total FROM orders GROUP BY 1")
def segment_sum(spark, sf_dir):
    """The packed primitive on the orders of each customer, dealt out in 16 slices."""
    orders = graphs.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("node_id"), (F.col("o_orderkey") % 97).alias("v"), F.pmod("o_custkey", F.lit(16)).alias("slice"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("node_id", kind="stable")
        ids, starts = np.unique(pdf["node_id"].to_numpy(), return_index=True)
        return pd.DataFrame({"node_id": ids, "total": packing.segment_sum(pdf["v"].to_numpy(), starts)})

    return orders.groupBy("slice").applyInPandas(run, "node_id bigint, total bigint")


@query("forward_packed_2layer", BASE + _sql_add("x0", "x1", 1) + _sql_add("x1", "x2", 2) + " SELECT * FROM x2")
def forward_packed_2layer(spark, sf_dir):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        batch = packing.Packed.of(pdf.iloc[0])
        h0 = np.stack([batch.vertex_ids % 7, batch.vertex_ids % 11], 1).astype(float)
        h, _ = packed_layers.run_forward(batch, h0, [packed_layers.AddLayer(), packed_layers.AddLayer()])
        return pd.DataFrame({"batch_id": pdf["batch_id"].iloc[0], "node_id": batch.vertex_ids[-len(h) :], "h0": h[:, 0], "h1": h[:, 1]})

    return packing.pack(sample(spark, sf_dir)).groupBy("batch_id").applyInPandas(run, "batch_id int, node_id bigint, h0 double, h1 double")


WS, WN, B = [[0.5, -0.25], [0.125, 1.0]], [[1.0, 0.5], [-0.5, 0.25]], [0.1, -0.2]
_SAGE = """ SELECT n.batch_id, n.node_id, round(greatest(0.5 * x.h0 - 0.25 * x.h1 + {a}0 * 1.0 + 0.5 * {a}1 + 0.1, 0), 6) AS h0, round(greatest(0.125 * x.h0 + x.h1 - 0.5 * {a}0 + 0.25 * {a}1 - 0.2, 0), 6) AS h1
FROM nodes n JOIN x0 x USING (batch_id, node_id) LEFT JOIN (SELECT e.batch_id, e.node_id, {f}(y.h0) AS m0, {f}(y.h1) AS m1 FROM nbrs e JOIN x0 y ON y.batch_id = e.batch_id AND y.node_id = e.nbr_id GROUP BY ALL) a ON a.batch_id = n.batch_id AND a.node_id = n.node_id WHERE n.delta_idx >= 1"""


def _sage_sql(f):
    return BASE + _SAGE.format(a="@", f=f).replace("@0", "coalesce(a.m0, 0)").replace("@1", "coalesce(a.m1, 0)")


def _sage(spark, sf_dir, aggregator):
    x = sample(spark, sf_dir)
    return flat(layers.sage_layer(*outputs(x), features(x.nodes), D, WS, WN, B, "relu", aggregator), D, 6)


query("sage_mean_layer1", _sage_sql("avg"))(lambda spark, sf_dir: _sage(spark, sf_dir, "mean"))
query("sage_max_layer1", _sage_sql("max"))(lambda spark, sf_dir: _sage(spark, sf_dir, "max"))
query("sage_sum_layer1", _sage_sql("sum"))(lambda spark, sf_dir: _sage(spark, sf_dir, "sum"))


@query("agg_custom_max", BASE + " SELECT e.batch_id, e.node_id, max(y.h0) - min(y.h0) AS h0, max(y.h1) - min(y.h1) AS h1 FROM nbrs e JOIN x0 y ON y.batch_id = e.batch_id AND y.node_id = e.nbr_id GROUP BY ALL")
def agg_custom_max(spark, sf_dir):
    layers.register_aggregator("spread", lambda c: F.max(c) - F.min(c))
    x = sample(spark, sf_dir)
    return flat(layers.neighbourhood(x.nbrs, features(x.nodes), D, "spread").withColumnRenamed("agg", "h"))


HEAD = {"weights": [[0.1, -0.2], [0.3, 0.05]], "a_self": [0.2, -0.1], "a_nbr": [0.15, 0.25]}
_GAT = """, z AS (SELECT batch_id, node_id, 0.1 * h0 - 0.2 * h1 AS z0, 0.3 * h0 + 0.05 * h1 AS z1 FROM x0),
p AS (SELECT batch_id, node_id, nbr_id, false AS is_self FROM nbrs WHERE delta_idx >= 1 UNION ALL SELECT batch_id, node_id, node_id, true FROM nodes WHERE delta_idx >= 1),
e AS (SELECT p.*, zj.z0, zj.z1, 0.2 * zi.z0 - 0.1 * zi.z1 + 0.15 * zj.z0 + 0.25 * zj.z1 AS pre FROM p JOIN z zi ON zi.batch_id = p.batch_id AND zi.node_id = p.node_id JOIN z zj ON zj.batch_id = p.batch_id AND zj.node_id = p.nbr_id),
l AS (SELECT *, CASE WHEN pre > 0 THEN pre ELSE 0.2 * pre END AS s FROM e),
w AS (SELECT *, exp(s - max(s) OVER (PARTITION BY batch_id, node_id)) AS u FROM l),
a AS (SELECT *, u / sum(u) OVER (PARTITION BY batch_id, node_id) AS alpha FROM w)"""


@query("gat_attention_weights", BASE + _GAT + " SELECT batch_id, node_id, nbr_id, is_self, round(alpha, 7) AS alpha FROM a")
def gat_attention_weights(spark, sf_dir):
    x = sample(spark, sf_dir)
    return layers.attention(*outputs(x), features(x.nodes), **HEAD).select("batch_id", "node_id", "nbr_id", "is_self", F.round("alpha", 7).alias("alpha"))


@query("gat_layer1", BASE + _GAT + " SELECT batch_id, node_id, round(sum(alpha * z0), 5) AS h0, round(sum(alpha * z1), 5) AS h1, round(sum(alpha * z0), 5) AS h2, round(sum(alpha * z1), 5) AS h3 FROM a GROUP BY ALL")
def gat_layer1(spark, sf_dir):
    x = sample(spark, sf_dir)
    return flat(layers.gat_layer(*outputs(x), features(x.nodes), [HEAD, HEAD]), 4, 5)


EMB = "SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings"


def _vectors(spark, sf_dir):
    return graphs.table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))


def _next(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    return v.join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("w")), "vec_id")


query("dot_score", f"SELECT a.vec_id, round(list_inner_product(a.v, b.v), 8) AS score FROM ({EMB}) a JOIN ({EMB}) b ON b.vec_id = a.vec_id + 1")(lambda spark, sf_dir: _next(spark, sf_dir).select("vec_id", F.round(layers.dot(F.col("v"), F.col("w")), 8).alias("score")))
query("distmult_score", f"SELECT a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: a.v[i] * (CAST(i % 3 AS DOUBLE) - 1) * b.v[i])), 8) AS score FROM ({EMB}) a JOIN ({EMB}) b ON b.vec_id = a.vec_id + 1")(
    lambda spark, sf_dir: _next(spark, sf_dir).select("vec_id", F.round(layers.distmult(F.col("v"), F.transform(F.sequence(F.lit(1), F.lit(64)), lambda i: (i % 3 - 1).cast("double")), F.col("w")), 8).alias("score"))
)


@query("softmax_ce_loss", "SELECT round(avg(ln(exp(v[1]) + exp(v[2]) + exp(v[3]) + exp(v[4])) - v[1 + label % 4]), 8) AS loss FROM (SELECT embedding::DOUBLE[] AS v, label FROM embeddings)")
def softmax_ce_loss(spark, sf_dir):
    rows = graphs.table(spark, sf_dir, "embeddings").select(F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("logits"), (F.col("label") % 4).alias("label"))
    return layers.softmax_loss(rows, 4).agg(F.round(F.avg("loss"), 8).alias("loss"))


def _examples(spark, sf_dir):
    edges = graphs.customer_part_edges(spark, sf_dir, relational=False)
    return edges.select(F.floor(F.col("src_id") / 1600).cast("int").alias("batch_id"), (F.col("src_id") * 1000000 + F.col("dst_id")).alias("example_id"), "src_id", "rel_id", "dst_id")


_EX = "SELECT DISTINCT CAST(floor(o_custkey / 100) AS INTEGER) AS batch_id, o_custkey * 16000000 + l_partkey * 16 + 1 AS example_id, o_custkey * 16 AS src_id, 0 AS rel_id, l_partkey * 16 + 1 AS dst_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


def _neg_sql(n):
    """Draws over the places of all parts in hash order; the given tables have more parts than negatives."""
    draw = "('0x' || substr(md5(concat_ws(':', 5, 0, b.batch_id, t.k)), 1, 8))::BIGINT"
    return f"""SELECT batch_id, candidate_id FROM (SELECT batch_id, candidate_id, row_number() OVER (PARTITION BY batch_id ORDER BY k) AS r FROM (
SELECT d.batch_id, p.candidate_id, min(d.k) AS k FROM (SELECT b.batch_id, t.k, ({draw} * (SELECT count(*) FROM part)) >> 32 AS place FROM (SELECT DISTINCT batch_id FROM ({_EX})) b CROSS JOIN range({2 * n}) t(k)) d
JOIN (SELECT p_partkey * 16 + 1 AS candidate_id, row_number() OVER (ORDER BY {mix('p_partkey * 16 + 1', '(5 * 1009 + 0)')}, p_partkey) - 1 AS place FROM part) p USING (place) GROUP BY ALL)) WHERE r <= {n}"""


def _negatives(spark, sf_dir, n):
    pool = graphs.table(spark, sf_dir, "part").select(graphs.typed("p_partkey", "part").alias("node_id"))
    return layers.sample_negatives(_examples(spark, sf_dir), pool, n, 5, 0)


query("negatives_per_batch", _neg_sql(50))(lambda spark, sf_dir: _negatives(spark, sf_dir, 50))

_SC = f"WITH ex AS ({_EX}), ng AS ({_neg_sql(5)}), c AS (SELECT batch_id, example_id, src_id, dst_id, dst_id AS candidate_id, true AS is_pos FROM ex UNION ALL SELECT batch_id, example_id, src_id, candidate_id, candidate_id, false FROM ex JOIN ng USING (batch_id) WHERE candidate_id <> dst_id), s AS (SELECT *, CAST((src_id * 31 + dst_id * 17) % 23 AS DOUBLE) / 4 AS score FROM c) "


def _scored(spark, sf_dir):
    rows = layers.corrupt(_examples(spark, sf_dir), _negatives(spark, sf_dir, 5))
    return rows.withColumn("score", ((F.col("src_id") * 31 + F.col("dst_id") * 17) % 23).cast("double") / 4)


query("link_candidates", _SC + "SELECT batch_id, example_id, candidate_id, is_pos, score FROM s")(lambda spark, sf_dir: _scored(spark, sf_dir).select("batch_id", "example_id", "candidate_id", "is_pos", "score"))
query("link_logloss", _SC + "SELECT round(avg(greatest(-y, 0) + ln(1 + exp(-abs(y)))), 7) AS loss FROM (SELECT CASE WHEN is_pos THEN score ELSE -score END AS y FROM s)")(
    lambda spark, sf_dir: layers.link_loss(_scored(spark, sf_dir), "logistic").select(F.round("loss", 7).alias("loss"))
)
query("link_softmax_loss", _SC + "SELECT round(avg(l), 7) AS loss FROM (SELECT example_id, ln(sum(exp(score))) - max(score) FILTER (WHERE is_pos) AS l FROM s GROUP BY 1)")(
    lambda spark, sf_dir: layers.link_loss(_scored(spark, sf_dir)).select(F.round("loss", 7).alias("loss"))
)

# Reciprocal ranks of held-out edges (a twentieth, by hash) under a DistMult decoder over fixed vectors.
_HELD = f"SELECT * FROM ({_EX}) WHERE {mix('src_id * 31 + dst_id', 3)} % 100 >= 95"
_SIDES = "CAST(src_id % 7 AS DOUBLE) AS s0, CAST(src_id % 11 AS DOUBLE) * 0.5 AS s1"


def _held(spark, sf_dir):
    return _examples(spark, sf_dir).where(F.pmod(hashing.mix(F.col("src_id") * 31 + F.col("dst_id"), 3), F.lit(100)) >= 95)


def _node_vectors(spark, sf_dir):
    nodes = graphs.Graph.from_edges(graphs.customer_part_edges(spark, sf_dir, relational=False)).nodes
    return features(nodes.withColumn("batch_id", F.lit(0))).select("node_id", "h")


def _mrr_all_sql(share):
    return f"""WITH v AS (SELECT DISTINCT unnest([src_id, dst_id]) AS node_id FROM ({_EX})), e AS (SELECT example_id, dst_id, {_SIDES} FROM ({_HELD})),
o AS (SELECT *, s0 * (dst_id % 7) + s1 * (dst_id % 11) AS own FROM e),
r AS (SELECT example_id, 1 + sum(CASE WHEN node_id = dst_id THEN 0 WHEN x > own THEN 1.0 WHEN x = own THEN {share} ELSE 0 END) AS rank FROM (SELECT o.*, v.node_id, s0 * (v.node_id % 7) + s1 * (v.node_id % 11) AS x FROM o CROSS JOIN v) GROUP BY 1)
SELECT count(*) AS n, round(avg(1 / rank), 9) AS mrr FROM r"""


for _n, _ties, _share in (("mrr_all", "mid", 0.5), ("mrr_optimistic", "optimistic", 0.0), ("mrr_pessimistic", "pessimistic", 1.0)):
    query(_n, _mrr_all_sql(_share))(
        lambda spark, sf_dir, t=_ties: layers.rank_against_all(_held(spark, sf_dir), _node_vectors(spark, sf_dir), [[1.0, 0.5]], t).agg(F.count("*").alias("n"), F.round(F.avg(1 / F.col("rank")), 9).alias("mrr"))
    )


@query(
    "mrr_sampled",
    f"""WITH ng AS ({_neg_sql(50)}), e AS (SELECT batch_id, example_id, dst_id, {_SIDES} FROM ({_HELD})),
r AS (SELECT example_id, 1 + sum(CASE WHEN x > own THEN 1.0 WHEN x = own THEN 0.5 ELSE 0 END) AS rank FROM (SELECT example_id, s0 * (dst_id % 7) + s1 * (dst_id % 11) AS own, s0 * (candidate_id % 7) + s1 * (candidate_id % 11) AS x FROM e JOIN ng USING (batch_id) WHERE candidate_id <> dst_id) GROUP BY 1)
SELECT count(*) AS n, round(avg(1 / rank), 9) AS mrr FROM r""",
)
def mrr_sampled(spark, sf_dir):
    rows = layers.corrupt(_held(spark, sf_dir), _negatives(spark, sf_dir, 50))
    side = lambda c: F.array((F.col(c) % 7).cast("double"), (F.col(c) % 11).cast("double"))
    scored = rows.withColumn("score", layers.distmult(side("src_id"), F.array(F.lit(1.0), F.lit(0.5)), side("dst_id")))
    return metrics.mrr(scored, "mid").select("n", F.round("mrr", 9).alias("mrr"))


__all__ = ["hashing", "s"]
