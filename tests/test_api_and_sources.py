"""The facade and the synthetic graphs."""

from pyspark.sql import functions as F

from deltahop.api import Engine
from deltahop.sources import synthetic


def test_synthetic_source_equals_the_plan_and_has_hubs(spark):
    synthetic.register(spark)
    read = spark.read.format("synthetic_graph").option("nodes", 500).option("edges", 4000).option("relations", 3).option("seed", 2).load()
    made = synthetic.hub_graph(spark, 500, 4000, relations=3, seed=2)
    rows = lambda df: sorted(tuple(r)[:3] for r in df.collect())
    assert rows(read) == rows(made)
    degree = [r["count"] for r in made.groupBy("dst_id").count().orderBy(F.desc("count")).collect()]
    assert degree[0] > 10 * degree[len(degree) // 2]


def test_engine_walk_through(spark, sf):
    engine = Engine.from_tables(spark, sf, "trade_core")
    best = engine.autotune(400_000, 4096, 50, 12, 50_000)
    assert 1 <= best["c"] <= best["p"] and best["l"] >= 1
    engine = engine.partition(8, "balanced")
    sizes = [r["count"] for r in engine.parts.groupBy("part_id").count().collect()]
    assert len(sizes) == 8 and max(sizes) - min(sizes) <= 1
    plan = engine.plan("two_level", 4)
    inside = engine.resident(plan.sets[0])
    assert 0 < inside.edges.count() < engine.graph.edges.count()
    targets = spark.createDataFrame([(0, 16), (0, 32)], "batch_id int, node_id bigint")
    delta, again = engine.sample(targets, [5, 5]), engine.sample(targets, [5, 5], sampler="layer_resample")
    assert Engine.pack(delta).count() == 1
    assert delta.nbrs.count() <= again.count()
    train = engine.graph.nodes.where("node_id % 160 = 0")
    labelled = engine.partition(8, "label_first", train=train)
    assert labelled.plan("label_cache", 5).n_loads == 5
    assert engine.plan("full", 8).n_loads == 8 and engine.plan("greedy", 2).sets and engine.plan("cover", 4).sets
