"""Training learns, streams equal their batch twins, late rows are dropped, repeats are written once."""

import datetime as dt

import numpy as np
from pyspark.sql import functions as F

from deltahop import hashing
from deltahop import streaming as st
from deltahop.graphs import Graph, table
from deltahop.operators import partitioning as part
from deltahop.plans import metrics, policy
from deltahop.queries.streams import static
from deltahop.queries.training import document_task, geo_task
from deltahop.sources.store import GraphStore
from deltahop.train import Model, Prefetcher, Trainer, load_params, save_params


def test_node_classification_learns_and_history_answers(spark, sf):
    edges, h0, labels = geo_task(spark, sf)
    trainer = Trainer(Model("sage", (30, 16, 16), "softmax", 5), [5, 5], batch_size=80, steps=8)
    params = trainer.fit_nodes(edges, h0, labels, 3)
    got = metrics.accuracy(trainer.predict_nodes(params, edges, h0, labels)).first()
    assert got.accuracy > 0.9
    losses = [v for *_, metric, v in trainer.history if metric == "loss"]
    assert losses[-1] < losses[0]
    history = trainer.history_df(spark).withColumn("value", -F.col("value"))
    assert metrics.time_to_metric(history, "loss", -losses[0] - 1e-9).count() == 1


def test_label_cache_trains_on_the_resident_set(spark, sf):
    edges, h0, labels = document_task(spark, sf)
    parts, k = part.assign_label_first(Graph.from_edges(edges).nodes, labels, 8, 1)
    plan = policy.plan_label_cache(k, 4, 8, 0, 1)
    trainer = Trainer(Model("sage", (24, 8), "softmax", 4), [15], batch_size=100, steps=6)
    params = trainer.fit_nodes(edges, h0, labels, 2, plan, parts)
    assert metrics.accuracy(trainer.predict_nodes(params, edges, h0, labels)).first().accuracy > 0.6


def test_link_training_improves_ranks_in_memory_and_by_sets(spark):
    rng = np.random.default_rng(0)
    pairs = {(int(a) * 16, (int(a) % 5 + 5 * int(b)) * 16 + 1) for a, b in zip(rng.integers(0, 40, 400), rng.integers(0, 6, 400), strict=True)}
    edges = spark.createDataFrame([(a, 0, b) for a, b in sorted(pairs)], "src_id bigint, rel_id int, dst_id bigint")
    nodes = edges.select(F.explode(F.array("src_id", "dst_id")).alias("node_id")).distinct()
    h0 = nodes.select("node_id", F.transform(F.sequence(F.lit(1), F.lit(8)), lambda i: F.pmod(F.col("node_id") * 37 + i * 101, F.lit(97)) / 97 - 0.5).alias("h"))
    mean_rank = lambda t, params, h: t.rank_links(params, edges, h, edges).agg(F.avg("rank")).first()[0]
    for plans, p, epochs in ((None, 1, 3), (lambda e: policy.plan_two_level(4, 4, 2, e, 1), 4, 1)):
        trainer = Trainer(Model("sage", (8, 8), "distmult"), [5], batch_size=100, negatives=10, steps=4, rate=0.05)
        params, vectors = trainer.fit_links(edges, h0, epochs, plans, p)
        assert vectors.count() == nodes.count()
        assert mean_rank(trainer, params, vectors) < mean_rank(trainer, trainer.model.start(), h0)
    assert trainer.rank_links(params, edges, vectors, edges).count() == edges.count()


def test_parameters_round_trip_and_prefetch(spark, tmp_path):
    params = Model("gat", (4, 4), "distmult", relations=3).start()
    save_params(spark, params, str(tmp_path / "p"))
    back = load_params(spark, str(tmp_path / "p"))
    assert all(np.allclose(back[k], v) for k, v in params.items())
    assert list(Prefetcher(lambda s: s * 2)([1, 2, 3])) == [2, 4, 6]


def test_training_from_the_store_reads_and_writes_resident_partitions(spark, tmp_path):
    rng = np.random.default_rng(0)
    pairs = {(int(a) * 16, (int(a) % 5 + 5 * int(b)) * 16 + 1) for a, b in zip(rng.integers(0, 40, 400), rng.integers(0, 6, 400), strict=True)}
    edges = spark.createDataFrame([(a, 0, b, None) for a, b in sorted(pairs)], "src_id bigint, rel_id int, dst_id bigint, edge_ts timestamp_ntz")
    graph = Graph.from_edges(edges)
    h0 = graph.nodes.select("node_id", F.transform(F.sequence(F.lit(1), F.lit(8)), lambda i: F.pmod(F.col("node_id") * 37 + i * 101, F.lit(97)) / 97 - 0.5).alias("h"))
    store = GraphStore.write(graph, 4, 7, str(tmp_path / "store"), h0)
    sizes = {q: store.node_bytes(q) for q in range(4)}
    plan = policy.plan_two_level(4, 4, 2, 0, 1, assign="eager")  # every set trains some buckets
    trainer = Trainer(Model("sage", (8, 8), "distmult"), [5], batch_size=100, negatives=10, steps=4, rate=0.05)
    params, vectors = trainer.fit_links(None, None, 1, lambda e: plan, store=store)
    assert [(q, a) for _, q, a, _ in store.log] == [(q, a) for _, q, a in plan.loads()]
    first = {q: n for x, q, a, n in store.log if a == "load" and x == 0}
    assert first == {q: sizes[q] for q in plan.sets[0]}
    kinds = spark.createDataFrame([(q, n) for q, n in sizes.items()], "part_id int, bytes bigint")
    none = spark.createDataFrame([], "src_part int, dst_part int, bytes bigint")
    want = metrics.io_bytes(plan.loads_df(spark), plan.sets_df(spark), kinds, none).first().node_bytes
    loaded = sum(sizes[q] for _, q, a, _ in store.log if a == "load")
    assert loaded == want
    assert {r.node_id for r in vectors.collect()} == {r.node_id for r in graph.nodes.collect()}
    assert vectors.where(F.aggregate("s", F.lit(0.0), lambda a, x: a + x) > 0).count() > 30  # states are kept beside the vectors
    mean_rank = lambda p, h: trainer.rank_links(p, edges, h, edges).agg(F.avg("rank")).first()[0]
    assert mean_rank(params, vectors) < mean_rank(trainer.model.start(), h0)
    files = [str(f) for q in store.version for f in store.nodes_of([q]).inputFiles()]
    assert len(files) >= len(store.version) > 1
    for q in store.version:
        only = store.nodes_of([q]).inputFiles()
        assert only and all(f"part_id={q}/" in f for f in only)
    every = trainer.rank_links_all(params, edges, vectors, edges.limit(30))
    assert every.count() == 30 and every.agg(F.min("rank")).first()[0] >= 1


def test_degree_state_over_several_micro_batches(spark, sf, tmp_path):
    rows = table(spark, sf, "events").orderBy("event_id").limit(300).collect()
    source = str(tmp_path / "in")
    for k in range(3):
        part_ = spark.createDataFrame(rows[100 * k : 100 * k + 100], st.SCHEMA)
        if k == 1:
            part_ = part_.withColumn("props", F.when(F.col("event_id") % 5 == 0, F.lit("{}")).otherwise(F.col("props")))
        part_.coalesce(1).write.mode("append").parquet(source)
    stream = st.degree_and_sample(st.edge_stream(spark, source, "*.parquet", files=1))
    got = {r.user_id: (r.degree, r.sample) for r in st.drain(stream, "degree", "update", ("user_id",)).collect()}
    events = spark.read.schema(st.SCHEMA).parquet(source)
    want = {}
    for r in events.select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("item")).collect():
        n, items = want.setdefault(r.user_id, [0, set()])
        want[r.user_id][0] = n + 1
        if r["item"] is not None:
            items.add(r["item"])
    order = lambda u, i: (hashing.mix_int(u * 1000 + i, 5), i)
    assert got == {u: (n, ",".join(str(i) for i in sorted(items, key=lambda i: order(u, i))[:5])) for u, (n, items) in want.items()}


def test_streamed_windows_equal_batch_windows(spark, sf):
    events = static(spark, sf)
    for name in ("tumbling", "sliding", "sessions"):
        fn = getattr(st, name)
        streamed = {tuple(r) for r in st.drain(fn(st.edge_stream(spark, sf)), name).collect()}
        batch = {tuple(r) for r in fn(events).collect()}
        assert streamed <= batch
        # windows still open when the source ends stay in the state
        last = max(r[1] for r in batch)
        assert all(r[1] > last - dt.timedelta(days=3) for r in batch - streamed)


def test_appends_to_buckets_happen_once(spark, sf, tmp_path):
    rows = table(spark, sf, "events")
    first = rows.agg(F.min("ts")).first()[0]
    folder = tmp_path / "in"
    rows.where(F.col("ts") >= F.lit(first + dt.timedelta(days=10))).coalesce(1).write.parquet(str(folder / "a"))
    source = str(folder / "a")
    out, marks = str(tmp_path / "out"), str(tmp_path / "marks")
    stream = lambda: st.edge_stream(spark, source, "*.parquet")
    st.append_to_buckets(stream(), out, marks)
    n = spark.read.parquet(out).count()
    rows.where(F.col("ts") < F.lit(first + dt.timedelta(days=5))).coalesce(1).write.mode("append").parquet(source)
    st.append_to_buckets(stream(), out, marks)
    st.append_to_buckets(stream(), out, marks)
    late = rows.where(F.col("ts") < F.lit(first + dt.timedelta(days=5))).count()
    assert late > 0 and spark.read.parquet(out).count() == n + late


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    day = lambda k: dt.datetime(2024, 1, k, 12)
    source, out, marks = str(tmp_path / "in"), str(tmp_path / "out"), str(tmp_path / "marks")
    rows = lambda days: spark.createDataFrame([(i, day(k), 1, "view", 1.0, '{"k": 1}') for i, k in enumerate(days)], st.SCHEMA)

    def run():
        windows = st.tumbling(st.edge_stream(spark, source, "*.parquet"))
        windows.writeStream.format("parquet").option("path", out).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()

    rows([10, 11, 20]).coalesce(1).write.parquet(source)
    run()
    rows([2, 19, 25]).coalesce(1).write.mode("append").parquet(source)
    run()
    starts = {r.start.day for r in spark.read.parquet(out).collect()}
    assert 2 not in starts and {10, 11} <= starts
