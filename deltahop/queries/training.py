"""Experiment workloads that train, at sizes that fit a query; the same functions run larger settings from bench.py."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from deltahop import graphs, hashing
from deltahop.operators import packed_layers, packing
from deltahop.operators import partitioning as part
from deltahop.operators import sampling as sp
from deltahop.operators.storage import stored
from deltahop.plans import metrics, policy
from deltahop.queries.registry import query
from deltahop.queries.sampling import adjacency, sample_sizes, targets
from deltahop.sources.store import GraphStore
from deltahop.train import Model, Trainer


def hash_split(node, seed: int, share: int):
    return F.pmod(hashing.mix(node, seed), F.lit(100)) < share


def geo_task(spark, sf_dir):
    """(edges, h0, labels): the region of a customer; only nations and regions have features (their own region's place and id)."""
    edges = graphs.geo_edges(spark, sf_dir)
    g = graphs.Graph.from_edges(edges)
    code = F.shiftright("node_id", 4)
    one_hot = F.transform(F.sequence(F.lit(0), F.lit(29)), lambda i: F.when((F.col("node_type") == 3) & (code == i), 1.0).when((F.col("node_type") == 4) & (code + 25 == i), 1.0).otherwise(0.0))
    nation = graphs.table(spark, sf_dir, "nation")
    labels = graphs.table(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select(graphs.typed("c_custkey", "customer").alias("node_id"), F.col("n_regionkey").cast("bigint").alias("label"))
    return edges, g.nodes.select("node_id", one_hot.alias("h")), labels


def document_task(spark, sf_dir, d: int = 24):
    """(edges, h0, labels): the language of a document; a token's vector counts its letters in d places."""
    pairs = graphs.document_tokens(spark, sf_dir)
    doc = graphs.typed("doc_id", "document")
    token = graphs.typed(F.shiftrightunsigned(F.xxhash64("token"), 5), "token")
    edges = pairs.select(doc.alias("src_id"), F.lit(0).alias("rel_id"), token.alias("dst_id"))
    letters = F.transform(F.split("token", ""), lambda c: F.ascii(c) % d)
    vector = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.size(F.filter(letters, lambda x: x == i)).cast("double") / F.length("token"))
    tokens = pairs.select("token").distinct().select(token.alias("node_id"), vector.alias("h"))
    docs = graphs.table(spark, sf_dir, "documents").select(doc.alias("node_id"), "lang")
    h0 = tokens.unionByName(docs.select("node_id", F.array(*[F.lit(0.0)] * d).alias("h")))
    label = F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1
    return edges, h0, docs.select("node_id", label.cast("bigint").alias("label"))


def node_classification(spark, sf_dir, task, fanouts, dims, classes, epochs, seeds=(1,), disk=False, kind="sage", direction="both", history=False):
    """(run, seed, n, accuracy) for each seed; disk: a label-cache plan over 8 partitions, 4 resident. history: instead
    (run, epoch, elapsed_s, metric, value) with the accuracy after every epoch."""
    edges, h0, labels = task(spark, sf_dir)
    edges, h0 = stored(edges, "edges"), stored(h0, "vectors")
    train, test = labels.where(hash_split(F.col("node_id"), 3, 30)), labels.where(~hash_split(F.col("node_id"), 3, 30))
    out = None
    for seed in seeds:
        trainer = Trainer(Model(kind, dims, "softmax", classes, seed=seed), fanouts, batch_size=200, steps=8, rate=0.1, seed=seed, direction=direction, run="disk" if disk else "memory")
        plan = parts = None
        if disk:
            nodes = graphs.Graph.from_edges(edges).nodes
            parts, k = part.assign_label_first(nodes, train, 8, seed)
            parts = stored(parts, "parts")
            plan = policy.plan_label_cache(k, max(4, k + 1), 8, 0, seed)
        params = trainer.fit_nodes(edges, h0, train, epochs, plan, parts, test if history else None)
        row = trainer.history_df(spark) if history else metrics.accuracy(trainer.predict_nodes(params, edges, h0, test)).select(F.lit(trainer.run).alias("run"), F.lit(seed).alias("seed"), "n", "accuracy")
        out = row if out is None else out.unionByName(row)
    return out


def link_prediction(spark, sf_dir, kind="sage", mode="memory", epochs=2, d=16, p=16, c=4, n_logical=8, fanout=20, negatives=50, layers=1, seed=1, core=False, direction="both", every=False, batch_size=2000, from_store=False):
    """(run, model, n, mrr) on held-out edges of the trade graph. every: ranks among all vertices instead of sampled ones.
    from_store: resident sets are read from a partitioned store and written back to it."""
    edges = stored((graphs.trade_core_edges if core else graphs.customer_part_edges)(spark, sf_dir).select("src_id", "rel_id", "dst_id"), "edges")
    held = F.pmod(hashing.mix(F.col("src_id") * 31 + F.col("dst_id"), 3), F.lit(100))
    train, test = edges.where(held < 90), edges.where(held >= 95)
    nodes = graphs.Graph.from_edges(edges).nodes
    h0 = stored(nodes.select("node_id", F.transform(F.sequence(F.lit(1), F.lit(d)), lambda i: hashing.mix(F.col("node_id"), i) / hashing.MIX_PRIME - 0.5).alias("h")), "vectors")
    model = Model(kind if layers else "sage", (d,) * (layers + 1), "distmult", relations=8, seed=seed)
    trainer = Trainer(model, [fanout] * layers, batch_size=batch_size, negatives=negatives, steps=3, rate=0.05, seed=seed, direction=direction, run=mode)
    plans = {"memory": None, "two_level": lambda e: policy.plan_two_level(p, n_logical, c, e, seed), "greedy": lambda e: policy.plan_greedy(p, c)}[mode]
    store = None
    if from_store and plans:
        graph = graphs.Graph(nodes, train.withColumn("edge_ts", F.lit(None).cast("timestamp_ntz")), "trade")
        store = GraphStore.write(graph, p, seed, vectors=h0)
    params, vectors = trainer.fit_links(train, h0, epochs, plans, p if plans else 1, store=store)
    ranks = (trainer.rank_links_all if every else trainer.rank_links)(params, train, vectors, test)
    return ranks.agg(F.count("*").alias("n"), F.avg(1 / F.col("rank")).alias("mrr")).select(F.lit(mode).alias("run"), F.lit(kind if layers else "distmult").alias("model"), "n", "mrr")


def union(frames):
    out = None
    for f in frames:
        out = f if out is None else out.unionByName(f)
    return out


MODELS = (("distmult", 0, "any"), ("sage", 1, "both"), ("gat", 1, "in"))  # attention takes incoming neighbours, half as many


def disk_policies(spark, sf_dir, modes=("memory", "two_level", "greedy"), models=MODELS, epochs=1, every=True, p=16, c=4, n_logical=8, seed=1, fanout=20, negatives=50, batch_size=2000):
    """(run, model, n, mrr): every model under every policy; ranks among all vertices."""
    return union([
        link_prediction(spark, sf_dir, name if layers else "sage", mode, epochs, p=p, c=c, n_logical=n_logical, layers=layers, direction=direction, every=every, seed=seed, fanout=fanout // 2 if name == "gat" else fanout, negatives=negatives, batch_size=batch_size, from_store=True)
        for name, layers, direction in models for mode in modes
    ])


def depth_times(spark, sf_dir, name="core", fanout=10, most=3):
    """(graph, k, nodes, edges, sampling_s, compute_s): size and seconds of the delta sample of all targets, packed, and of a forward pass
    of additive layers over it."""
    start, adj = targets(spark, sf_dir, name), stored(adjacency(spark, sf_dir, name), "adjacency")
    rows = []
    for k in range(1, most + 1):
        began = time.time()
        sample = sp.delta_sample(start, adj, [fanout] * k, sp.Salt(fast=True))
        batches = stored(packing.pack(sample), "batches")
        sampled = time.time()

        def run(frames, k=k):
            for pdf in frames:
                for _, r in pdf.iterrows():
                    batch = packing.Packed.of(r)
                    h, _ = packed_layers.run_forward(batch, np.ones((len(batch.vertex_ids), 8)), [packed_layers.AddLayer() for _ in range(k)])
                    yield pd.DataFrame({"n": [len(h)]})

        batches.mapInPandas(run, "n bigint").agg(F.sum("n")).first()
        done = time.time()
        size = batches.agg(F.sum(F.size("vertex_ids")), F.sum(F.size("nbr_ids"))).first()
        rows.append((name, k, size[0], size[1], sampled - began, done - sampled))
    return spark.createDataFrame(rows, "graph string, k int, nodes bigint, edges bigint, sampling_s double, compute_s double")


query("workload_node_memory")(lambda s, d: node_classification(s, d, geo_task, [30, 20, 10], (30, 16, 16, 16), 5, 2, seeds=(1, 2, 3)))
query("workload_node_documents")(lambda s, d: node_classification(s, d, document_task, [20], (24, 16), 4, 3, direction="any"))
query("workload_node_disk")(lambda s, d: node_classification(s, d, document_task, [20], (24, 16), 4, 3, disk=True, direction="any"))
query("workload_time_to_accuracy")(lambda s, d: metrics.time_to_metric(node_classification(s, d, document_task, [20], (24, 16), 4, 3, direction="any", history=True), "accuracy", 0.6))
query("workload_link_sage")(lambda s, d: link_prediction(s, d, "sage", epochs=1))
query("workload_link_gat")(lambda s, d: link_prediction(s, d, "gat", epochs=1, fanout=10, direction="in"))
query("workload_link_decoder_only")(lambda s, d: link_prediction(s, d, layers=0, epochs=1))
query("workload_link_all_negatives")(lambda s, d: link_prediction(s, d, layers=0, epochs=1, every=True))
query("workload_disk_policies")(lambda s, d: disk_policies(s, d, models=MODELS[:1]))
query("workload_depth_sweep")(lambda s, d: sample_sizes(s, d, "core", 10, 3))
query("workload_depth_times")(depth_times)
