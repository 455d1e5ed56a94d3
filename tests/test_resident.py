"""Training in tasks that hold the graph equals training through tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltahop import hashing, train
from deltahop.graphs import Graph, customer_part_edges
from deltahop.operators.layers import count_scores
from deltahop.plans import policy
from deltahop.queries.training import document_task, geo_task
from deltahop.sources.store import GraphStore
from deltahop.train import Model, Trainer


def same(a: dict, b: dict) -> None:
    assert a.keys() == b.keys()
    for k in a:
        np.testing.assert_allclose(a[k], b[k], rtol=1e-7, atol=1e-9)


@pytest.mark.parametrize(("task", "dims", "classes", "fanouts", "direction"), [(geo_task, (30, 8, 8), 5, [4, 3], "both"), (document_task, (24, 8), 4, [5], "any")])
def test_node_training_equals_tables(spark, sf, task, dims, classes, fanouts, direction):
    edges, h0, labels = (x.cache() for x in task(spark, sf))
    got = []
    for limit in (1 << 26, 0):
        trainer = Trainer(Model("sage", dims, "softmax", classes), fanouts, batch_size=40, steps=2, direction=direction, resident=limit)
        params = trainer.fit_nodes(edges, h0, labels, 2)
        found = {tuple(r) for r in trainer.predict_nodes(params, edges, h0, labels).collect()}
        got.append((params, found, [v for *_, m, v in trainer.history if m == "loss"]))
    same(got[0][0], got[1][0])
    assert got[0][1] == got[1][1] and len(got[0][1]) == labels.count()
    np.testing.assert_allclose(got[0][2], got[1][2])


@pytest.mark.parametrize(("kind", "layers", "direction", "stored_sets"), [("sage", 0, "both", False), ("sage", 1, "both", False), ("gat", 1, "in", False), ("sage", 0, "any", True)])
def test_link_training_equals_tables(spark, sf, monkeypatch, kind, layers, direction, stored_sets):
    if kind == "gat":
        monkeypatch.setattr(train, "COLLECTED", 0)  # changes are added up by a shuffle
    edges = customer_part_edges(spark, sf).where("src_id < 800").cache()
    nodes = Graph.from_edges(edges).nodes
    h0 = nodes.select("node_id", F.transform(F.sequence(F.lit(1), F.lit(6)), lambda i: hashing.mix(F.col("node_id"), i) / hashing.MIX_PRIME - 0.5).alias("h")).cache()
    got = []
    for limit in (1 << 26, 0):
        trainer = Trainer(Model(kind, (6,) * (layers + 1), "distmult", relations=8), [4] * layers, batch_size=300, negatives=10, steps=2, direction=direction, resident=limit)
        if stored_sets:
            store = GraphStore.write(Graph(nodes, edges, "trade"), 4, 1, vectors=h0)
            params, vectors = trainer.fit_links(None, None, 1, lambda e: policy.plan_two_level(4, 4, 2, e, 1), store=store)
        else:
            params, vectors = trainer.fit_links(edges, h0, 2)
        rows = vectors.orderBy("node_id").collect()
        ranks = sorted(tuple(r) for r in trainer.rank_links(params, edges, vectors, edges).collect())
        got.append((params, [r.node_id for r in rows], np.array([r.h + r.s for r in rows]), ranks))
    same(got[0][0], got[1][0])
    assert got[0][1] == got[1][1] and len(got[0][1]) == nodes.count()
    np.testing.assert_allclose(got[0][2], got[1][2], rtol=1e-7, atol=1e-9)
    assert len(got[0][3]) == len(got[1][3]) == edges.count()
    assert np.mean([x == y for x, y in zip(got[0][3], got[1][3], strict=True)]) > 0.99  # sums of floats differ in the last places


@pytest.mark.parametrize("single", [True, False])
def test_counts_of_scores_equal_rounding(single):
    rng = np.random.default_rng(0)
    src, h = rng.normal(size=(300, 6)), rng.normal(size=(2500, 6))
    h[100:200] = h[:100]  # equal scores
    h[200:300] = h[:100] + 1e-10 * rng.normal(size=(100, 6))  # equal or next to it after rounding
    src[:20] = 0
    n, reps, ends = rng.integers(1, 2 if single else 4, 2500), rng.permutation(2500) * 3, rng.integers(0, 7600, 300)
    ends[::2] = reps[rng.integers(0, 300, 150)]
    at = {int(r): i for i, r in enumerate(reps)}
    own = np.array([src[i] @ h[at.get(int(e), 0)] for i, e in enumerate(ends)])
    score, mine = np.round(src @ h.T, 9), np.round(own, 9)[:, None]
    weight = n[None] - (reps[None] == ends[:, None])
    above, equal = count_scores(src, own, h, n, reps, ends)
    assert (above == np.where(score > mine, weight, 0).sum(1)).all() and (equal == np.where(score == mine, weight, 0).sum(1)).all()
