"""Samples drawn from neighbour lists in files equal those of the relational operators."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltahop import md5
from deltahop.operators import mapped
from deltahop.operators import partitioning as part
from deltahop.operators import sampling as sp

FANOUTS = [4, 3, None]


@pytest.fixture(scope="module")
def graph(spark):
    """Edges with repeats, loops and negative ids of all lengths, a hub, a target without edges and targets named twice."""
    rng = random.Random(5)
    ids = [rng.choice([-1, 1, 1]) * rng.randrange(10 ** rng.randrange(1, 12)) for _ in range(120)]
    pairs = [(rng.choice(ids), rng.choice(ids)) for _ in range(500)]
    pairs += pairs[:50] + [(ids[0], x) for x in ids] + [(ids[3], ids[3])]
    targets = [(b, x) for b in range(7) for x in rng.sample(ids, 6)] + [(0, ids[1])] * 2 + [(2, 10**15 + 7)]
    return spark.createDataFrame(pairs, "src_id bigint, dst_id bigint").cache(), spark.createDataFrame(targets, "batch_id int, node_id bigint").cache()


@pytest.fixture(scope="module")
def lists(graph):
    found = sp.lists_of(graph[0], "any", graph[1])
    assert isinstance(found, mapped.Mapped)
    return found


def rows(df, *columns):
    return sorted((tuple(r) for r in df.select(*columns).collect()), key=repr)


def test_hashes_equal_hashlib():
    ids = np.array([0, 7, -3, 10**9, 2**62, -(2**63), 123456789012], np.int64)
    words, lengths = md5.texts(ids)
    prefixes = [b"x" * k for k in (1, 4, 7, 19, 30)]
    which, at = np.repeat(np.arange(5), len(ids)), np.tile(np.arange(len(ids)), 5)
    high, low = (md5.listed(prefixes, which, words, lengths, at, lower) for lower in (False, True))
    for w, i, a, b in zip(which, at, high, low, strict=True):
        assert hashlib.md5(prefixes[w] + str(ids[i]).encode()).hexdigest() == f"{a:016x}{b:016x}"


@pytest.mark.parametrize("most", [1, 5, 200, None])
def test_first_of_segments(most):
    counts, ids = np.array([3, 0, 300, 1, 40]), np.arange(344) * 37
    prefixes = [f"7:{i}:".encode() for i in range(5)]
    segments, places, ranks = md5.first(prefixes, counts, *md5.texts(ids), ids, np.arange(344), most)
    want = [(s, i, r) for s, (a, n) in enumerate(zip(np.cumsum(counts) - counts, counts, strict=True)) for r, i in enumerate(sorted(range(a, a + n), key=lambda i: hashlib.md5(prefixes[s] + str(ids[i]).encode()).hexdigest())[:most])]
    assert list(zip(segments.tolist(), places.tolist(), ranks.tolist(), strict=True)) == want


def test_delta_sample_equals_tables(graph, lists, monkeypatch):
    monkeypatch.setattr(mapped, "stored", None)  # no step writes
    got = sp.delta_sample(graph[1], lists, FANOUTS, hops=False)
    want = sp.delta_sample(graph[1], part.adjacency(graph[0], "any"), FANOUTS)
    for part_, columns in (("nodes", ("batch_id", "delta_idx", "node_id", "fanout")), ("nbrs", ("batch_id", "delta_idx", "node_id", "nbr_rank", "nbr_id"))):
        assert rows(getattr(got, part_), *columns) == rows(getattr(want, part_), *columns)
    assert got.nodes.schema == want.nodes.schema or [f.dataType for f in got.nodes.schema] == [f.dataType for f in want.nodes.schema]
    for f in (sp.sampled_counts, sp.sample_stats):
        assert rows(f(got), *f(want).columns) == rows(f(want), *f(want).columns)


@pytest.mark.parametrize("layer_salt", [True, False])
def test_resample_equals_tables(graph, lists, layer_salt):
    columns = ("batch_id", "hop", "node_id", "nbr_rank", "nbr_id")
    want = sp.layer_resample(graph[1], part.adjacency(graph[0], "any"), [3, 5, 2], layer_salt=layer_salt)
    assert rows(sp.layer_resample(graph[1], lists, [3, 5, 2], layer_salt=layer_salt, hops=False), *columns) == rows(want, *columns)


def test_path_counts_equal_tables(graph, lists):
    want = sp.resample_path_counts(graph[1], sp.Lists.of(part.adjacency(graph[0], "any")), [3, 2, 4])
    assert rows(sp.resample_path_counts(graph[1], lists, [3, 2, 4]), "k", "resample_nodes", "resample_edges", "path_edges") == rows(want, "k", "resample_nodes", "resample_edges", "path_edges")


def test_candidates_come_in_pieces(graph, lists, monkeypatch):
    """Vertices of more neighbours than a piece holds, and batches of several pieces."""
    sampler = mapped.Sampler(lists.path)
    nodes = np.arange(len(sampler.ids))
    want = [tuple(np.concatenate(x).tolist() for x in zip(*sampler.draw("7:0:1:", nodes, 3, ranked=True), strict=True))]
    monkeypatch.setattr(mapped, "_CHUNK", 20)
    assert [tuple(np.concatenate(x).tolist() for x in zip(*sampler.draw("7:0:1:", nodes, 3, ranked=True), strict=True))] == want


def test_other_graphs_go_through_tables(spark, graph, monkeypatch):
    edges, targets = graph
    assert isinstance(sp.lists_of(edges.unionByName(spark.createDataFrame([(1, None)], edges.schema)), "any", targets), sp.Lists)
    assert isinstance(sp.lists_of(spark.createDataFrame([(1, 2)], edges.schema), "out", targets), sp.Lists)  # 2 has no list and is no target
    assert isinstance(sp.lists_of(edges, "any", targets.withColumn("batch_id", F.lit(None).cast("int"))), sp.Lists)
    monkeypatch.setattr(mapped, "MOST_PAIRS", 10)
    assert isinstance(sp.lists_of(edges, "any", targets), sp.Lists)
