"""Worked examples, invariants and gradient checks of the methods."""

import hashlib
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltahop import graphs, hashing, md5, queries
from deltahop.operators import layers as tables
from deltahop.operators import packed_layers as pl
from deltahop.operators import packing, sampling
from deltahop.operators import partitioning as part
from deltahop.plans import batching, metrics, policy, tuning
from deltahop.sources import store

A, B, C, D, E = range(5)
TWO_HOP = [(A, C), (A, D), (B, C), (C, E), (C, A), (D, B)]


def two_hop(spark):
    adj = spark.createDataFrame(TWO_HOP, "node_id bigint, nbr_id bigint")
    return sampling.delta_sample(spark.createDataFrame([(0, A), (0, B), (0, A)], "batch_id int, node_id bigint"), adj, [None, None])


def test_worked_two_hop_example(spark):
    batch = packing.Packed.of(packing.pack(two_hop(spark)).first())
    assert batch.vertex_ids.tolist() == [E, C, D, A, B] and batch.group_starts.tolist() == [0, 1, 3]
    lists = {int(v): sorted(batch.nbr_ids[s : s + n].tolist()) for v, s, n in zip(batch.vertex_ids[1:], batch.nbr_starts, batch.lengths(), strict=True)}
    assert lists == {C: [A, E], D: [B], A: [C, D], B: [C]}
    assert all(batch.vertex_ids[r] == n for r, n in zip(batch.input_rows, batch.nbr_ids, strict=True))
    h1, _ = pl.AddLayer().forward(batch, (batch.vertex_ids + 1.0)[:, None])
    assert h1.ravel().tolist() == [9, 6, 8, 5]
    small = batch.trimmed()
    assert small.vertex_ids.tolist() == [C, D, A, B] and small.group_starts.tolist() == [0, 2] and small.nbr_starts.tolist() == [0, 2]
    h2, _ = pl.AddLayer().forward(small, h1)
    assert h2.ravel().tolist() == [23, 14]


def test_delta_invariants(spark, sf):
    adj = part.adjacency(graphs.trade_core_edges(spark, sf), "any").persist()
    targets = spark.createDataFrame([(b, i * 16) for b in (0, 1) for i in range(10)] + [(1, 10**9 * 16)], "batch_id int, node_id bigint")
    s = sampling.delta_sample(targets, adj, [4, 3])
    nodes = s.nodes.collect()
    assert len({(r.batch_id, r.node_id) for r in nodes}) == len(nodes)
    edges = {(r.node_id, r.nbr_id) for r in adj.collect()}
    degree = {}
    for a, _ in edges:
        degree[a] = degree.get(a, 0) + 1
    nbrs = s.nbrs.collect()
    assert all((r.node_id, r.nbr_id) in edges for r in nbrs)
    count = {}
    for r in nbrs:
        count[r.batch_id, r.node_id] = count.get((r.batch_id, r.node_id), 0) + 1
    for r in nodes:
        if r.delta_idx:
            assert count.get((r.batch_id, r.node_id), 0) == min(degree.get(r.node_id, 0), r.fanout)
    exact = {(r.batch_id, r.node_id) for r in sampling.khop_exact(targets, adj, 2).collect()}
    assert {(r.batch_id, r.node_id) for r in nodes} <= exact
    whole = sampling.delta_sample(targets, adj, [None, None]).nodes.collect()
    assert {(r.batch_id, r.node_id) for r in whole} == exact
    shared = sampling.layer_resample(targets, adj, [4, 4], layer_salt=False)
    delta = sampling.delta_sample(targets, adj, [4, 4])
    assert {tuple(r) for r in shared.select("batch_id", "node_id", "nbr_id").collect()} == {tuple(r) for r in delta.nbrs.select("batch_id", "node_id", "nbr_id").collect()}
    assert shared.count() >= delta.nbrs.count()


def test_sample_is_uniform_over_salts(spark):
    adj = spark.createDataFrame([(0, i) for i in range(1, 21)], "node_id bigint, nbr_id bigint")
    targets = spark.range(400).select(F.col("id").cast("int").alias("batch_id"), F.lit(0).cast("bigint").alias("node_id"))
    seen = sampling.one_hop(targets, adj, 5).groupBy("nbr_id").count().collect()
    assert len(seen) == 20 and sum((r["count"] - 100) ** 2 / 100 for r in seen) < 45


def test_hub_keeps_fanout_and_plan_limits_rows(spark):
    hub = spark.range(100_000).select(F.lit(1).cast("bigint").alias("node_id"), (F.col("id") + 5).alias("nbr_id"))
    found = sampling.one_hop(spark.createDataFrame([(0, 1)], "batch_id int, node_id bigint"), hub, 7, sampling.Salt(fast=True))
    assert found.count() == 7
    assert "WindowGroupLimit" in found._jdf.queryExecution().toString()


# (p, sets two-level, sets greedy, loads two-level, loads greedy), c = p / 4, eight groups, lowest ties
@pytest.mark.parametrize("p, n_two, n_greedy, l_two, l_greedy", [(8, 28, 28, 29, 29), (16, 28, 43, 58, 46), (32, 28, 79, 116, 86)])
def test_plan_goldens(p, n_two, n_greedy, l_two, l_greedy):
    two, greedy = policy.plan_two_level(p, 8, p // 4, seed=1), policy.plan_greedy(p, p // 4)
    assert (len(two.sets), len(greedy.sets)) == (n_two, n_greedy)
    assert (two.n_loads, greedy.n_loads) == (l_two, l_greedy)


@pytest.mark.parametrize("tie", ["lowest", "random", "least_visited"])
def test_plan_invariants(tie):
    for plan in (policy.plan_greedy(12, 4, tie), policy.plan_two_level(12, 6, 4, 1, 5, tie), policy.plan_two_level(13, 7, 4, 1, 5, tie)):
        assert set(plan.buckets) == {(i, j) for i in range(plan.p) for j in range(plan.p)}
        assert all(i in plan.sets[x] and j in plan.sets[x] for (i, j), x in plan.buckets.items())
        assert all(len(s) <= 4 for s in plan.sets)
        logical = plan.logical_sets or plan.sets
        assert all(len(set(b) - set(a)) == 1 for a, b in zip(logical, logical[1:], strict=False))
    cover = policy.plan_random_cover(16, 8, 4, 0, 2)
    assert {q for s in cover.sets for q in s} == set(range(16)) and cover.n_loads == 16
    cache = policy.plan_label_cache(2, 5, 16, 3, 1)
    assert set(cache.sets[0]) >= {0, 1} and len(cache.sets[0]) == 5
    with pytest.raises(ValueError):
        policy.plan_label_cache(5, 5, 16)
    with pytest.raises(ValueError):
        policy.plan_two_level(8, 4, 3)


def test_deferred_sets_are_balanced():
    two, greedy = policy.plan_two_level(32, 8, 8, seed=2), policy.plan_greedy(32, 8)
    size = lambda plan: np.bincount(list(plan.buckets.values()))
    assert size(two).max() / size(two).min() < 1.6 < size(greedy).max() / size(greedy).min()


def test_bias_bounds(spark):
    one = metrics.edge_permutation_bias(policy.plan_full(4).buckets_df(spark), 4).first().bias
    some = metrics.edge_permutation_bias(policy.plan_greedy(8, 2).buckets_df(spark), 8).first().bias
    assert one == 0 and 0 < some <= 1


def test_cost_model_example():
    o = tuning.Overheads.of(3630, 111122, 50, 12)
    assert tuning.autotune(o, 400_000, 4096, 50_000) == {"p": 18, "c": 4, "l": 9}
    p, c = 18, 4
    use = lambda c: c * o.partition(p) + 2 * c * c * o.bucket(p) + 50_000
    assert use(c) < 400_000 <= use(c + 1)
    assert min(o.partition(p), o.bucket(p)) >= 4096 > min(o.partition(p + 1), o.bucket(p + 1))


def test_segment_sum_with_empty_segments():
    got = packing.segment_sum(np.arange(8.0).reshape(4, 2), np.array([0, 0, 2, 4, 4]))
    assert got.tolist() == [[0, 0], [2, 4], [10, 12], [0, 0], [0, 0]]


def random_batch(rng):
    ids = np.arange(9)
    lengths = [2, 0, 3, 1, 2, 3]
    nbrs = [rng.choice(9 if k < 3 else np.arange(3, 9), n) for k, n in enumerate(lengths)]
    flat = np.concatenate(nbrs)
    return packing.Packed(np.array([0, 3, 6]), ids, np.concatenate([[0], np.cumsum(lengths)[:-1]]), flat, flat.copy())


@pytest.mark.parametrize("kind", ["add", "sage", "gat"])
def test_gradients_match_finite_differences(kind):
    rng = np.random.default_rng(3)
    batch = random_batch(rng)
    make = {"add": lambda: pl.AddLayer(), "sage": lambda: pl.SageLayer.random(4, 4, rng, "tanh"), "gat": lambda: pl.GatLayer.random(4, 4, rng, 2)}[kind]
    layers, h0 = [make(), make()], rng.normal(size=(9, 4))
    r, neg = rng.normal(size=(2, 4)), np.array([0, 2])
    src, rel, dst = np.array([0, 1]), np.array([0, 1]), np.array([1, 2])

    def loss(h0, layers):
        h, saved = pl.run_forward(batch, h0, layers)
        return pl.distmult_head(h, src, rel, dst, neg, r), saved

    (value, gh, gr, *_), saved = loss(h0, layers)
    g0, grads = pl.run_backward(layers, saved, gh)
    eps = 1e-6

    def check(array, grad):
        for at in list(np.ndindex(array.shape))[::3]:
            old = array[at]
            array[at] = old + eps
            up = loss(h0, layers)[0][0]
            array[at] = old - eps
            down = loss(h0, layers)[0][0]
            array[at] = old
            assert abs((up - down) / (2 * eps) - grad[at]) < 1e-5

    check(h0, g0)
    check(r, gr)
    for layer, g in zip(layers, grads, strict=True):
        for name, w in layer.weights.items():
            check(w, g[name])


def test_softmax_gradient():
    rng = np.random.default_rng(1)
    h, w, b, y = rng.normal(size=(5, 3)), rng.normal(size=(3, 4)), rng.normal(size=4), np.array([0, 3, 1, 2, 2])
    _, _, gh, gw, _ = pl.softmax_head(h, w, b, y)
    for array, grad in ((h, gh), (w, gw)):
        for at in np.ndindex(array.shape):
            old = array[at]
            array[at] = old + 1e-6
            up = pl.softmax_head(h, w, b, y)[0]
            array[at] = old - 1e-6
            down = pl.softmax_head(h, w, b, y)[0]
            array[at] = old
            assert abs((up - down) / 2e-6 - grad[at]) < 1e-6


def test_store_prunes_and_updates_resident_partitions(spark, sf, tmp_path):
    g = graphs.Graph.from_tables(spark, sf, "trade")
    held = store.GraphStore.write(g, 4, 3, str(tmp_path / "g"))
    plan = held.bucket(1, 2)._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and "src_part" in plan.split("PartitionFilters")[1][:120]
    assert held.edges().count() == g.edges.count()
    before = held.nodes_of([0, 2, 3]).count()
    changed = spark.createDataFrame(held.nodes_of([1]).limit(3).collect(), held.nodes().schema)
    held.update_nodes(changed)
    assert held.nodes_of([1]).count() == 3 and held.nodes_of([0, 2, 3]).count() == before


def test_bucketed_table_needs_no_exchange(spark, sf):
    table = store.write_bucketed(graphs.part_supplier_edges(spark, sf).select("src_id", "rel_id", "dst_id"), "dh_bucketed_test", 4)
    assert "Exchange" not in table.groupBy("src_id").count()._jdf.queryExecution().executedPlan().toString()
    spark.sql("DROP TABLE dh_bucketed_test")


def test_mix_agrees_with_plain_numbers(spark):
    rows = spark.range(50).select("id", hashing.mix(F.col("id") * 1_000_003, 9).alias("m")).collect()
    assert all(r.m == hashing.mix_int(r.id * 1_000_003, 9) for r in rows)


def scans(df):
    return df._jdf.queryExecution().optimizedPlan().toString().count("Relation [")


def test_plans_grow_evenly_with_hops(spark, sf):
    edges = graphs.trade_core_edges(spark, sf)
    adj = part.adjacency(edges, "any")
    targets = spark.createDataFrame([(0, i * 16) for i in range(20)], "batch_id int, node_id bigint")
    targets.write.mode("overwrite").saveAsTable("dh_targets_test")
    targets = spark.table("dh_targets_test")
    samples = [sampling.delta_sample(targets, adj, [3] * k) for k in range(1, 6)]
    for frames in ([x.nodes for x in samples], [x.nbrs for x in samples], [sampling.layer_resample(targets, adj, [3] * k) for k in range(1, 6)]):
        n = [scans(f) for f in frames]
        assert len(set(np.diff(n))) == 1 and n[-1] <= 12
    lazy = [scans(sampling.delta_sample(targets, adj, [3] * k, keep=False).nodes) for k in range(1, 4)]
    assert lazy[2] - lazy[1] > 2 * (lazy[1] - lazy[0])  # what keeping hops avoids
    spark.sql("DROP TABLE dh_targets_test")


def test_delta_sample_of_both_directions(spark):
    edges = spark.createDataFrame([(1, 0, 2), (2, 0, 3), (4, 0, 2), (3, 0, 1)], "src_id bigint, rel_id int, dst_id bigint")
    pair = part.adjacency(edges, "in"), part.adjacency(edges, "out")
    found = sampling.delta_sample(spark.createDataFrame([(0, 2)], "batch_id int, node_id bigint"), pair, [None, None])
    assert {(r.delta_idx, r.node_id, r.nbr_id) for r in found.nbrs.collect()} == {(2, 2, 1), (2, 2, 4), (2, 2, 3), (1, 1, 3), (1, 1, 2), (1, 4, 2), (1, 3, 2), (1, 3, 1)}
    assert packing.Packed.of(packing.pack(found).first()).group_starts.tolist() == [0, 0, 3]


def test_ranks_equal_a_whole_sort(spark):
    rng = np.random.default_rng(2)
    ids = [int(x) for x in rng.choice(10**6, 500, replace=False)]
    df = spark.createDataFrame([(i % 3, i) for i in ids], "g int, node_id bigint")
    got = {r.node_id: r.place for r in part.hash_ranked(df, 4, "place").collect()}
    assert sorted(ids, key=lambda i: (hashing.mix_int(i, 4), i)) == sorted(ids, key=got.get) and sorted(got.values()) == list(range(500))
    within = part.ranked(df, F.floor(F.col("node_id") / 1000), ["node_id"], "place", ("g",)).collect()
    assert all(sorted(r.place for r in within if r.g == g) == list(range(sum(r.g == g for r in within))) for g in range(3))
    edges = df.select(F.col("node_id").alias("src_id"), F.lit(0).alias("rel_id"), F.col("g").cast("bigint").alias("dst_id"))
    sizes = sorted(r["count"] for r in batching.exact_batches(edges, 120, 1, 0).groupBy("batch_id").count().collect())
    assert sizes == [20, 120, 120, 120, 120]


def test_negatives_are_uniform_and_need_no_cross_join(spark):
    pool = spark.range(40).select((F.col("id") * 7).alias("node_id"))
    batches = spark.range(600).select(F.col("id").cast("int").alias("batch_id"))
    found = tables.sample_negatives(batches, pool, 10, 1, 0)
    rows = found.collect()
    per = {}
    for r in rows:
        per.setdefault(r.batch_id, set()).add(r.candidate_id)
    assert len(per) == 600 and all(len(v) <= 10 for v in per.values()) and sum(map(len, per.values())) == len(rows) > 5900
    count = np.bincount([r.candidate_id // 7 for r in rows], minlength=40)
    assert len(count) == 40 and ((count - len(rows) / 40) ** 2 / (len(rows) / 40)).sum() < 75
    text = found._jdf.queryExecution().optimizedPlan().toString()
    assert "Cross" not in text and "NestedLoop" not in found._jdf.queryExecution().executedPlan().toString()
    assert tables.sample_negatives(batches.limit(2), pool.limit(6), 10, 1, 0).count() == 12


@pytest.mark.parametrize("ties, share", [("mid", 0.5), ("optimistic", 0.0), ("pessimistic", 1.0)])
def test_ranks_among_all_vertices(spark, ties, share):
    rng = np.random.default_rng(7)
    h = rng.integers(-2, 3, (30, 3)).astype(float)
    edges = [(k, int(a), int(r), int(b)) for k, (a, r, b) in enumerate(zip(rng.integers(0, 30, 40), rng.integers(0, 2, 40), rng.integers(0, 30, 40), strict=True))]
    rel = [[1.0, 0.5, 2.0], [1.0, -1.0, 0.0]]
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(h)], "node_id bigint, h array<double>")
    examples = spark.createDataFrame(edges, "example_id bigint, src_id bigint, rel_id int, dst_id bigint")
    got = {r.example_id: r["rank"] for r in tables.rank_against_all(examples, vectors, rel, ties, block=7).collect()}
    for k, a, r, b in edges:
        score = (h[a] * rel[r]) @ h.T
        other = np.delete(score, b)
        assert got[k] == 1 + (other > score[b]).sum() + share * (other == score[b]).sum()


def test_samples_without_stored_hops(spark, monkeypatch):
    """The same sample, hubs or not; hops aren't written, nothing is ranked by a window, and counts need no hop."""
    adj = spark.range(3000).selectExpr("(id * id * 31 + id) % 97 AS node_id", "(id * 7919) % 101 AS nbr_id").distinct()
    targets = spark.range(60).selectExpr("CAST(id % 3 AS INT) AS batch_id", "id AS node_id")
    rows = lambda df, *c: sorted(map(tuple, df.select(*c).collect()), key=repr)
    hop = ("batch_id", "delta_idx", "node_id", "nbr_rank", "nbr_id")
    own, keep = sampling.Lists.of, sampling.stored
    for width, fanouts in ((4096, [4, 3]), (20, [5, None])):
        written = []
        monkeypatch.setattr(sampling.Lists, "of", lambda a, width=width: own(a, width))
        monkeypatch.setattr(sampling, "stored", lambda df, name="step", free=False, written=written: written.append(name) or keep(df, name, free))
        few = sampling.delta_sample(targets, adj, fanouts, hops=False)
        assert "hop" not in written and written.count("frontier") == len(fanouts)
        all_ = sampling.delta_sample(targets, adj, fanouts)
        assert rows(few.nodes, "batch_id", "delta_idx", "node_id", "fanout") == rows(all_.nodes, "batch_id", "delta_idx", "node_id", "fanout")
        assert rows(few.nbrs, *hop) == rows(all_.nbrs, *hop)
        assert rows(sampling.sampled_counts(few), "batch_id", "node_id", "c") == rows(sampling.sampled_counts(all_), "batch_id", "node_id", "c")
        assert ("Window" in few.nbrs._jdf.queryExecution().optimizedPlan().toString()) == (width == 20)
        monkeypatch.undo()


def test_ranks_score_equal_vectors_once(spark):
    """With few different vectors the blocks don't grow with vertices or examples: 3,000 vertices of 4 vectors fit one block of 7."""
    ids = spark.range(3000)
    vectors = ids.select(F.col("id").alias("node_id"), F.array((F.col("id") % 4).cast("double")).alias("h"))
    examples = ids.select(F.col("id").alias("example_id"), F.col("id").alias("src_id"), F.lit(0).alias("rel_id"), (F.col("id") * 7 % 3000).alias("dst_id"))
    found = tables.rank_against_all(examples, vectors, [[1.0]], block=16)
    assert "sequence(0, 0" in found._jdf.queryExecution().analyzed().toString()
    for r in found.collect():
        a, b = r.example_id % 4, r.example_id * 7 % 3000 % 4
        assert r["rank"] == 1 + (750 * (3 - b) + 0.5 * 749 if a else 0.5 * 2999)


def test_price_band_of_equal_prices_is_linear(spark, tmp_path):
    """Rows of one price aren't paired one by one; equal keys are no pairs, nor are rows without a price."""
    rows = spark.range(200000).selectExpr("id AS p_partkey", "CASE WHEN id % 2 = 0 THEN 10.0D ELSE 10.5D END AS p_retailprice")
    more = spark.createDataFrame([(200000, 11.2), (200000, 11.3), (200001, None), (200002, -0.25), (200003, 0.25), (200004, 0.26)], "p_partkey bigint, p_retailprice double")
    rows.unionByName(more).write.parquet(f"{tmp_path}/part.parquet")
    got = {r.part: r.n for r in queries.load()[0]["join_range_price_band"](spark, str(tmp_path)).collect()}
    assert len(got) == 200003 and got[0] == got[1] == 199999
    assert {k: v for k, v in got.items() if k >= 200000} == {200002: 1, 200003: 2, 200004: 1}


def brute_greedy(n, m):
    """One swap at a time, by counting from scratch which pairs each swap would bring together."""
    held, covered, out = set(range(m)), set(), []
    while True:
        covered |= {frozenset(x) for x in combinations(sorted(held), 2)}
        out.append(sorted(held))
        if len(covered) == n * (n - 1) // 2:
            return out
        swaps = []
        for gone in sorted(held):
            for new in sorted(set(range(n)) - held):
                kept = held - {gone}
                swaps.append((-len({frozenset((new, k)) for k in kept} - covered), gone, new))
        gain, gone, new = min(swaps)
        if gain == 0:
            a, b = min(tuple(sorted(p)) for p in ({frozenset(x) for x in combinations(range(n), 2)} - covered))
            keep, new = (a, b) if a in held else (b, a) if b in held else (None, a)
            gone = min(held - {keep})
        held = held - {gone} | {new}


@pytest.mark.parametrize("n, m", [(4, 2), (6, 3), (8, 2), (9, 4), (16, 4)])
def test_greedy_sets_equal_brute_force(n, m):
    assert policy.greedy_sets(n, m) == brute_greedy(n, m)


@pytest.mark.parametrize("p, groups, c", [(16, 8, 4), (12, 6, 4), (20, 5, 8), (32, 8, 8)])
def test_two_level_and_cover_sets_follow_their_groups(p, groups, c):
    for epoch in range(3):
        plan = policy.plan_two_level(p, groups, c, epoch, 3)
        order = sorted(range(p), key=lambda i: (hashing.mix_int(i, 3 * 1009 + epoch), i))
        size = p // groups
        assert plan.groups == [sorted(order[g * size : (g + 1) * size]) for g in range(groups)]
        logical = brute_greedy(groups, c // size)
        assert plan.sets == [sorted(q for g in s for q in plan.groups[g]) for s in logical]
        cover = policy.plan_random_cover(p, groups, c, epoch, 3)
        seen = set(cover.logical_sets[0])
        assert len(seen) == c // size
        for a, b in zip(cover.logical_sets, cover.logical_sets[1:], strict=False):
            (new,) = set(b) - set(a)
            assert new not in seen and len(b) == len(a)
            seen.add(new)
        assert seen == set(range(groups))


def test_tuned_point_is_among_the_cheapest(spark, sf):
    from deltahop.queries.plan import tuning_scan

    rows = tuning_scan(spark, sf).collect()
    (best,) = [r for r in rows if r.tuned]
    assert len(rows) >= 6 and best.place <= max(1, len(rows) // 4)
    assert all(r.min_read <= best.min_read for r in rows if r.p > best.p)
    assert all(0 <= r.bias <= 1 and r.io_bytes > 0 for r in rows)


def test_md5_in_numpy_equals_the_text(spark):
    """All lengths of prefixes and ids, negative ids too, up to one block of the hash."""
    rng = np.random.default_rng(0)
    prefixes = [f"7:0:{'9' * n}:".encode() for n in range(30)]
    ids = np.array([0, -1, *(s * 10**k + d for k in range(19) for s in (1, -1) for d in (-1, 0, 1)), *rng.integers(-(2**62), 2**62, 200)], np.int64)
    which, many = np.repeat(np.arange(len(prefixes)), len(ids)), np.tile(ids, len(prefixes))
    high, low = md5.priorities(prefixes, which, many)
    assert all(hashlib.md5(prefixes[w] + str(i).encode()).hexdigest() == f"{h:016x}{x:016x}" for w, i, h, x in zip(which.tolist(), many.tolist(), high.tolist(), low.tolist(), strict=True))
    order, ranks = md5.smallest(np.array([0, 0, 0, 2]), 3, np.array([5, 5, 1, 9], np.uint64), np.array([2, 1, 7, 0], np.uint64), np.arange(4), 2)
    assert order.tolist() == [2, 1, 3] and ranks.tolist() == [0, 1, 0]


@pytest.mark.parametrize("width", [4096, 20])
def test_sweep_sizes_without_stored_hops(spark, monkeypatch, width):
    """Vertices, edges and paths of both baselines from one draw a hop; no hop is written."""
    adj = spark.range(3000).selectExpr("(id * id * 31 + id) % 97 AS node_id", "(id * 7919) % 101 AS nbr_id").distinct()
    targets = spark.range(60).selectExpr("CAST(id % 3 AS INT) AS batch_id", "id AS node_id")
    fanouts = [4, 3, 2]
    again, paths = sampling.layer_resample(targets, adj, fanouts).collect(), sampling.path_sample(targets, adj, fanouts).collect()
    written, keep = [], sampling.stored
    monkeypatch.setattr(sampling, "stored", lambda df, name="step", free=False: written.append(name) or keep(df, name, free))
    got = {r.k: (r.resample_nodes, r.resample_edges, r.path_edges) for r in sampling.resample_path_counts(targets, sampling.Lists.of(adj, width), fanouts).collect()}
    assert "hop" not in written
    start = {(i % 3, i) for i in range(60)}
    for k in (1, 2, 3):
        met = start | {(r.batch_id, r.nbr_id) for r in again if r.hop < k}
        assert got[k] == (len(met), sum(r.hop < k for r in again), sum(r.n_paths for r in paths if r.hop < k))
