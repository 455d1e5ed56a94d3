"""Layers, decoders, negatives and losses on tables. Vectors are arrays of doubles of a small fixed length d.

A sum of vectors is d plain sums, which stay inside generated code and combine before the shuffle. The packed form of the
same layers, for long vectors, is in `packed_layers`.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltahop import hashing
from deltahop.operators.partitioning import hash_ranked
from deltahop.operators.storage import stored

KEYS = ["batch_id", "node_id"]


def vector_agg(fn: Callable[[Column], Column], column: str, d: int) -> Column:
    return F.array(*(fn(F.col(column)[i]) for i in range(d)))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def distmult(s: Column, r: Column, t: Column) -> Column:
    return dot(F.zip_with(s, r, lambda x, y: x * y), t)


def linear(h: Column, weights: list[list[float]], bias: list[float] | None = None) -> Column:
    """weights[o][i]: one output per row."""
    outs = []
    for o, row in enumerate(weights):
        total = F.lit(float(bias[o])) if bias else F.lit(0.0)
        for i, w in enumerate(row):
            total = total + h[i] * float(w)
        outs.append(total)
    return F.array(*outs)


ACTIVATIONS = {"none": lambda x: x, "relu": lambda x: F.greatest(x, F.lit(0.0)), "tanh": F.tanh}
AGGREGATORS: dict[str, Callable[[Column], Column]] = {"sum": F.sum, "mean": F.avg, "max": F.max, "min": F.min}


def register_aggregator(name: str, fn: Callable[[Column], Column]) -> None:
    """A user's aggregation of one vector component over the neighbours."""
    AGGREGATORS[name] = fn


def gather(nbrs: DataFrame, h: DataFrame) -> DataFrame:
    """Neighbour entries with the neighbour's vector `hn`."""
    return nbrs.join(h.select("batch_id", F.col("node_id").alias("nbr_id"), F.col("h").alias("hn")), ["batch_id", "nbr_id"])


def neighbourhood(nbrs: DataFrame, h: DataFrame, d: int, aggregator: str = "sum") -> DataFrame:
    """(batch_id, node_id, agg) over each vertex's sampled neighbours."""
    return gather(nbrs, h).groupBy(*KEYS).agg(vector_agg(AGGREGATORS[aggregator], "hn", d).alias("agg"))


def zeros(d: int) -> Column:
    return F.array(*[F.lit(0.0)] * d)


def additive_layer(nodes: DataFrame, nbrs: DataFrame, h: DataFrame, d: int) -> DataFrame:
    """(batch_id, node_id, h): own vector plus the neighbours' sum; a vertex without neighbours keeps its own."""
    agg = neighbourhood(nbrs, h, d)
    out = nodes.select(*KEYS).join(h, KEYS).join(agg, KEYS, "left")
    return out.select(*KEYS, add(F.col("h"), F.coalesce("agg", zeros(d))).alias("h"))


def sage_layer(nodes, nbrs, h, d: int, w_self, w_nbr, bias=None, activation: str = "relu", aggregator: str = "mean") -> DataFrame:
    """act(W_self h + W_nbr agg + b)."""
    agg = neighbourhood(nbrs, h, d, aggregator)
    out = nodes.select(*KEYS).join(h, KEYS).join(agg, KEYS, "left").withColumn("agg", F.coalesce("agg", zeros(d)))
    total = add(linear(F.col("h"), w_self, bias), linear(F.col("agg"), w_nbr))
    return out.select(*KEYS, F.transform(total, ACTIVATIONS[activation]).alias("h"))


def attention(nodes, nbrs, h, weights, a_self: list[float], a_nbr: list[float], slope: float = 0.2) -> DataFrame:
    """(batch_id, node_id, nbr_id, alpha, z): softmax over a vertex's neighbours and itself of LeakyReLU(a_self z_i + a_nbr z_j)."""
    z = h.select(*KEYS, linear(F.col("h"), weights).alias("z"))
    lits = lambda v: F.array(*map(F.lit, map(float, v)))
    # rows of one neighbour each, and a row for the vertex itself
    own = nodes.select(*KEYS, F.col("node_id").alias("nbr_id"), F.lit(True).alias("is_self"))
    pairs = nbrs.select(*KEYS, "nbr_id", F.lit(False).alias("is_self")).unionByName(own)
    zi, zj = z.withColumnRenamed("z", "zi"), z.select("batch_id", F.col("node_id").alias("nbr_id"), "z")
    e = dot(F.col("zi"), lits(a_self)) + dot(F.col("z"), lits(a_nbr))
    scored = pairs.join(zi, KEYS).join(zj, ["batch_id", "nbr_id"]).withColumn("e", F.when(e > 0, e).otherwise(e * slope))
    w = Window.partitionBy(*KEYS)
    weight = F.exp(F.col("e") - F.max("e").over(w))
    return scored.withColumn("x", weight).withColumn("alpha", F.col("x") / F.sum("x").over(w)).select(*KEYS, "nbr_id", "is_self", "alpha", "z")


def gat_layer(nodes, nbrs, h, heads: list[dict], slope: float = 0.2, activation: str = "none") -> DataFrame:
    """Heads (weights, a_self, a_nbr) are concatenated."""
    out = None
    for head in heads:
        rows = attention(nodes, nbrs, h, head["weights"], head["a_self"], head["a_nbr"], slope)
        d = len(head["weights"])
        one = rows.groupBy(*KEYS).agg(F.array(*(F.sum(F.col("alpha") * F.col("z")[i]) for i in range(d))).alias("o"))
        out = one if out is None else out.join(one.withColumnRenamed("o", "o2"), KEYS).select(*KEYS, F.concat("o", "o2").alias("o"))
    return out.select(*KEYS, F.transform("o", ACTIVATIONS[activation]).alias("h"))


def forward(sample, h0: DataFrame, layer: Callable[[int, DataFrame, DataFrame, DataFrame], DataFrame]) -> DataFrame:
    """k layers, the sample trimmed after each: layer(i, nodes, nbrs, h) gives the vectors of groups i and above."""
    h = h0
    for i in range(1, sample.k + 1):
        nodes = sample.nodes.where(F.col("delta_idx") >= i)
        nbrs = sample.nbrs.where(F.col("delta_idx") >= i)
        h = layer(i, nodes, nbrs, h)
    return h


# ---- heads, negatives, losses


def softmax_loss(logits: DataFrame, classes: int) -> DataFrame:
    """(.., loss) from (.., logits array, label): cross entropy."""
    top = F.array_max("logits")
    log_sum = F.log(F.aggregate("logits", F.lit(0.0), lambda s, x: s + F.exp(x - top)))
    return logits.withColumn("loss", log_sum + top - F.col("logits")[F.col("label")])


def sample_negatives(examples: DataFrame, pool: DataFrame, n: int, seed: int, epoch: int) -> DataFrame:
    """(batch_id, candidate_id): up to n different negatives per batch, uniform over the pool's vertices.

    A batch draws 2 n hashes, each of which names a place in the pool's hash order, and keeps the first n vertices; so a batch costs
    2 n rows however large the pool is. A pool of n vertices or fewer is taken whole.
    """
    total = pool.select("node_id").distinct()
    batches, size = examples.select("batch_id").distinct(), total.count()
    if size <= n:
        return batches.join(F.broadcast(total.select(F.col("node_id").alias("candidate_id"))))  # n rows at most
    placed = hash_ranked(total, seed * 1009 + epoch, "_place").withColumnRenamed("node_id", "candidate_id")
    draws = batches.withColumn("_k", F.explode(F.sequence(F.lit(0), F.lit(2 * n - 1))))
    hit = F.conv(F.substring(hashing.priority(seed, epoch, F.col("batch_id"), F.col("_k")), 1, 8), 16, 10).cast("bigint")  # below 2**32
    draws = draws.withColumn("_place", F.shiftright(hit * size, 32))
    first = draws.join(placed, "_place").groupBy("batch_id", "candidate_id").agg(F.min("_k").alias("_k"))
    order = Window.partitionBy("batch_id").orderBy("_k")
    return first.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= n).select("batch_id", "candidate_id")


def _last(k: np.ndarray) -> np.ndarray:
    """The largest score that rounds to k billionths or less."""
    t = (k + 0.5) / 1e9
    while (up := np.rint(np.nextafter(t, np.inf) * 1e9) <= k).any():
        t = np.where(up, np.nextafter(t, np.inf), t)
    while (down := np.rint(t * 1e9) > k).any():
        t = np.where(down, np.nextafter(t, -np.inf), t)
    return t


def count_scores(src: np.ndarray, own: np.ndarray, h: np.ndarray, n: np.ndarray, reps: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(above, equal): how many vertices, n for each row of h, score higher than own or the same to nine places; the true end is no rival.

    A rounded score is above or equal if the score itself passes one of two limits of its query, so that no score has to be rounded."""
    k = np.rint(own * 1e9)
    if len(k) and np.abs(k).max() >= 1 << 51:
        raise ValueError("scores of two million and more have no nine places")
    limits = np.stack([_last(k), _last(k - 1)], 1)
    order = np.argsort(reps)
    h, n, reps = np.ascontiguousarray(h[order].T), n[order], reps[order]
    place = np.minimum(np.searchsorted(reps, ends), len(reps) - 1)
    place = np.where(reps[place] == ends, place, -1)
    single, weights = (n == 1).all(), n.astype(float)
    passed = np.zeros((len(src), 2), np.int64)
    for i in range(0, len(src), 256):
        some, mine, row = src[i : i + 256], limits[i : i + 256], place[i : i + 256]
        for j in range(0, len(n), 1024):
            score = some @ h[:, j : j + 1024]
            here = np.flatnonzero((row >= j) & (row < j + 1024))
            for c in (0, 1):
                hit = score > mine[:, c : c + 1]
                passed[i : i + 256, c] += np.count_nonzero(hit, axis=1) if single else (hit @ weights[j : j + 1024]).astype(np.int64)
                passed[i + here, c] -= hit[here, row[here] - j]
    return passed[:, 0], passed[:, 1] - passed[:, 0]


def rank_against_all(examples: DataFrame, vectors: DataFrame, relations: list[list[float]] | None = None, ties: str = "mid", block: int = 1 << 16) -> DataFrame:
    """(example_id, rank) of the true end of (example_id, src_id, rel_id, dst_id) among all vertices of vectors (node_id, h).

    Vertices of one vector score alike, so each different vector is scored once, weighted by its vertices, and so is each different
    (source's vector, relation, destination's vector). Vertices are dealt out in blocks of about `block` rows, queries in blocks of half as many;
    a pair of blocks counts higher and equal scores by matrix products that stay in the cache, and the counts of a query are added up. relations: the decoder's diagonals (None: plain dot
    products).
    """
    share = {"mid": 0.5, "optimistic": 0.0, "pessimistic": 1.0}[ties]
    vectors = stored(vectors.select("node_id", "h"), "vectors", free=True)
    groups = vectors.groupBy("h").agg(F.min("node_id").alias("rep"), F.count("*").alias("n"))
    if groups.count() == vectors.count():
        groups = vectors.select("h", F.col("node_id").alias("rep"), F.lit(1).cast("bigint").alias("n"))
        member = vectors.select("node_id", F.col("node_id").alias("rep"))
    else:
        groups = stored(groups, "groups")
        member = stored(vectors.select("node_id", "h").join(groups, "h").select("node_id", "rep"), "members")
    of = lambda e: member.select(F.col("node_id").alias(f"{e}_id"), F.col("rep").alias(f"{e}_rep"))
    full = stored(examples.select("example_id", "src_id", "rel_id", "dst_id").join(of("src"), "src_id").join(of("dst"), "dst_id").select("example_id", "src_rep", "rel_id", "dst_rep"), "examples", free=True)
    key = ["src_rep", "rel_id", "dst_rep"]
    end = lambda e: groups.select(F.col("rep").alias(f"{e}_rep"), F.col("h").alias(e))
    queries = full.select(key).distinct()
    vb, qb = max(1, -(-groups.count() // block)), max(1, -(-2 * queries.count() // block))
    queries = queries.join(end("src"), "src_rep").join(end("dst"), "dst_rep")
    left = queries.select(*key, "src", "dst", F.pmod(F.xxhash64(*key), F.lit(qb)).cast("int").alias("qb"), F.explode(F.sequence(F.lit(0), F.lit(vb - 1))).alias("vb"))
    right = groups.select("rep", "h", "n", F.pmod(F.xxhash64("rep"), F.lit(vb)).cast("int").alias("vb"), F.explode(F.sequence(F.lit(0), F.lit(qb - 1))).alias("qb"))

    def count(q: pd.DataFrame, v: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(v):
            return pd.DataFrame({c: [] for c in (*key, "above", "equal")}).astype("int64")
        src, dst, h = (np.stack(x).astype(np.float64) for x in (q["src"], q["dst"], v["h"]))
        if relations is not None:
            src = src * np.asarray(relations, float)[q["rel_id"].to_numpy()]
        above, equal = count_scores(src, (src * dst).sum(1), h, v["n"].to_numpy(), v["rep"].to_numpy(), q["dst_rep"].to_numpy())
        return q[key].assign(above=above, equal=equal)

    tasks = min(2 * vb * qb, 1024)
    left, right = left.repartition(tasks, "qb", "vb"), right.repartition(tasks, "qb", "vb")
    counted = left.groupBy("qb", "vb").cogroup(right.groupBy("qb", "vb")).applyInPandas(count, "src_rep bigint, rel_id int, dst_rep bigint, above bigint, equal bigint")
    counts = counted.groupBy(key).agg(F.sum("above").alias("above"), F.sum("equal").alias("equal"))
    return full.join(counts, key).groupBy("example_id").agg((1 + F.sum("above") + share * F.sum("equal")).alias("rank"))


def corrupt(examples: DataFrame, negatives: DataFrame, side: str = "dst") -> DataFrame:
    """(batch_id, example_id, src_id, rel_id, dst_id, candidate_id, is_pos): positives, and each with its batch's shared negatives."""
    end = f"{side}_id"
    pos = examples.select("batch_id", "example_id", "src_id", "rel_id", "dst_id", F.col(end).alias("candidate_id"), F.lit(True).alias("is_pos"))
    neg = examples.join(negatives, "batch_id").where(F.col("candidate_id") != F.col(end))
    neg = neg.select("batch_id", "example_id", *(F.col("candidate_id").alias(end) if c == end else F.col(c) for c in ("src_id", "rel_id", "dst_id")), "candidate_id", F.lit(False).alias("is_pos"))
    return pos.unionByName(neg)


def link_loss(scores: DataFrame, kind: str = "softmax") -> DataFrame:
    """Mean loss over examples of (example_id, is_pos, score): softmax of the positive among its negatives, or logistic."""
    if kind == "logistic":
        # log(1 + exp(-y)) without overflow
        y = F.when(F.col("is_pos"), F.col("score")).otherwise(-F.col("score"))
        each = F.greatest(-y, F.lit(0.0)) + F.log1p(F.exp(-F.abs(y)))
        return scores.agg(F.avg(each).alias("loss"))
    top = scores.groupBy("example_id").agg(F.max("score").alias("top"), F.max(F.when(F.col("is_pos"), F.col("score"))).alias("own"))
    total = scores.join(top, "example_id").groupBy("example_id", "top", "own").agg(F.sum(F.exp(F.col("score") - F.col("top"))).alias("z"))
    return total.agg(F.avg(F.log("z") + F.col("top") - F.col("own")).alias("loss"))
