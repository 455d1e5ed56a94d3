"""Multi-hop neighbourhood samples of many mini batches at once.

A sample of f neighbours is the f smallest priorities, a hash of (seed, epoch, batch, vertex, neighbour): each vertex has one
sample per batch. The delta sample asks for neighbours of every vertex once and lets all layers share them; the layer-resample
baseline puts the hop into the hash and asks again in every layer; the path baseline expands every path.

All functions take frontiers (batch_id, node_id) and adjacency (node_id, nbr_id[, rel_id]). The rank filter lets Spark keep at
most f rows of a vertex per task before its shuffle, so a hub costs f rows a task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltahop import hashing, md5
from deltahop.operators import mapped
from deltahop.operators import partitioning as part
from deltahop.operators.storage import drop, stored


@dataclass(frozen=True)
class Salt:
    seed: int = 7
    epoch: int = 0
    fast: bool = False

    def of(self, *parts: Column) -> Column:
        make = hashing.fast_priority if self.fast else hashing.priority
        return make(self.seed, self.epoch, *parts)


def one_hop(frontier: DataFrame, adj: DataFrame, fanout: int | None, salt: Salt = Salt(), hop: int | None = None) -> DataFrame:
    """(batch_id, node_id, nbr_rank, nbr_id[, rel_id]): up to `fanout` neighbours, all of them if there are fewer (None: all)."""
    rel = [c for c in ("rel_id",) if c in adj.columns]
    parts = [F.col("batch_id"), *([F.lit(hop)] if hop is not None else []), F.col("node_id"), F.col("nbr_id"), *map(F.col, rel)]
    found = frontier.select("batch_id", "node_id").join(adj, "node_id").withColumn("_p", salt.of(*parts))
    rank = F.row_number().over(Window.partitionBy("batch_id", "node_id").orderBy("_p", "nbr_id", *rel))
    out = found.withColumn("nbr_rank", rank)
    if fanout is not None:
        out = out.where(F.col("nbr_rank") <= fanout)
    return out.select("batch_id", "node_id", "nbr_rank", "nbr_id", *rel)


def one_hop_both(frontier: DataFrame, outgoing: DataFrame, incoming: DataFrame, fan_in: int | None, fan_out: int | None, salt: Salt = Salt(), hop: int | None = None) -> DataFrame:
    """Incoming neighbours first, then outgoing ones, each with a fanout of its own."""
    into = one_hop(frontier, incoming, fan_in, salt, hop).withColumn("side", F.lit(0))
    out = one_hop(frontier, outgoing, fan_out, salt, hop).withColumn("side", F.lit(1))
    return into.unionByName(out)


def _drawn(joined: DataFrame, fanout: int | None, salt: Salt, hop: int | None, key: bool = False) -> DataFrame:
    """(batch_id, node_id[, ..], nbr_rank, nbr_id[, _p]) of rows (batch_id, node_id, nbrs[, ..]): the order of one_hop within each row.
    Priorities are computed many at a time, without a text per candidate; _p are their 16 bytes."""
    more = [c for c in joined.columns if c not in ("batch_id", "node_id", "nbrs")]
    names = ["batch_id", "node_id", *more, "nbr_rank", "nbr_id", *["_p"] * key]
    head = [str(salt.seed), str(salt.epoch)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            lists, batch, node = rows.column(2), rows.column(0).to_pylist(), rows.column(1).to_pylist()
            offsets, values = lists.offsets.to_numpy(), lists.values.to_numpy()
            at = 0
            while at < rows.num_rows:  # about a million candidates at a time, a row at least
                end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + (1 << 20), side="right")) - 1)
                sizes, ids = np.diff(offsets[at : end + 1]), values[offsets[at] : offsets[end]]
                prefixes = [":".join([*head, *(str(x) for x in ((b, n) if hop is None else (b, hop, n)) if x is not None), ""]).encode() for b, n in zip(batch[at:end], node[at:end], strict=True)]
                segments = np.repeat(np.arange(end - at), sizes)
                high, low = md5.priorities(prefixes, segments, ids)
                order, ranks = md5.smallest(segments, end - at, high, low, ids, fanout)
                mine = pa.array(segments[order] + at)
                out = [*(rows.column(i).take(mine) for i in range(rows.num_columns) if i != 2), pa.array((ranks + 1).astype(np.int32)), pa.array(ids[order])]
                if key:
                    both = np.stack([high[order], low[order]], 1).astype(">u8")
                    out.append(pa.FixedSizeBinaryArray.from_buffers(pa.binary(16), len(both), [None, pa.py_buffer(both.tobytes())]).cast(pa.binary()))
                yield pa.RecordBatch.from_arrays(out, names)
                at = end

    kind = {f.name: f.dataType.simpleString() for f in joined.schema}
    kind |= {"nbr_rank": "int", "nbr_id": kind["nbrs"][len("array<") : -1], "_p": "binary"}
    return joined.select("batch_id", "node_id", "nbrs", *more).mapInArrow(run, ", ".join(f"{n} {kind[n]}" for n in names))


@dataclass
class Lists:
    """An adjacency as one row (node_id, nbrs) a vertex. Hubs of more than `width` neighbours have several rows of about that many."""

    rows: DataFrame
    hubs: DataFrame | None

    @classmethod
    def of(cls, adj: DataFrame, width: int = 4096) -> Lists:
        adj = stored(adj, "adjacency", free=True)
        hubs = stored(adj.groupBy("node_id").agg(F.count("*").alias("n")).where(F.col("n") > width), "hubs")
        some = hubs.limit(1).count() > 0
        small = adj.join(hubs, "node_id", "left_anti") if some else adj
        lists = stored(small.groupBy("node_id").agg(F.collect_list("nbr_id").alias("nbrs")), "lists", free=True)
        pieces = None
        if some:
            piece = F.pmod(F.xxhash64("nbr_id"), F.ceil(F.col("n") / width))
            pieces = stored(adj.join(hubs, "node_id").groupBy("node_id", piece.alias("_piece")).agg(F.collect_list("nbr_id").alias("nbrs")).drop("_piece"), "hub_lists", free=True)
        if files := adj.inputFiles():
            drop(adj.sparkSession, files[0].rsplit("/", 1)[0])
        return cls(lists, pieces)

    def top(self, frontier: DataFrame, fanout: int | None, salt: Salt, hop: int | None) -> DataFrame:
        """The rows of one_hop. A vertex's priorities are ranked within its row: no task sorts or sends the candidates; a hub's rows send up to
        `fanout` each. Other columns of the frontier are kept."""
        if salt.fast:
            frontier = frontier.select("batch_id", "node_id")
            parts = lambda n: (F.col("batch_id"), *([F.lit(hop)] if hop is not None else []), F.col("node_id"), n)
            ranked = F.array_sort(F.transform("nbrs", lambda n: F.struct(salt.of(*parts(n)).alias("p"), n.alias("nbr_id"))))
            best = ranked if fanout is None else F.slice(ranked, 1, fanout)
            found = frontier.join(self.rows, "node_id").select("batch_id", "node_id", F.posexplode(best["nbr_id"]).alias("_r", "nbr_id"))
            found = found.select("batch_id", "node_id", (F.col("_r") + 1).alias("nbr_rank"), "nbr_id")
            return found if self.hubs is None else found.unionByName(one_hop(frontier, self._hub_rows(), fanout, salt, hop))
        found = _drawn(frontier.join(self.rows, "node_id"), fanout, salt, hop)
        if self.hubs is None:
            return found
        rank = F.row_number().over(Window.partitionBy("batch_id", "node_id").orderBy("_p", "nbr_id"))
        merged = _drawn(frontier.join(self.hubs, "node_id"), fanout, salt, hop, True).withColumn("nbr_rank", rank).drop("_p")
        return found.unionByName(merged if fanout is None else merged.where(F.col("nbr_rank") <= fanout))

    def _hub_rows(self) -> DataFrame:
        return self.hubs.select("node_id", F.explode("nbrs").alias("nbr_id"))

    def all(self, frontier: DataFrame) -> DataFrame:
        """(batch_id, node_id, nbr_id): every neighbour, without ranks."""
        rows = self.rows if self.hubs is None else self.rows.unionByName(self.hubs)
        return frontier.select("batch_id", "node_id").join(rows, "node_id").select("batch_id", "node_id", F.explode("nbrs").alias("nbr_id"))

    def degrees(self) -> DataFrame:
        own = self.rows.select("node_id", F.size("nbrs").cast("bigint").alias("degree"))
        return own if self.hubs is None else own.unionByName(self.hubs.groupBy("node_id").agg(F.sum(F.size("nbrs")).alias("degree")))


def lists_of(edges: DataFrame, direction: str, targets: DataFrame) -> mapped.Mapped | Lists:
    """The neighbour lists of edges (src_id, dst_id), which may repeat: in files that tasks map if they can hold them, else as a table."""
    return mapped.Mapped.of(edges, direction, targets) or Lists.of(part.adjacency(edges, direction))


def fresh_frontier(sampled: DataFrame, seen: DataFrame) -> DataFrame:
    """Distinct neighbours that the batch hasn't seen yet."""
    new = sampled.select("batch_id", F.col("nbr_id").alias("node_id")).distinct()
    return new.join(seen.select("batch_id", "node_id"), ["batch_id", "node_id"], "left_anti")


@dataclass
class Sample:
    """nodes (batch_id, delta_idx, node_id, fanout) and nbrs (batch_id, delta_idx, node_id, nbr_rank, nbr_id[, rel_id])."""

    nodes: DataFrame
    nbrs: DataFrame
    k: int
    lists: Lists | None = None
    counts: DataFrame | None = None  # nodes with c of sampled_counts


def _step(frontier: DataFrame, adj, fanout: int | None, salt: Salt, hop: int | None = None) -> DataFrame:
    """One hop over an adjacency, or over a pair (incoming, outgoing), of which each gives up to `fanout` neighbours."""
    if isinstance(adj, Lists):
        return adj.top(frontier, fanout, salt, hop)
    if not isinstance(adj, tuple):
        return one_hop(frontier, adj, fanout, salt, hop)
    found = one_hop_both(frontier, adj[1], adj[0], fanout, fanout, salt, hop)
    return found.withColumn("nbr_rank", F.col("nbr_rank") + F.col("side") * (fanout or 1 << 30)).drop("side")


def _keeper(keep: bool):
    """Writes a step's table to the shared folder, so that later steps read it instead of doing it again."""
    return (lambda df, name: stored(df, name, free=True)) if keep else (lambda df, name: df)


def _kept(save, adj, hops: int, lists: bool = False):
    if lists or isinstance(adj, Lists):
        return adj if isinstance(adj, Lists) else Lists.of(adj)
    if hops < 2:
        return adj
    return tuple(save(a, "adjacency") for a in adj) if isinstance(adj, tuple) else save(adj, "adjacency")


def delta_sample(targets: DataFrame, adj, fanouts: list[int | None], salt: Salt = Salt(), keep: bool = True, hops: bool = True) -> Sample:
    """fanouts[0] applies to the targets (group k); group i-1 are vertices first met among the neighbours of group i.

    adj: an adjacency, or a pair (incoming, outgoing). keep: each hop is written once and read by all that needs it, so the plan grows
    by the same number of scans with every hop; without it each hop repeats all hops before. hops=False (one adjacency, no relations): only the vertices
    are written; nbrs draws each hop from them once more where it is read, and sampled_counts needs no hop at all. Mapped lists (lists_of): nothing
    is written, and nodes and nbrs are drawn where they are read.
    """
    if isinstance(adj, mapped.Mapped):
        counts = mapped.delta_nodes(adj, targets, fanouts, salt)
        return Sample(counts.drop("c"), mapped.delta_nbrs(adj, targets, fanouts, salt), len(fanouts), counts=counts)
    k, save = len(fanouts), _keeper(keep)
    adj = _kept(save, adj, k, not hops)
    frontier = targets.select("batch_id", "node_id").distinct()
    frontier = save(frontier, "targets") if k else frontier
    nodes, nbrs = None, None
    for i, fanout in zip(range(k, 0, -1), fanouts, strict=True):
        group = frontier.select("batch_id", F.lit(i).alias("delta_idx"), "node_id", F.lit(fanout).cast("int").alias("fanout"))
        nodes = group if nodes is None else nodes.unionByName(group)
        found = _step(frontier, adj, fanout, salt).withColumn("delta_idx", F.lit(i))
        found = save(found, "hop") if hops else found
        nbrs = found if nbrs is None else nbrs.unionByName(found)
        met = adj.all(frontier) if not hops and fanout is None else found
        frontier = save(fresh_frontier(met, nodes), "frontier")
    last = frontier.select("batch_id", F.lit(0).alias("delta_idx"), "node_id", F.lit(None).cast("int").alias("fanout"))
    return Sample(last if nodes is None else nodes.unionByName(last), nbrs, k, None if hops else adj)


def layer_resample(targets: DataFrame, adj, fanouts: list[int], salt: Salt = Salt(), layer_salt: bool = True, keep: bool = True, hops: bool = True) -> DataFrame:
    """(batch_id, hop, node_id, nbr_rank, nbr_id): in each hop all vertices met so far are sampled again. hops: as in delta_sample."""
    if isinstance(adj, mapped.Mapped):
        return mapped.resampled(adj, targets, fanouts, salt, layer_salt)
    save = _keeper(keep)
    adj = _kept(save, adj, len(fanouts), not hops)
    frontier, out = save(targets.select("batch_id", "node_id").distinct(), "targets"), None
    for hop, fanout in enumerate(fanouts):
        found = _step(frontier, adj, fanout, salt, hop if layer_salt else None).withColumn("hop", F.lit(hop))
        found = save(found, "hop") if hops else found
        out = found if out is None else out.unionByName(found)
        if hop + 1 < len(fanouts):
            frontier = save(frontier.unionByName(found.select("batch_id", F.col("nbr_id").alias("node_id"))).distinct(), "frontier")
    return out


def path_sample(targets: DataFrame, adj, fanouts: list[int], salt: Salt = Salt(), dedupe: bool = False, keep: bool = True) -> DataFrame:
    """(batch_id, hop, node_id, nbr_id, n_paths): expansion along paths, without reuse between layers.

    Paths through one vertex at one hop share its sample, so equal paths are counted instead of listed. dedupe: once per hop.
    """
    save = _keeper(keep)
    adj = _kept(save, adj, len(fanouts))
    frontier = save(targets.select("batch_id", "node_id").distinct().withColumn("n_paths", F.lit(1).cast("bigint")), "targets")
    out = None
    for hop, fanout in enumerate(fanouts):
        found = _step(frontier, adj, fanout, salt, hop).join(frontier, ["batch_id", "node_id"]).withColumn("hop", F.lit(hop))
        found = save(found.select("batch_id", "hop", "node_id", "nbr_id", "n_paths"), "hop")
        out = found if out is None else out.unionByName(found)
        if hop + 1 < len(fanouts):
            frontier = save(found.groupBy("batch_id", F.col("nbr_id").alias("node_id")).agg((F.lit(1) if dedupe else F.sum("n_paths")).cast("bigint").alias("n_paths")), "frontier")
    return out


def resample_path_counts(targets: DataFrame, lists: mapped.Mapped | Lists, fanouts: list[int], salt: Salt = Salt()) -> DataFrame:
    """(k, resample_nodes, resample_edges, path_edges) of layer_resample and path_sample for each depth k, without writing a hop.

    Both draw a vertex's neighbours in a hop by the same priorities, and a path's vertex is always among those met so far. So each hop is
    drawn once; the frontier holds the number of paths that end at a vertex in this hop, 0 for one that was met earlier only. A hop's
    edges follow from degrees.
    """
    so_far = Window.partitionBy(F.lit(0)).orderBy("k")  # a row for each depth
    path_edges = F.when(F.count(F.when(F.col("p").isNull(), 1)).over(so_far) == 0, F.sum("p").over(so_far)).alias("path_edges")
    if isinstance(lists, mapped.Mapped):
        drawn = mapped.resample_path_sizes(lists, targets, fanouts, salt).groupBy((F.col("hop") + 1).alias("k")).agg(*(F.sum(c).alias(c) for c in "nep"))
        depths = targets.sparkSession.range(1, len(fanouts) + 1).select(F.col("id").cast("int").alias("k"))  # those without a batch too
        drawn = depths.join(drawn, "k", "left").withColumns({c: F.coalesce(c, F.lit(0).cast("bigint")) for c in "ne"})
        return drawn.select("k", F.col("n").alias("resample_nodes"), F.sum("e").over(so_far).alias("resample_edges"), path_edges)
    degrees = stored(lists.degrees(), "degrees")
    frontier = stored(targets.select("batch_id", "node_id").distinct().withColumn("n_paths", F.lit(1).cast("bigint")), "targets")
    met, edges = None, None
    for hop, fanout in enumerate(fanouts):
        c = F.least("degree", F.lit(fanout).cast("bigint"))
        sizes = frontier.join(degrees, "node_id").agg(F.coalesce(F.sum(c), F.lit(0)).alias("e"), F.sum(F.when(F.col("n_paths") > 0, F.col("n_paths") * c)).alias("p")).select(F.lit(hop + 1).alias("k"), "e", "p")
        edges = sizes if edges is None else edges.unionByName(sizes)
        if hop + 1 < len(fanouts):
            found = lists.top(frontier, fanout, salt, hop).select("batch_id", F.col("nbr_id").alias("node_id"), "n_paths")
            frontier = stored(found.unionByName(frontier.withColumn("n_paths", F.lit(0).cast("bigint"))).groupBy("batch_id", "node_id").agg(F.sum("n_paths").alias("n_paths")), "frontier", free=True)
            now = frontier
        else:
            own = frontier.select("batch_id", "node_id")
            now = lists.top(own, fanout, salt, hop).select("batch_id", F.col("nbr_id").alias("node_id")).unionByName(own).distinct()
        now = now.agg(F.count("*").alias("resample_nodes")).select(F.lit(hop + 1).alias("k"), "resample_nodes")
        met = now if met is None else met.unionByName(now)
    total = edges.select("k", F.sum("e").over(so_far).alias("resample_edges"), path_edges)
    return met.join(total, "k").select("k", "resample_nodes", "resample_edges", "path_edges")


def khop_exact(targets: DataFrame, adj: DataFrame, k: int, keep: bool = True) -> DataFrame:
    """(batch_id, node_id, dist): all vertices within k hops."""
    save = _keeper(keep)
    adj = _kept(save, adj, k)
    seen = save(targets.select("batch_id", "node_id").distinct().withColumn("dist", F.lit(0)), "targets")
    frontier = seen
    for hop in range(1, k + 1):
        near = frontier.join(adj, "node_id").select("batch_id", F.col("nbr_id").alias("node_id")).distinct()
        frontier = save(near.join(seen, ["batch_id", "node_id"], "left_anti").withColumn("dist", F.lit(hop)), "frontier")
        seen = seen.unionByName(frontier)
    return seen


def sampled_counts(sample: Sample) -> DataFrame:
    """(batch_id, delta_idx, node_id, fanout, c) for every vertex of a delta sample: how many neighbours it drew. With kept lists that is
    the fanout or the degree, whichever is less."""
    if sample.counts is not None:
        return sample.counts
    if sample.lists is None:
        drawn = sample.nbrs.groupBy("batch_id", "node_id").agg(F.count("*").alias("c"))
        return sample.nodes.join(drawn, ["batch_id", "node_id"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    drawn = F.when(F.col("delta_idx") > 0, F.least(F.coalesce("degree", F.lit(0)), F.coalesce(F.col("fanout").cast("bigint"), F.col("degree"), F.lit(0)))).otherwise(0)
    return sample.nodes.join(sample.lists.degrees(), "node_id", "left").select("batch_id", "delta_idx", "node_id", "fanout", drawn.cast("bigint").alias("c"))


def sample_stats(sample: Sample) -> DataFrame:
    """(batch_id, n_nodes, n_edges) of a delta sample."""
    if sample.lists is not None or sample.counts is not None:
        return sampled_counts(sample).groupBy("batch_id").agg(F.count("*").alias("n_nodes"), F.sum("c").alias("n_edges"))
    n = sample.nodes.groupBy("batch_id").agg(F.count("*").alias("n_nodes"))
    if sample.nbrs is None:
        return n.withColumn("n_edges", F.lit(0).cast("bigint"))
    e = sample.nbrs.groupBy("batch_id").agg(F.count("*").alias("n_edges"))
    return n.join(e, "batch_id", "left").select("batch_id", "n_nodes", F.coalesce("n_edges", F.lit(0)).cast("bigint").alias("n_edges"))


def hop_stats(edges: DataFrame, targets: DataFrame) -> DataFrame:
    """The same for a baseline's edges: unique vertices and edges summed over hops."""
    ends = targets.select("batch_id", "node_id").unionByName(edges.select("batch_id", F.col("nbr_id").alias("node_id"))).distinct()
    n = ends.groupBy("batch_id").agg(F.count("*").alias("n_nodes"))
    weight = F.sum("n_paths") if "n_paths" in edges.columns else F.count("*")
    return n.join(edges.groupBy("batch_id").agg(weight.cast("bigint").alias("n_edges")), "batch_id", "left")


def subset_diversity(samples: DataFrame) -> DataFrame:
    """(node_id, n_samples, n_subsets) of samples (sample_id, node_id, nbr_id): how many different neighbour sets a vertex got."""
    sets = samples.groupBy("sample_id", "node_id").agg(F.array_join(F.array_sort(F.collect_list("nbr_id")), ",").alias("members"))
    return sets.groupBy("node_id").agg(F.count("*").alias("n_samples"), F.countDistinct("members").alias("n_subsets"))
