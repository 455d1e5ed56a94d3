"""Neighbour lists in files of the shared folder, which tasks map into memory: a task draws all hops of a batch by itself.

The lists of a graph are written once, by buckets of vertices; a task reads the pages it needs and several tasks of a machine share
them. So an epoch's hops need no join and no shuffle of drawn neighbours. Samples are those of the relational operators: the same hashes in the
same order. A vertex of a batch whose neighbours were all met already can meet nothing new, so where only the met vertices are
asked for it is not drawn. Graphs above MOST_VERTICES or MOST_PAIRS, with null ids, with a neighbour that is no vertex, or a shared folder
that isn't mounted as files are left to the relational operators.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import unquote, urlparse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop import md5
from deltahop.operators.storage import drop, shared_path, stored

MOST_VERTICES = 1 << 24  # the driver orders their ids
MOST_PAIRS = 1 << 29
BUCKETS = 256
HELD = 1 << 20  # pairs that a task sorts at once
_CHUNK = 1 << 19  # candidates that a task draws from at once


def _unique(node: np.ndarray, nbr: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different pairs, ascending."""
    if not len(node):
        return node, nbr
    a, b = int(node.min()), int(nbr.min())
    span = int(nbr.max()) - b + 1
    if (int(node.max()) - a + 1) * span < 1 << 63:
        key = np.sort((node - a) * span + (nbr - b))
        key = key[np.append(True, key[1:] != key[:-1])]
        return key // span + a, key % span + b
    order = np.lexsort((nbr, node))
    node, nbr = node[order], nbr[order]
    first = np.append(True, (node[1:] != node[:-1]) | (nbr[1:] != nbr[:-1]))
    return node[first], nbr[first]


def _bucket(ids: np.ndarray) -> np.ndarray:
    return (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(48)).astype(np.int64) % BUCKETS


def _blobs(rows: DataFrame, direction: str | None) -> DataFrame:
    """(bucket, nodes, sizes, nbrs) of rows (src_id, dst_id), or (node_id) for vertices alone (None). Bucket -1 stands for nulls."""
    fields = [pa.field("bucket", pa.int32()), *(pa.field(c, pa.binary()) for c in ("nodes", "sizes", "nbrs"))]

    def pieces(held: list) -> Iterator[pa.RecordBatch]:
        src, dst = (np.concatenate([x[i] for x in held]) for i in (0, -1))
        if direction is None:
            nodes, sizes, nbr = np.unique(src), None, np.empty(0, np.int64)
            sizes = np.zeros(len(nodes), np.int64)
        else:
            both = [(src, dst)] * (direction != "in") + [(dst, src)] * (direction != "out")
            node, nbr = _unique(*(np.concatenate([x[i] for x in both]) for i in (0, 1)))
            first = np.flatnonzero(np.append(True, node[1:] != node[:-1]))
            nodes, sizes = node[first], np.diff(np.append(first, len(node)))
            nbr = nbr[np.argsort(np.repeat(_bucket(nodes), sizes).astype(np.uint16), kind="stable")]
        bucket = _bucket(nodes)
        order = np.argsort(bucket, kind="stable")
        nodes, sizes = nodes[order], sizes[order]
        cuts = np.searchsorted(bucket[order], np.arange(BUCKETS + 1))
        ends = np.append(0, np.cumsum(sizes))[cuts]
        out = [(k, nodes[a:b].tobytes(), sizes[a:b].astype(np.int32).tobytes(), nbr[ends[k] : ends[k + 1]].tobytes()) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if a < b]
        yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*out, strict=True), fields, strict=True)], schema=pa.schema(fields))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for rows in batches:
            if any(c.null_count for c in rows.columns):
                yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int32()), *[pa.array([b""])] * 3], schema=pa.schema(fields))
                continue
            held.append([c.to_numpy().astype(np.int64) for c in rows.columns])
            n += rows.num_rows
            if n >= HELD:
                yield from pieces(held)
                held, n = [], 0
        if n:
            yield from pieces(held)

    return rows.mapInArrow(run, "bucket int, nodes binary, sizes binary, nbrs binary")


def _write(path: str, values: np.ndarray) -> None:
    """The whole file or none, should the task be run again."""
    part = f"{path}.{os.getpid()}-{os.urandom(4).hex()}"
    values.tofile(part)
    os.replace(part, path)


@dataclass
class Mapped:
    """path: a folder with ids (ascending), starts, sizes, texts and lengths by a vertex's place in ids, and the places of neighbours."""

    path: str
    kinds: tuple[str, str]

    @classmethod
    def of(cls, edges: DataFrame, direction: str, targets: DataFrame) -> Mapped | None:
        """The lists of edges (src_id, dst_id), which may repeat, in one direction or in both ('any'); targets (batch_id, node_id) are vertices too.
        None if this form can't hold them."""
        spark = edges.sparkSession
        uri = urlparse(shared_path(spark, "mapped"))
        if uri.scheme not in ("", "file") or targets.where("batch_id is null or node_id is null").limit(1).count():
            return None
        path = unquote(uri.path)
        os.makedirs(path)

        def merge(rows: pa.Table) -> pa.Table:
            bucket = rows["bucket"][0].as_py()
            if bucket < 0:
                return pa.table({"bucket": pa.array([bucket], pa.int32()), "n": [0], "m": [0]})
            held = {c: np.concatenate([np.frombuffer(x, np.int32 if c == "sizes" else np.int64) for x in rows[c].to_pylist()]) for c in ("nodes", "sizes", "nbrs")}
            nodes = np.unique(held["nodes"])
            node, nbr = _unique(np.repeat(held["nodes"], held["sizes"]), held["nbrs"])
            sizes = np.diff(np.append(np.searchsorted(node, nodes), len(node)))
            for name, values in (("nodes", nodes), ("sizes", sizes), ("nbrs", nbr)):
                _write(f"{path}/{bucket}.{name}", values.astype(np.int64))
            return pa.table({"bucket": pa.array([bucket], pa.int32()), "n": [len(nodes)], "m": [len(nbr)]})

        blobs = _blobs(edges.select("src_id", "dst_id"), direction).unionByName(_blobs(targets.select("node_id"), None))
        done = stored(blobs.groupBy("bucket").applyInArrow(merge, "bucket int, n bigint, m bigint"), "buckets", free=True)
        counts = sorted(tuple(r) for r in done.collect())
        n, m = sum(x[1] for x in counts), sum(x[2] for x in counts)
        kinds = tuple(targets.schema[c].dataType.simpleString() for c in ("batch_id", "node_id"))
        if n and counts[0][0] >= 0 and n <= MOST_VERTICES and m <= MOST_PAIRS and cls._joined(spark, path, counts, m):
            return cls(path, kinds)
        drop(spark, f"file://{path}")
        return None

    @staticmethod
    def _joined(spark, path: str, counts: list, m: int) -> bool:
        """Brings the buckets together; whether all neighbours are vertices."""
        nodes, sizes = (np.concatenate([np.fromfile(f"{path}/{b}.{c}", np.int64) for b, _, _ in counts]) for c in ("nodes", "sizes"))
        order = np.argsort(nodes)
        ids = nodes[order]
        words, lengths = md5.texts(ids)
        for name, values in (("ids", ids), ("starts", (np.cumsum(sizes) - sizes)[order]), ("sizes", sizes[order]), ("words", words), ("lengths", lengths)):
            np.save(f"{path}/{name}.npy", values)
        with open(f"{path}/nbrs", "wb") as f:
            f.truncate(4 * max(m, 1))
        begin = dict(zip([b for b, _, _ in counts], np.cumsum([0, *(x[2] for x in counts)]).tolist(), strict=False))

        def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ids = np.load(f"{path}/ids.npy")
            for rows in frames:
                for b in rows.column(0).to_pylist():
                    nbrs = np.fromfile(f"{path}/{b}.nbrs", np.int64) if b in begin else np.empty(0, np.int64)
                    at = np.minimum(np.searchsorted(ids, nbrs), len(ids) - 1)
                    if len(at):
                        np.memmap(f"{path}/nbrs", np.int32, "r+", begin[b] * 4, len(at))[:] = at
                    yield pa.RecordBatch.from_arrays([pa.array([int((ids[at] != nbrs).sum())], pa.int64())], ["missing"])

        missing = spark.range(0, BUCKETS, 1, min(BUCKETS, 4 * spark.sparkContext.defaultParallelism)).mapInArrow(run, "missing bigint").agg(F.sum("missing")).first()[0]
        for b, _, _ in counts:
            for c in ("nodes", "sizes", "nbrs"):
                os.unlink(f"{path}/{b}.{c}")
        return missing == 0

    def each_batch(self, targets: DataFrame, draw, schema: str) -> DataFrame:
        """Rows of draw(sampler, batch, ascending different places of its targets), an iterator of columns, for every batch."""
        tasks, path = 16 * targets.sparkSession.sparkContext.defaultParallelism, self.path
        rows = targets.select("batch_id", "node_id").repartition(tasks, "batch_id").groupBy("batch_id").agg(F.collect_list("node_id").alias("nodes"))
        names = [x.split()[0] for x in schema.split(", ")]
        kinds = [{"int": pa.int32(), "bigint": pa.int64()}[x.split()[1]] for x in schema.split(", ")]

        def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sampler = Sampler(path)
            for rows in frames:
                for batch, nodes in zip(rows.column(0).to_pylist(), rows.column(1), strict=True):
                    targets = np.searchsorted(sampler.ids, np.unique(nodes.values.to_numpy()))
                    for columns in draw(sampler, batch, targets):
                        n = next(len(c) for c in columns if isinstance(c, np.ndarray))
                        if n:
                            yield pa.RecordBatch.from_arrays([pa.array(c.astype(k.to_pandas_dtype(), copy=False)) if isinstance(c, np.ndarray) else pa.repeat(pa.scalar(c, k), n) for c, k in zip(columns, kinds, strict=True)], names)

        return rows.mapInArrow(run, schema)


class Sampler:
    """The files of Mapped in a task."""

    def __init__(self, path: str):
        self.ids, self.starts, self.sizes, self.words, self.lengths = (np.load(f"{path}/{c}.npy", mmap_mode="r").view(np.ndarray) for c in ("ids", "starts", "sizes", "words", "lengths"))
        self.nbrs = np.memmap(f"{path}/nbrs", np.int32, "r").view(np.ndarray)

    def candidates(self, nodes: np.ndarray, met: np.ndarray | None = None, always: np.ndarray | None = None) -> Iterator[tuple]:
        """(rows of nodes, their list sizes, neighbours), many vertices at a time. met: leaves out vertices without a neighbour that isn't met, but for `always`."""
        sizes = self.sizes[nodes]
        ends, at = np.cumsum(sizes), 0
        while at < len(nodes):
            end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _CHUNK, side="right")))
            rows, n = np.arange(at, end), sizes[at:end]
            found = self.nbrs[np.arange(int(n.sum())) + np.repeat(self.starts[nodes[at:end]] - np.cumsum(n) + n, n)]
            if met is not None:
                of = np.repeat(np.arange(end - at), n)
                useful = np.zeros(end - at, bool) if always is None else always[at:end].copy()
                useful[of[met[found] == 0]] = True
                if not useful.all():
                    rows, found, n = rows[useful], found[useful[of]], n[useful]
            yield rows, n, found
            at = end

    def draw(self, head: str, nodes: np.ndarray, fanout: int | None, met: np.ndarray | None = None, always: np.ndarray | None = None, ranked: bool = False) -> Iterator[tuple]:
        """(rows of nodes, neighbours, ranks from 0 if ranked) of the first `fanout` neighbours of each vertex. head: text before the vertex in the hash."""
        for rows, n, found in self.candidates(nodes, met, always):
            if not ranked and (fanout is None or (n <= fanout).all()):
                yield np.repeat(rows, n), found, None
                continue
            if not ranked and (n <= fanout).any():
                few = n <= fanout
                of = np.repeat(few, n)
                yield np.repeat(rows[few], n[few]), found[of], None
                rows, n, found = rows[~few], n[~few], found[~of]
            prefixes = [f"{head}{i}:".encode() for i in self.ids[nodes[rows]].tolist()]
            of, order, ranks = md5.first(prefixes, n, self.words, self.lengths, self.ids, found, fanout)
            yield rows[of], found[order], ranks

    def hop(self, head: str, nodes: np.ndarray, fanout: int | None, met: np.ndarray) -> np.ndarray:
        """Ascending vertices that are met anew, marked in met."""
        for _, found, _ in self.draw(head, nodes, fanout, met):
            met[found[met[found] == 0]] = 2
        new = np.flatnonzero(met == 2)
        met[new] = 1
        return new

    def marks(self, targets: np.ndarray) -> np.ndarray:
        met = np.zeros(len(self.ids), np.uint8)
        met[targets] = 1
        return met


def _head(salt, batch, hop: int | None = None) -> str:
    return ":".join(str(x) for x in (salt.seed, salt.epoch, batch, hop) if x is not None) + ":"


def delta_nodes(lists: Mapped, targets: DataFrame, fanouts: list[int | None], salt) -> DataFrame:
    """(batch_id, delta_idx, node_id, fanout, c) of delta_sample; c: how many neighbours the vertex draws."""
    k = len(fanouts)

    def draw(sampler: Sampler, batch, group: np.ndarray) -> Iterator[tuple]:
        met = sampler.marks(group)
        for i, fanout in zip(range(k, 0, -1), fanouts, strict=True):
            sizes = sampler.sizes[group]
            yield batch, i, sampler.ids[group], fanout, sizes if fanout is None else np.minimum(sizes, fanout)
            group = sampler.hop(_head(salt, batch), group, fanout, met)
        yield batch, 0, sampler.ids[group], None, np.zeros(len(group), np.int64)

    return lists.each_batch(targets, draw, f"batch_id {lists.kinds[0]}, delta_idx int, node_id {lists.kinds[1]}, fanout int, c bigint")


def delta_nbrs(lists: Mapped, targets: DataFrame, fanouts: list[int | None], salt) -> DataFrame:
    """(batch_id, delta_idx, node_id, nbr_rank, nbr_id) of delta_sample."""
    k = len(fanouts)

    def draw(sampler: Sampler, batch, group: np.ndarray) -> Iterator[tuple]:
        met = sampler.marks(group)
        for i, fanout in zip(range(k, 0, -1), fanouts, strict=True):
            for rows, found, ranks in sampler.draw(_head(salt, batch), group, fanout, ranked=True):
                yield batch, i, sampler.ids[group[rows]], ranks + 1, sampler.ids[found]
                met[found[met[found] == 0]] = 2
            group = np.flatnonzero(met == 2)
            met[group] = 1

    return lists.each_batch(targets, draw, f"batch_id {lists.kinds[0]}, delta_idx int, node_id {lists.kinds[1]}, nbr_rank int, nbr_id {lists.kinds[1]}")


def resampled(lists: Mapped, targets: DataFrame, fanouts: list[int], salt, layer_salt: bool) -> DataFrame:
    """(batch_id, hop, node_id, nbr_rank, nbr_id) of layer_resample."""

    def draw(sampler: Sampler, batch, group: np.ndarray) -> Iterator[tuple]:
        met = sampler.marks(group)
        for hop, fanout in enumerate(fanouts):
            for rows, found, ranks in sampler.draw(_head(salt, batch, hop if layer_salt else None), group, fanout, ranked=True):
                yield batch, hop, sampler.ids[group[rows]], ranks + 1, sampler.ids[found]
                met[found] = 1
            group = np.flatnonzero(met)

    return lists.each_batch(targets, draw, f"batch_id {lists.kinds[0]}, hop int, node_id {lists.kinds[1]}, nbr_rank int, nbr_id {lists.kinds[1]}")


def resample_path_sizes(lists: Mapped, targets: DataFrame, fanouts: list[int], salt) -> DataFrame:
    """(hop, n, e, p) of every batch: vertices met after the hop, the edges that layer_resample draws in it, and those of path_sample (null if no path goes on)."""

    def draw(sampler: Sampler, batch, group: np.ndarray) -> Iterator[tuple]:
        met, paths = sampler.marks(group), np.ones(len(group), np.int64)
        for hop, fanout in enumerate(fanouts):
            c = np.minimum(sampler.sizes[group], fanout)
            e, p = int(c.sum()), int((paths * c).sum()) if (paths > 0).any() else None
            last, ends = hop + 1 == len(fanouts), np.zeros(0 if hop + 1 == len(fanouts) else len(met), np.int64)
            for rows, found, _ in sampler.draw(_head(salt, batch, hop), group, fanout, met, None if last else paths > 0):
                met[found] = 1
                if not last:
                    np.add.at(ends, found, paths[rows])
            group = np.flatnonzero(met)
            paths = ends[group] if not last else None
            yield np.array([hop]), len(group), e, p

    return lists.each_batch(targets, draw, "hop int, n bigint, e bigint, p bigint")
