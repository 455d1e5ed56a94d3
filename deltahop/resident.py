"""A graph, or the subgraph of a resident set, that fits a task: sampling, batches and negatives of its mini batches in numpy.

Every task gets the same read-only copy and draws whole batches from it, so an epoch is one plan instead of a dozen for every hop. All
choices are those of the relational operators: the same hashes, hence the same samples, batches and negatives. Graphs above `LIMIT`
bytes, or with vertices that lack a vector, are left to these operators.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop import hashing, md5
from deltahop.operators.packing import Packed
from deltahop.operators.sampling import Salt

LIMIT = 160 << 20  # bytes of a copy: vectors, states, neighbour lists and examples


def _column(table: pa.Table, name: str) -> np.ndarray | None:
    """A column without nulls."""
    column = table[name]
    return None if column.null_count else column.to_numpy()


def _matrix(table: pa.Table, name: str, order: np.ndarray) -> np.ndarray | None:
    """A column of equally long arrays, its rows in the given order."""
    lists = pa.concat_arrays(table[name].chunks)
    values = lists.flatten()
    if lists.null_count or values.null_count or len(np.unique(np.diff(lists.offsets.to_numpy()))) != 1:
        return None
    return values.to_numpy().reshape(len(lists), -1)[order]


def mixed(ids: np.ndarray, seed: int) -> np.ndarray:
    """hashing.mix of many ids."""
    return (np.mod(ids, hashing.MIX_PRIME) * 1103515245 + seed * 16807 + 7) % hashing.MIX_PRIME * 69621 % hashing.MIX_PRIME


def fits(n_edges: int, n_nodes: int, d: int, direction: str, limit: int = LIMIT) -> bool:
    return n_nodes * (16 + d * 16) + n_edges * (20 if direction in ("any", "both") else 16) <= limit


@dataclass
class Resident:
    """ids ascend; all other vertices are places in ids. lists: (starts, neighbours) for each direction that is sampled."""

    ids: np.ndarray
    h: np.ndarray
    s: np.ndarray | None  # None: zeros
    rest: pa.Table  # the other columns of the vertices
    lists: list[tuple[np.ndarray, np.ndarray]]
    src: np.ndarray
    rel: np.ndarray
    dst: np.ndarray

    @classmethod
    def of(cls, edges: DataFrame, h0: DataFrame, direction: str, limit: int = LIMIT) -> Resident | None:
        """The graph of edges and vectors (node_id, h[, s][, ..]), or None if it doesn't fit or isn't regular."""
        n, d = h0.agg(F.count("*"), F.coalesce(F.max(F.size("h")), F.lit(0))).first()
        if not n or not fits(0, n, d, direction, limit) or not fits(edges.count(), n, d, direction, limit):
            return None
        return cls.of_tables(edges.select("src_id", "rel_id", "dst_id").toArrow(), h0.toArrow(), direction)

    @classmethod
    def of_tables(cls, edges: pa.Table, table: pa.Table, direction: str) -> Resident | None:
        ids = _column(table, "node_id")
        if ids is None or not len(ids):
            return None
        order = np.argsort(ids)
        ids = ids[order]
        h = _matrix(table, "h", order)
        s = _matrix(table, "s", order) if "s" in table.column_names else None
        if h is None or (ids[1:] == ids[:-1]).any() or ("s" in table.column_names and s is None):
            return None
        rest = table.select([c for c in table.column_names if c not in ("h", "s")]).take(pa.array(order))
        graph = cls(ids, h, s, rest, [], *(np.empty(0, np.int32) for _ in range(3)))
        ends = graph.examples(edges)
        if ends is None:
            return None
        graph.src, graph.rel, graph.dst = ends
        out, into = (graph.src, graph.dst), (graph.dst, graph.src)
        if direction == "any":
            graph.lists = [graph._lists(np.concatenate([out[0], into[0]]), np.concatenate([out[1], into[1]]))]
        else:
            graph.lists = [graph._lists(*x) for x in {"in": [into], "out": [out], "both": [into, out]}[direction]]
        return graph

    def places(self, ids: np.ndarray | None) -> np.ndarray | None:
        """Places of ids, None if one of them is no vertex."""
        if ids is None:
            return None
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1)
        return at.astype(np.int32) if (self.ids[at] == ids).all() else None

    def examples(self, edges: DataFrame | pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
        """(src, rel, dst) of edges."""
        table = edges if isinstance(edges, pa.Table) else edges.select("src_id", "rel_id", "dst_id").toArrow()
        ends = self.places(_column(table, "src_id")), _column(table, "rel_id"), self.places(_column(table, "dst_id"))
        return None if any(x is None for x in ends) else (ends[0], ends[1].astype(np.int32), ends[2])

    def moved(self, h0: DataFrame) -> Resident:
        """The same graph with new vectors and states of its vertices."""
        table = h0.select("node_id", "h", "s").toArrow()
        order = np.argsort(table["node_id"].to_numpy())
        return replace(self, h=_matrix(table, "h", order), s=_matrix(table, "s", order))

    def labelled(self, nodes: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
        """(vertices, labels) of nodes (node_id, label), each vertex once."""
        table = nodes.select("node_id", "label").toArrow()
        at, labels = self.places(_column(table, "node_id")), _column(table, "label")
        return None if at is None or labels is None or len(np.unique(at)) != len(at) else (at, labels.astype(np.int64))

    def _lists(self, node: np.ndarray, nbr: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Different neighbours of every vertex, one list after another."""
        n = len(self.ids)
        keys = np.unique(node.astype(np.int64) * n + nbr)
        return np.searchsorted(keys, np.arange(n + 1, dtype=np.int64) * n), (keys % n).astype(np.int32)

    def sample(self, batch: int, targets: np.ndarray, fanouts: list[int | None], salt: Salt) -> Packed:
        """The delta sample of different, ascending targets, packed; vertex_ids and nbr_ids are places."""
        seen = np.zeros(len(self.ids), bool)
        seen[targets] = True
        groups, hops = [targets], []
        for fanout in fanouts:
            node, sides = groups[-1], []
            prefixes = [f"{salt.seed}:{salt.epoch}:{batch}:{i}:".encode() for i in self.ids[node].tolist()]
            for starts, nbrs in self.lists:
                sizes = starts[node + 1] - starts[node]
                segments = np.repeat(np.arange(len(node)), sizes)
                before = np.cumsum(sizes) - sizes
                found = nbrs[np.arange(len(segments)) + (starts[node] - before)[segments]]
                high, low = md5.priorities(prefixes, segments, self.ids[found])
                order, _ = md5.smallest(segments, len(node), high, low, self.ids[found], fanout)
                sides.append((segments[order], found[order]))
            segments, found = np.concatenate([x[0] for x in sides]), np.concatenate([x[1] for x in sides])
            order = np.argsort(segments, kind="stable")  # a vertex's incoming neighbours stay first
            hops.append((np.bincount(segments, minlength=len(node)), found[order]))
            met = np.zeros(len(self.ids), bool)
            met[found] = True
            new = np.flatnonzero(met & ~seen)
            seen |= met
            groups.append(new)
        sizes = np.array([len(g) for g in reversed(groups)])
        vertices = np.concatenate(groups[::-1])
        place = np.empty(len(self.ids), np.int64)
        place[vertices] = np.arange(len(vertices))
        counts = np.concatenate([np.empty(0, np.int64), *(c for c, _ in reversed(hops))])
        found = np.concatenate([np.empty(0, np.int32), *(f for _, f in reversed(hops))])
        return Packed(np.cumsum(sizes) - sizes, vertices, np.cumsum(counts) - counts, found, place[found])

    def pool(self, seed: int) -> np.ndarray:
        """The vertices that edges end at, in hash order."""
        ends = np.unique(self.dst)
        return ends[np.lexsort((self.ids[ends], mixed(self.ids[ends], seed)))]

    def batches(self, ends: tuple[np.ndarray, np.ndarray, np.ndarray], seed: int, epoch: int) -> tuple[np.ndarray, ...]:
        """Examples (src, rel, dst) in the order that exact_batches cuts into batches."""
        src, rel, dst = ends
        heads, which = np.unique(src.astype(np.int64) << 32 | rel.astype(np.int64), return_inverse=True)
        prefixes = [f"{seed}:{epoch}:{i}:{r}:".encode() for i, r in zip(self.ids[heads >> 32].tolist(), (heads & 0xFFFFFFFF).tolist(), strict=True)]
        high, low = md5.priorities(prefixes, which, self.ids[dst])
        order = np.lexsort((dst, src, low, high))
        return src[order], rel[order], dst[order]


def negatives(pool: np.ndarray, n: int, seed: int, epoch: int, batch: int) -> np.ndarray:
    """The candidates of sample_negatives for one batch, ascending. pool: in hash order."""
    if len(pool) <= n:
        return np.sort(pool)
    drawn: dict[int, None] = {}
    for k in range(2 * n):
        hit = int(hashlib.md5(f"{seed}:{epoch}:{batch}:{k}".encode()).hexdigest()[:8], 16)
        drawn[int(pool[hit * len(pool) >> 32])] = None
        if len(drawn) == n:
            break
    return np.sort(np.fromiter(drawn, np.int64))
