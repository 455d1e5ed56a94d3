"""Suffix-array dedup: later copies of long byte strings go, the first stays.

Every byte covered by a string of `length` bytes that also starts in a document with a smaller id is removed. In the suffix
order of all texts the earlier match of a suffix is its previous or next neighbour from an earlier document; the longer of both is its
longest previous factor, and a window goes where that reaches `length`. The suffix order is partitioned: of the short hashes within a window the smallest one is its anchor,
so equal windows have equal anchors and suffixes only need to be compared with those of the same anchor.

    1  a chunk sends its distinct anchors, each with a hash of its cell (all bytes of the windows that share it), to buckets
    2  an anchor with one cell everywhere is settled: the first document keeps it, the others lose it
    3  of other anchors the cells go to buckets as bytes; there the suffixes are sorted, and previous and next
       smaller documents in suffix order, with the least common prefix on the way to them, give the factors
    4  a chunk marks the removed bytes

Anchors that very many cells share send their windows one by one, dealt out by window, so no bucket gathers them. Keys
are combined within a chunk before they are sent, so a passage that many documents share costs one entry per chunk.

Defined results: null and empty texts have no bytes; rows that repeat an id never remove bytes from each other; a null
id comes after all others and removes nothing; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltahop.llm import packed
from deltahop.llm import textnum as tn
from deltahop.llm.workdir import drop_path, stored

LAST = np.iinfo(np.int64).max


@dataclass(frozen=True)
class SuffixConfig:
    length: int = 50
    gram: int = 16
    chunk_bytes: int = 5 << 20
    bucket_bytes: int = 8 << 20
    slab_bytes: int = 512 << 10
    hot_cells: int = 5000
    sorted_at_once: int = 250_000  # suffixes


# ---- suffix order and longest previous factors


def suffix_array(data: np.ndarray) -> np.ndarray:
    """Suffix array of a byte array by prefix doubling."""
    n = len(data)
    rank, step = data.astype(np.int64) + 1, 1
    order = np.argsort(rank, kind="stable")
    while n:
        ahead = np.zeros(n, np.int64)
        ahead[:-step or None] = rank[step:] if step < n else 0
        key = rank * (max(n, 256) + 2) + ahead
        order = np.argsort(key, kind="stable")
        fresh = np.empty(n, np.int64)
        fresh[order] = np.cumsum(np.concatenate([[1], key[order][1:] != key[order][:-1]]))
        rank, step = fresh, 2 * step
        if rank.max() == n or step >= n:
            break
    return order


def previous_smaller(values: np.ndarray) -> np.ndarray:
    """Index of the nearest smaller value to the left, or -1, by pointer jumping."""
    near = np.arange(-1, len(values) - 1)
    active = np.arange(len(values))
    while len(active):
        at = near[active]
        wrong = (at >= 0) & (values[at] >= values[active])
        active = active[wrong]
        near[active] = near[near[active]]
    return near


def next_smaller(values: np.ndarray) -> np.ndarray:
    """Index of the nearest smaller value to the right, or len(values)."""
    return len(values) - 1 - previous_smaller(values[::-1])[::-1]


def _common(data: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Lengths of the common prefixes of suffix pairs."""
    out, active, n = np.zeros(len(a), np.int64), np.arange(len(a)), len(data)
    while len(active):
        x, y = a[active] + out[active], b[active] + out[active]
        fit = (x < n) & (y < n)
        fit[fit] = data[x[fit]] == data[y[fit]]
        active = active[fit]
        out[active] += 1
    return out


def longest_previous_factor(data: np.ndarray) -> np.ndarray:
    """For each position the length of the longest string there that also starts at an earlier position."""
    order = suffix_array(data)
    out = np.zeros(len(data), np.int64)
    for near in (previous_smaller(order), next_smaller(order)):
        real = np.flatnonzero((near >= 0) & (near < len(order)))
        np.maximum.at(out, order[real], _common(data, order[real], order[near[real]]))
    return out


def _word(data: np.ndarray, start: np.ndarray, at: int, take: int) -> np.ndarray:
    word = np.zeros(len(start), tn.U)
    for k in range(at, at + take):
        word <<= tn.U(8)
        word |= data[start + k]
    return word


def _least_within(values: np.ndarray, after: np.ndarray, upto: np.ndarray) -> np.ndarray:
    """min(values[after + 1 .. upto]) of non-empty ranges, from minima of runs of 1, 2, 4, ... values."""
    out, level = np.empty(len(after), values.dtype), np.frexp(upto - after)[1] - 1
    table, step = values, 0
    while len(table):
        at = np.flatnonzero(level == step)
        out[at] = np.minimum(table[after[at] + 1], table[upto[at] - (1 << step) + 1])
        if not (level > step).any():
            break
        table, step = np.minimum(table[: -(1 << step)], table[1 << step :]), step + 1
    return out


def earlier_factors(data: np.ndarray, start: np.ndarray, doc: np.ndarray, length: int, at_once: int = 1 << 30) -> np.ndarray:
    """Of each suffix the length of its longest prefix, of at most `length` bytes, that also starts in an earlier document.

    Suffixes, which all have `length` bytes, are sorted; the earlier match of each is its previous or next neighbour of a smaller
    document, and the prefix in common is the least of the common prefixes between them. More than `at_once` suffixes are dealt
    out by their first bytes and sorted part by part: matches shorter than these then read as zero.
    """
    n = len(start)
    if not n:
        return np.zeros(0, np.uint8)
    if n > at_once:
        parts = -(-n // at_once)
        part = (tn.mix(_word(data, start, 0, min(8, length))) % tn.U(parts)).astype(np.uint32)
        out = np.zeros(n, np.uint8)
        for p in range(parts):
            pick = np.flatnonzero(part == p)
            out[pick] = earlier_factors(data, start[pick], doc[pick], length)
        return out
    keys = [(_word(data, start, at, min(8, length - at)), min(8, length - at)) for at in range(0, length, 8)]
    order = np.lexsort((doc, *[word for word, _ in keys[::-1]]))
    common, open_ = np.zeros(n, np.uint8), np.ones(n, bool)  # with the suffix before
    open_[0] = False
    for word, size in keys:
        ranked = word[order]
        differ = np.zeros(n, tn.U)
        differ[1:] = ranked[1:] ^ ranked[:-1]
        equal = differ == 0
        first = np.full(n, size, np.uint8)
        for k in range(size):
            first[(differ >> tn.U(8 * (size - 1 - k))) != 0] -= 1
        common[open_] += first[open_]
        open_ &= equal
    ranked = doc[order]
    factor = np.zeros(n, np.uint8)
    here = np.arange(n)
    before, behind = previous_smaller(ranked), next_smaller(ranked)
    at = np.flatnonzero(before >= 0)
    factor[at] = _least_within(common, before[at], here[at])
    at = np.flatnonzero(behind < n)
    factor[at] = np.maximum(factor[at], _least_within(common, here[at], behind[at]))
    out = np.zeros(n, np.uint8)
    out[order] = factor
    return out


# ---- anchors and cells of a chunk


class Cells:
    """Runs of windows that share an anchor: anchor and cell hashes, first window, number of windows, document row,
    and how far the anchor is behind the first window."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, config: SuffixConfig):
        found: list[tuple[np.ndarray, ...]] = []
        for low, high in tn.slabs(offsets, config.slab_bytes):
            begin, finish = int(offsets[low]), int(offsets[high])
            for at in range(begin, max(finish, begin + 1), 32 << 20):
                stop = min(at + (32 << 20) + config.length - 1, finish)
                part = np.clip(offsets[low : high + 1], at, stop)
                got = _cells(data[at:stop], part - at, config)
                if got is not None:
                    anchor, cell, start, count, place = got
                    doc = np.searchsorted(offsets, start + at, side="right") - 1
                    found.append((anchor, cell, start + at, count, doc, place - start))
        kinds = (tn.U, tn.U, np.int64, np.int64, np.int64, np.int64)
        self.anchor, self.cell, self.start, self.count, self.doc, self.shift = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.empty(0, t) for t in kinds)

    def __len__(self) -> int:
        return len(self.anchor)


def _rolled(data: np.ndarray, length: int) -> dict[int, np.ndarray]:
    """Polynomial hashes of the strings of 1, 2, 4, ... bytes that start at each position; past the end zeros follow."""
    base = 0x9E3779B97F4A7C15
    out, n = {1: tn._PLAIN[data]}, 1
    while 2 * n <= length:
        h = out[n]
        wide = h * tn.U(pow(base, n, 1 << 64))
        wide[:-n or None] += h[n:]
        out[2 * n] = wide
        n *= 2
    return out


def _joined(parts: dict[int, np.ndarray], length: int) -> np.ndarray:
    base, at, total = 0x9E3779B97F4A7C15, 0, None
    for n in sorted(parts, reverse=True):
        if length - at >= n:
            ahead = np.zeros_like(parts[n])
            ahead[: len(ahead) - at] = parts[n][at:]
            total = ahead if total is None else total * tn.U(pow(base, n, 1 << 64)) + ahead
            at += n
    return total


def _cells(data: np.ndarray, offsets: np.ndarray, config: SuffixConfig):
    n, length = len(data), config.length
    if n < length:
        return None
    parts = _rolled(data, length)
    whole, gram = _joined(parts, length), _joined(parts, config.gram)
    del parts
    gram = tn.mix(gram)
    least = ((gram >> tn.U(26)) << tn.U(26)) | np.arange(n, dtype=tn.U)
    span, width = 1, length - config.gram + 1
    while span < width:
        step = min(span, width - span)
        least[:-step] = np.minimum(least[:-step], least[step:])
        span += step
    anchor_at = (least & tn.U((1 << 26) - 1)).astype(np.int64)
    del least
    mark = np.zeros(n + 1, np.int32)
    sizes = np.diff(offsets)
    np.add.at(mark, offsets[1:] - np.minimum(sizes, length - 1), 1)
    np.add.at(mark, offsets[1:], -1)
    window = np.flatnonzero(np.cumsum(mark[:-1]) == 0)
    if not len(window):
        return None
    anchor_at = anchor_at[window]
    fresh = np.ones(len(window), bool)
    fresh[1:] = (anchor_at[1:] != anchor_at[:-1]) | (window[1:] != window[:-1] + 1)
    head = np.flatnonzero(fresh)
    tail = np.append(head[1:], len(window)) - 1
    start, end, anchor_at = window[head], window[tail], anchor_at[head]
    cell = tn.combine(tn.combine(whole[start], whole[end]), ((end - start) << 8 | (anchor_at - start)).astype(tn.U))
    # 48 bits of each name: anchors that clash are only compared with each other in vain
    return gram[anchor_at] >> tn.U(16), cell >> tn.U(16), start, end - start + 1, anchor_at


class Chunk:
    """A chunk's documents and cells, and the lists of keys that it sends."""

    def __init__(self, payload: bytes, config: SuffixConfig):
        self.batch, self.config = packed.unpack(payload), config
        self.data, self.offsets = tn.utf8_buffers(self.batch.column("text"))
        ids = self.batch.column("doc_id")
        self.ids = np.asarray(ids.fill_null(LAST)).astype(np.int64)
        c = self.cells = Cells(self.data, self.offsets, config)
        self.cell_id = self.ids[c.doc]
        order = np.lexsort((self.cell_id, c.cell, c.anchor))
        anchor, cell, doc = c.anchor[order], c.cell[order], self.cell_id[order]
        new_anchor = np.ones(len(order), bool)
        new_anchor[1:] = anchor[1:] != anchor[:-1]
        new_cell = new_anchor.copy()
        new_cell[1:] |= cell[1:] != cell[:-1]
        self.group = np.empty(len(order), np.int64)  # of each cell: its place among the distinct cells
        self.group[order] = np.cumsum(new_cell) - 1
        heads = np.flatnonzero(new_cell)
        self.first_cell, self.first_id = order[heads], doc[heads]  # a cell of the smallest id
        self.of_anchor = (np.cumsum(new_anchor) - 1)[heads] if len(heads) else heads
        tops = np.flatnonzero(new_anchor)
        self.anchor = anchor[tops]
        ends = np.searchsorted(self.of_anchor, np.arange(len(tops) + 1))
        self.n_cells = np.diff(ends)
        self.one_cell = np.where(self.n_cells == 1, cell[tops], 0).astype(tn.U)
        self.least = np.minimum.reduceat(doc, tops) if len(tops) else doc
        self.most = np.maximum.reduceat(doc, tops) if len(tops) else doc

    def requests(self, key: int, buckets: int) -> list[tuple[int, int, int, bytes]]:
        order, at = packed.split_by_bucket(self.anchor % tn.U(buckets), buckets)
        out = []
        for b in np.flatnonzero(np.diff(at)):
            pick = order[at[b] : at[b + 1]]
            out.append((int(b), 0, key, packed.pack_arrays(*_six(self.anchor[pick]), *_six(self.one_cell[pick]), self.least[pick], self.most[pick] - self.least[pick], np.minimum(self.n_cells[pick], 65535).astype(np.uint16))))
        return out

    def settle(self, answers: list[tuple[int, bytes]], buckets: int) -> None:
        """status (0 or 1 settled, 2 cells, 3 windows) and first id of every anchor, from the answers by bucket."""
        self.status = np.zeros(len(self.anchor), np.uint8)
        self.first = self.least.copy()
        order, at = packed.split_by_bucket(self.anchor % tn.U(buckets), buckets)
        for b, raw in answers:
            status, before = packed.unpack_arrays(raw)
            pick = order[at[b] : at[b + 1]]
            self.status[pick] = status
            self.first[pick] -= before

    def segments(self) -> tuple[np.ndarray, ...]:
        """(bucket hash, start, windows, anchor's place, id, cell) of the byte strings to compare, in a fixed order."""
        kind = self.status[self.of_anchor]
        cells = np.flatnonzero(kind == 2)
        c, own = self.cells, self.first_cell[cells]
        out = [(tn.mix(self.anchor[self.of_anchor[cells]]), c.start[own], c.count[own], c.shift[own], self.first_id[cells], cells)]
        hot = np.flatnonzero(kind == 3)
        if len(hot):
            own = self.first_cell[hot]
            cell = np.repeat(hot, c.count[own])
            start = np.concatenate([np.arange(s, s + n) for s, n in zip(c.start[own], c.count[own], strict=True)])
            pieces = self.data[start[:, None] + np.arange(self.config.length)]
            name = np.array([int.from_bytes(hashlib.blake2b(p.tobytes(), digest_size=8).digest(), "little") for p in pieces], tn.U)
            out.append((name, start, np.ones(len(start), np.int64), c.start[self.first_cell[cell]] + c.shift[self.first_cell[cell]] - start, self.first_id[cell], cell))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def send(self, key: int, buckets: int) -> list[tuple[int, int, int, bytes]]:
        name, start, count, shift, ids, _ = self.segments()
        order, at = packed.split_by_bucket(name % tn.U(buckets), buckets)
        out = []
        for b in np.flatnonzero(np.diff(at)):
            pick = order[at[b] : at[b + 1]]
            size = count[pick] + self.config.length - 1
            run = np.repeat(start[pick] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())
            out.append((int(b), 0, key, packed.pack_arrays(count[pick].astype(np.uint8), shift[pick].astype(np.uint8), ids[pick], self.data[run])))
        return out

    def removed(self, answers: list[tuple[int, bytes]], buckets: int) -> np.ndarray:
        """Which bytes of the chunk go."""
        c, length = self.cells, self.config.length
        mark = np.zeros(len(self.data) + 1, np.int32)
        anchor = self.of_anchor[self.group] if len(c) else np.empty(0, np.int64)
        settled = self.status[anchor] < 2
        whole = np.where(settled, self.cell_id > self.first[anchor], self.cell_id > self.first_id[self.group])
        np.add.at(mark, c.start[whole], 1)
        np.add.at(mark, c.start[whole] + c.count[whole] - 1 + length, -1)
        name, start, count, _, _, cell = self.segments()
        if len(name):
            order, at = packed.split_by_bucket(name % tn.U(buckets), buckets)
            masks = np.zeros(len(name), tn.U)
            for b, raw in answers:
                (masks[order[at[b] : at[b + 1]]],) = packed.unpack_arrays(raw)
            # all windows of the distinct cells that have to go, then every occurrence in the cell's own first document
            seg, bit = _bits(masks)
            shift = start[seg] + bit - c.start[self.first_cell[cell[seg]]]
            by = np.argsort(cell[seg], kind="stable")
            owner, shift = cell[seg][by], shift[by]
            same = np.flatnonzero(~settled & (self.cell_id == self.first_id[self.group])) if len(c) else np.empty(0, np.int64)
            low, high = np.searchsorted(owner, self.group[same]), np.searchsorted(owner, self.group[same], side="right")
            times = high - low
            pick = np.repeat(low - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum()) if len(times) else np.empty(0, np.int64)
            places = np.repeat(c.start[same], times) + shift[pick]
            np.add.at(mark, places, 1)
            np.add.at(mark, places + length, -1)
        return np.cumsum(mark[:-1]) > 0


def _bits(masks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    found = [(np.flatnonzero((masks >> tn.U(b)) & tn.U(1)), b) for b in range(64)]
    return np.concatenate([s for s, _ in found]), np.concatenate([np.full(len(s), b) for s, b in found])


def _six(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return (values & tn.U(0xFFFFFFFF)).astype(np.uint32), (values >> tn.U(32)).astype(np.uint16)


def _resolve(config: SuffixConfig):
    def answer(bucket: int, parts: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int, bytes]]:
        got = [packed.unpack_arrays(raw) for _, _, raw in parts]
        low, high, c_low, c_high, least, spread, cells = (np.concatenate(c) for c in zip(*got, strict=True))
        anchor, cell = low.astype(tn.U) | high.astype(tn.U) << tn.U(32), c_low.astype(tn.U) | c_high.astype(tn.U) << tn.U(32)
        order = np.argsort(anchor, kind="stable")
        a, c, d = anchor[order], cell[order], least[order]
        head = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))
        sizes = np.diff(np.append(head, len(a)))
        first = np.minimum.reduceat(d, head)
        final = np.maximum.reduceat(d + spread[order], head)
        several = (np.minimum.reduceat(c, head) != np.maximum.reduceat(c, head)) | (c[head] == 0)
        total = np.add.reduceat(cells[order].astype(np.int64), head)
        status = np.where(several & (final > first), np.where(total > config.hot_cells, 3, 2), 1).astype(np.uint8)
        back = np.empty(len(a), np.int64)
        back[order] = np.repeat(np.arange(len(head)), sizes)
        out, at = [], 0
        for (_, origin, _), g in zip(parts, got, strict=True):
            pick = back[at : at + len(g[0])]
            at += len(pick)
            # a chunk without this anchor's first id learns how far before its own that is
            out.append((origin, 1, bucket, packed.pack_arrays(status[pick], g[4] - first[pick])))
        return out

    return answer


def _can_match(data: np.ndarray, at: np.ndarray, size: np.ndarray, shift: np.ndarray, ids: np.ndarray, config: SuffixConfig) -> np.ndarray:
    """Segments that can share a window with another document.

    A window holds the anchor and length - gram more bytes, so at least half of these on one side of it: two segments with a
    common window have an equal anchor with equally many bytes before it, or after it.
    """
    half = -(-(config.length - config.gram) // 2)
    out = np.zeros(len(at), bool)
    for begin, room in ((shift - half, shift >= half), (shift, size - shift >= config.gram + half)):
        who = np.flatnonzero(room)
        if not len(who):
            continue
        name = np.zeros(len(who), tn.U)
        place = (at + begin)[who]
        for k in range(config.gram + half):
            name = (name + data[place + k].astype(tn.U) + tn.U(1)) * tn.U(0x9E3779B97F4A7C15)
        name = tn.mix(name)
        order = np.argsort(name)
        head = np.flatnonzero(np.concatenate([[True], name[order][1:] != name[order][:-1]]))
        doc = ids[who][order]
        several = np.minimum.reduceat(doc, head) != np.maximum.reduceat(doc, head)
        out[who[order]] |= np.repeat(several, np.diff(np.append(head, len(order))))
    return out


def _compare(config: SuffixConfig):
    def answer(bucket: int, parts: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int, bytes]]:
        got = [packed.unpack_arrays(raw) for _, _, raw in parts]
        count, shift, ids, data = (np.concatenate(c) for c in zip(*got, strict=True))
        count = count.astype(np.int64)
        size = count + config.length - 1
        seg_at = np.concatenate([[0], np.cumsum(size)[:-1]])
        live = np.flatnonzero(_can_match(data, seg_at, size, shift.astype(np.int64), ids, config))
        seg = np.repeat(live, count[live])
        within = np.arange(len(seg)) - np.repeat(np.concatenate([[0], np.cumsum(count[live])[:-1]]), count[live])
        hit = earlier_factors(data, seg_at[seg] + within, ids[seg], config.length, config.sorted_at_once) >= config.length
        masks = np.zeros(len(count), tn.U)
        np.bitwise_or.at(masks, seg[hit], tn.U(1) << within[hit].astype(tn.U))
        out, at = [], 0
        for (_, origin, _), g in zip(parts, got, strict=True):
            out.append((origin, 2, bucket, packed.pack_arrays(masks[at : at + len(g[0])])))
            at += len(g[0])
        return out

    return answer


DIGEST = [("n_bytes", pa.int64(), T.LongType()), ("n_removed", pa.int64(), T.LongType()), ("n_spans", pa.int64(), T.LongType()), ("kept_sha256", pa.string(), T.StringType())]


def remove_repeats(docs: DataFrame, config: SuffixConfig | None = None, with_text: bool = False) -> DataFrame:
    """docs without text, plus n_bytes, n_removed, n_spans and kept_sha256; with_text: plus kept_text, of whole characters only."""
    config = config or SuffixConfig()
    names = [n for n, *_ in DIGEST] + ["kept_text"]
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"), *[c for c in docs.columns if c not in ("doc_id", "text", *names)])
    chunks, chunk_path = stored(packed.chunk_documents(docs, config.chunk_bytes), "suffix-chunks")
    buckets = packed.bucket_count(packed.total_size(chunks), config.bucket_bytes)

    def request(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, payload in zip(batch.column("key").to_pylist(), batch.column("payload"), strict=True):
                yield packed.rows(Chunk(payload.as_py(), config).requests(key, buckets))

    first, _ = stored(packed.exchange(chunks.mapInArrow(request, packed.DDL), _resolve(config)), "suffix-anchors", free=True)

    def opened(parts: list[tuple[int, int, bytes]]) -> Chunk:
        chunk = Chunk(next(raw for kind, _, raw in parts if kind == 0), config)
        chunk.settle([(origin, raw) for kind, origin, raw in parts if kind == 1], buckets)
        return chunk

    second, _ = stored(packed.exchange(packed.exchange(chunks.unionByName(first), lambda key, parts: opened(parts).send(key, buckets)), _compare(config)), "suffix-windows", free=True)
    kept = [f for f in docs.schema.fields if f.name != "text"]
    out_fields = [*kept, *(T.StructField(n, t) for n, _, t in DIGEST)] + [T.StructField("kept_text", T.StringType())] * with_text

    def finish(group: pa.Table) -> pa.Table:
        parts = sorted(zip(group.column("kind").to_pylist(), group.column("origin").to_pylist(), group.column("payload").to_pylist(), strict=True), key=lambda x: x[:2])
        chunk = opened(parts)
        gone = chunk.removed([(origin, raw) for kind, origin, raw in parts if kind == 2], buckets)
        data, offsets = chunk.data, chunk.offsets
        edge = np.zeros(len(data) + 1, bool)
        edge[offsets] = True
        begins = gone.copy()
        begins[1:] &= ~gone[:-1] | edge[1:-1]
        count = lambda flags: np.diff(np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])[offsets])
        removed = count(gone)
        digests, texts = [], []
        for k, lost in enumerate(removed):
            raw = data[offsets[k] : offsets[k + 1]]
            raw = (raw[~gone[offsets[k] : offsets[k + 1]]] if lost else raw).tobytes()
            digests.append(hashlib.sha256(raw).hexdigest())
            if with_text:
                texts.append(raw.decode("utf-8", "ignore"))
        batch = chunk.batch
        cols = [batch.column(f.name) for f in kept] + [pa.array(np.diff(offsets)), pa.array(removed), pa.array(count(begins)), pa.array(digests, pa.string())] + [pa.array(texts, pa.string())] * with_text
        del chunk, gone, data
        tn.give_back()
        return pa.Table.from_arrays(cols, names=[f.name for f in out_fields])

    result = chunks.unionByName(first).unionByName(second).groupBy("key").applyInArrow(finish, T.StructType(out_fields))
    return result


__all__ = ["SuffixConfig", "drop_path", "longest_previous_factor", "remove_repeats", "suffix_array"]
