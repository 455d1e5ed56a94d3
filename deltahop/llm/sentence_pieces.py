"""SentencePiece encoding and decoding by suffix-array matching.

The distinct words of a batch are concatenated and their suffixes sorted; a binary search for every piece of the vocabulary gives
its range of occurrences; each occurrence is an edge between two places of a word. Sorted by their ends, the edges are relaxed
from left to right for all words at once.

Two relaxations are offered. For unigram scores the best sum wins (`relax_scores`). The public vocabulary is a merge
vocabulary, whose encoding isn't a best sum; there an edge is taken if its piece can follow the last piece of the encoding
of the text before it, which holds for exactly one edge at every place (`relax_merges`). Two pieces can stand side by side if
no merge across their border comes before the merges that made them; this is read off the last merges of both. Characters without
a piece are bytes. Results equal those of the library's own encoder.

A place that no occurrence of a piece crosses is never merged over, so words are cut there before the relaxation; this keeps texts without
spaces in short segments. Words with runs of spaces, whose pieces all have one priority, are merged one by one with a heap, and so are
segments over `longest` bytes (one character repeated thousands of times, say), whose relaxation would take a step a byte.
Defined results: null and empty texts have no tokens; decoding gives the text back unless it holds U+2581, which stands for a
space; repeated rows repeat; other columns are ignored.
"""

from __future__ import annotations

import heapq
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn
from deltahop.llm.token_table import MemoEncoder

BIG = np.int64(1 << 40)
NORMAL, BYTE = 1, 6  # kinds of pieces in the model file


def _wire(raw: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field, value) of a protocol-buffer message."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            b = raw[at]
            at += 1
            value |= (b & 127) << shift
            if b < 128:
                return value, at
            shift += 7

    at = 0
    while at < len(raw):
        key, at = varint(at)
        kind = key & 7
        if kind == 0:
            value, at = varint(at)
        else:
            size, at = varint(at) if kind == 2 else ({1: 8, 5: 4}[kind], at)
            value = raw[at : at + size]
            at += size
        yield key >> 3, value


@dataclass
class Vocabulary:
    """Pieces as bytes with a space for U+2581, and what merging needs: ranks, last merges and the pairs that merge."""

    pieces: list[bytes]
    scores: np.ndarray
    byte_id: np.ndarray
    usable: np.ndarray
    rank: np.ndarray
    left: np.ndarray
    right: np.ndarray
    pair_key: np.ndarray
    pair_rank: np.ndarray

    @property
    def unknown(self) -> int:
        return len(self.pieces)


def load_vocabulary(name: str = "piece_bpe_32k.model") -> Vocabulary:
    """Read a model file; runs once on the driver and travels to the tasks as arrays."""
    import os

    import public_tokenizers

    with open(name if os.path.sep in name else public_tokenizers.path(name), "rb") as source:
        entries = [dict(_wire(v)) for f, v in _wire(source.read()) if f == 1]
    text = [e[1].decode() for e in entries]
    kind = [e.get(3, NORMAL) for e in entries]
    scores = np.array([struct.unpack("<f", e.get(2, b"\0\0\0\0"))[0] for e in entries])
    byte_id = np.zeros(256, np.int64)
    for i, k in enumerate(kind):
        if k == BYTE:
            byte_id[int(text[i][1:-1], 16)] = i
    n = len(text)
    pieces = [t.replace("▁", " ").encode() if k == NORMAL else b"" for t, k in zip(text, kind, strict=True)]
    ids = {t.replace("▁", " "): i for i, (t, k) in enumerate(zip(text, kind, strict=True)) if k == NORMAL}
    # a merge's rank is its place by score; single characters exist from the start
    place = np.unique(-scores, return_inverse=True)[1] + 1
    rank = np.zeros(n + 1, np.int64)
    keys, ranks = [], []
    for t, i in ids.items():
        if len(t) > 1:
            rank[i] = place[i]
            for cut in range(1, len(t)):
                a, b = ids.get(t[:cut]), ids.get(t[cut:])
                if a is not None and b is not None:
                    keys.append(a * (n + 1) + b)
                    ranks.append(place[i])
    order = np.argsort(keys)
    left, right = np.full(n + 1, -1, np.int64), np.full(n + 1, -1, np.int64)
    usable = np.zeros(n, bool)
    for t, i in ids.items():
        if len(t) == 1:
            usable[i] = True
            continue
        symbols, last = list(t), None
        while len(symbols) > 1:
            best = min(((place[ids[a + b]], k) for k, (a, b) in enumerate(zip(symbols, symbols[1:], strict=False)) if a + b in ids), default=None)
            if best is None:
                break
            k = best[1]
            last = (symbols[k], symbols[k + 1])
            symbols[k : k + 2] = ["".join(last)]
        if len(symbols) == 1:
            usable[i], left[i], right[i] = True, ids.get(last[0], -1), ids.get(last[1], -1)
    usable &= left[:n] + right[:n] >= -2
    return Vocabulary(pieces, scores, byte_id, usable, rank, left, right, np.array(keys, np.int64)[order], np.array(ranks, np.int64)[order])


def can_follow(v: Vocabulary, one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Whether merging the joined text of two pieces gives these two pieces again, for arrays of piece ids."""
    out = np.ones(len(one), bool)
    a, b, limit, at = one.copy(), two.copy(), np.full(len(one), BIG), np.arange(len(one))
    while len(at):
        key = a * (v.unknown + 1) + b
        spot = np.minimum(np.searchsorted(v.pair_key, key), len(v.pair_key) - 1)
        merged = np.where(v.pair_key[spot] == key, v.pair_rank[spot], BIG)
        wrong = merged < limit
        out[at[wrong]] = False
        ra, rb = v.rank[a], v.rank[b]
        go = ~wrong & ((ra > 0) | (rb > 0))
        a, b, ra, rb, at = a[go], b[go], ra[go], rb[go], at[go]
        # take back the later of both merges; of equal ranks the right one came later
        first = ra > rb
        limit = np.where(first, ra, rb + 1)
        a, b = np.where(first, v.right[a], a), np.where(first, b, v.left[b])
    return out


def merge_one(v: Vocabulary, ids: dict[bytes, int], word: str) -> list[int]:
    """Piece ids of one word by repeatedly merging the pair of best rank, leftmost first."""
    symbols = list(word)
    raw = [s.encode() for s in symbols]
    after, before = list(range(1, len(raw) + 1)), list(range(-1, len(raw) - 1))
    heap: list[tuple[float, int, bytes]] = []

    def offer(k: int) -> None:
        j = after[k]
        if 0 <= k and j < len(raw):
            joined = raw[k] + raw[j]
            if joined in ids:
                heapq.heappush(heap, (-v.scores[ids[joined]], k, joined))

    for k in range(len(raw) - 1):
        offer(k)
    while heap:
        _, k, joined = heapq.heappop(heap)
        j = after[k] if raw[k] else len(raw)
        if not raw[k] or j >= len(raw) or raw[k] + raw[j] != joined:
            continue
        raw[k], raw[j] = joined, b""
        after[k] = after[j]
        if after[k] < len(raw):
            before[after[k]] = k
        offer(k)
        if before[k] >= 0:
            offer(before[k])
    out: list[int] = []
    for r in raw:
        if r:
            out += [ids[r]] if r in ids else v.byte_id[np.frombuffer(r, np.uint8)].tolist()
    return out


class SuffixIndex:
    """Suffixes of the words of a text in order, by their first 16 bytes; past a word's end come zeros."""

    def __init__(self, data: np.ndarray, start: np.ndarray, end: np.ndarray):
        n = len(data)
        stop = np.repeat(end, end - start)
        pad = np.concatenate([data, np.zeros(16, np.uint8)])
        at = np.arange(n)
        words = []
        for low in (0, 8):
            word = np.zeros(n, tn.U)
            for k in range(low, low + 8):
                word = (word << tn.U(8)) | np.where(at + k < stop, pad[k : n + k], 0).astype(tn.U)
            words.append(word)
        self.data, self.stop = pad, stop
        self.order = np.lexsort((words[1], words[0]))
        self.k0 = words[0][self.order]
        k1 = words[1][self.order]
        self.u0, r0 = np.unique(self.k0, return_inverse=True)
        self.u1, r1 = np.unique(k1, return_inverse=True)
        self.both = r0.astype(np.int64) * (len(self.u1) + 1) + r1

    def ranges(self, p0: np.ndarray, p1: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """[low, high) in suffix order of patterns given by their first two zero-padded words and sizes."""
        full = ~tn.U(0)
        with np.errstate(over="ignore"):
            tail0 = np.where(size >= 8, tn.U(0), full >> (np.minimum(size, 7) * 8).astype(tn.U))
            tail1 = np.where(size >= 16, tn.U(0), full >> (np.clip(size - 8, 0, 7) * 8).astype(tn.U))
        low, high = np.searchsorted(self.k0, p0), np.searchsorted(self.k0, p0 | tail0, side="right")
        long = np.flatnonzero(size > 8)
        r0 = np.searchsorted(self.u0, p0[long])
        there = r0 < len(self.u0)
        there[there] = self.u0[r0[there]] == p0[long][there]
        base = r0 * (len(self.u1) + 1)
        low[long] = np.searchsorted(self.both, base + np.searchsorted(self.u1, p1[long]))
        high[long] = np.where(there, np.searchsorted(self.both, base + np.searchsorted(self.u1, p1[long] | tail1[long], side="right")), low[long])
        return low, np.maximum(low, high)


class Matcher:
    """Edges of a batch of words: start, end and piece of every occurrence of every piece."""

    def __init__(self, v: Vocabulary):
        self.v = v
        self.ids = np.flatnonzero(v.usable)
        padded = [v.pieces[i][:16].ljust(16, b"\0") for i in self.ids]
        words = np.frombuffer(b"".join(padded), ">u8").reshape(-1, 2).astype(tn.U)
        self.p0, self.p1 = np.ascontiguousarray(words[:, 0]), np.ascontiguousarray(words[:, 1])
        self.size = np.array([len(v.pieces[i]) for i in self.ids])

    def edges(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        index = SuffixIndex(data, start, end)
        low, high = index.ranges(self.p0, self.p1, self.size)
        times = high - low
        run = np.repeat(low - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum())
        begin, which = index.order[run], np.repeat(np.arange(len(times)), times)
        long = np.flatnonzero(self.size[which] > 16)
        if len(long):
            fits = np.ones(len(begin), bool)
            fits[long] = [begin[e] + self.size[which[e]] <= index.stop[begin[e]] and index.data[begin[e] : begin[e] + self.size[which[e]]].tobytes() == self.v.pieces[self.ids[which[e]]] for e in long]
            begin, which = begin[fits], which[fits]
        return begin, begin + self.size[which], self.ids[which]


def _with_characters(v: Vocabulary, data, edges):
    """Adds an edge of the unknown piece for every character without a piece of its own."""
    begin, finish, piece = edges
    lead = np.flatnonzero((data & 0xC0) != 0x80)
    size = np.diff(np.append(lead, len(data)))
    own = np.zeros(len(data) + 1, np.int64)
    single = v.rank[piece] == 0
    own[begin[single]] = 1
    bare = own[lead] == 0
    return np.concatenate([begin, lead[bare]]), np.concatenate([finish, (lead + size)[bare]]), np.concatenate([piece, np.full(bare.sum(), v.unknown)])


def _by_end(begin, finish, piece, word_start):
    """Edges by the end's distance from the word's start, then end, then longest first; with run bounds for each distance."""
    far = finish - word_start[begin]
    order = np.lexsort((begin, finish, far))
    begin, finish, piece, far = begin[order], finish[order], piece[order], far[order]
    head = np.concatenate([np.ones(min(1, len(far)), bool), finish[1:] != finish[:-1]])
    first = np.flatnonzero(head)
    turn = np.arange(len(far)) - np.repeat(first, np.diff(np.append(first, len(far))))
    bounds = np.flatnonzero(np.concatenate([np.ones(min(1, len(far)), bool), far[1:] != far[:-1], np.ones(min(1, len(far)), bool)]))
    return begin, finish, piece, turn, bounds


def relax_merges(v: Vocabulary, data, start, end, edges) -> np.ndarray:
    """For every place the piece that ends the encoding of its word up to there (at index place), -1 where none does."""
    word_start = np.repeat(start, end - start)
    begin, finish, piece, turn, bounds = _by_end(*edges, word_start)
    last = np.full(len(data) + 1, -1, np.int64)
    whole = begin == word_start[begin]
    # places are named by their end, so the end of one word and the start of the next don't meet: starts are never read
    for low, high in zip(bounds[:-1], bounds[1:], strict=True):
        for k in range(int(turn[low:high].max()) + 1):
            e = low + np.flatnonzero(turn[low:high] == k)
            e = e[last[finish[e]] < 0]
            if len(e):
                good = whole[e].copy()
                rest = np.flatnonzero(~good)
                good[rest] = can_follow(v, last[begin[e[rest]]], piece[e[rest]])
                e = e[good]
                last[finish[e]] = piece[e]
    return last


def relax_scores(v: Vocabulary, data, start, end, edges, unknown_score: float = -1e6) -> np.ndarray:
    """As relax_merges, for unigram scores: the last piece of the best-scored segmentation, of equal ones the longest."""
    word_start = np.repeat(start, end - start)
    begin, finish, piece, turn, bounds = _by_end(*edges, word_start)
    score = np.append(v.scores, unknown_score)
    last, best = np.full(len(data) + 1, -1, np.int64), np.full(len(data) + 1, -np.inf)
    whole = begin == word_start[begin]
    for low, high in zip(bounds[:-1], bounds[1:], strict=True):
        for k in range(int(turn[low:high].max()) + 1):
            e = low + np.flatnonzero(turn[low:high] == k)
            total = np.where(whole[e], 0.0, best[begin[e]]) + score[piece[e]]
            better = total > best[finish[e]]
            last[finish[e[better]]], best[finish[e[better]]] = piece[e[better]], total[better]
    return last


def _cut_uncrossed(text, low, high, edges):
    """(starts, ends) of the segments of words between places that no edge crosses."""
    begin, finish, _ = edges
    step = np.zeros(len(text) + 1, np.int32)
    np.add.at(step, begin + 1, 1)  # an edge crosses the places after its begin and before its end
    np.add.at(step, finish, -1)
    cut = np.cumsum(step[:-1]) == 0
    cut[low] = True
    start = np.flatnonzero(cut)
    return start, np.append(start[1:], len(text))


class SentencePieceEncoder(MemoEncoder):
    def __init__(self, v: Vocabulary, relax=relax_merges, memo_size: int = 1_000_000, longest: int = 4000, at_once: int = 96 << 10):
        super().__init__(2 if v.unknown < 1 << 16 else 4, memo_size)
        self.v, self.matcher, self.relax, self.longest, self.at_once = v, Matcher(v), relax, longest, at_once
        self.by_bytes = {v.pieces[i]: int(i) for i in np.flatnonzero([len(p) > 0 for p in v.pieces])}
        self.length = np.array([len(p) for p in v.pieces])

    def pieces(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cut = data == 32
        cut[1:] &= data[:-1] != 32
        cut[offsets[:-1][np.diff(offsets) > 0]] = True
        start = np.flatnonzero(cut)
        return start, np.zeros(len(start), bool)

    def encode_new(self, data, start, end, alone):
        if self.relax is relax_merges:
            by_heap = (end - start > 1) & (data[start] == 32) & (data[np.minimum(start + 1, len(data) - 1)] == 32)
        else:
            by_heap = np.zeros(len(start), bool)
        found = [self._merged(data, start, end, np.flatnonzero(by_heap))]
        rest = np.flatnonzero(~by_heap)
        reached = np.cumsum((end - start)[rest])
        at = 0
        while at < len(rest):
            before = int(reached[at - 1]) if at else 0
            upto = max(at + 1, int(np.searchsorted(reached, before + self.at_once, side="right")))
            found.append(self._relaxed(data, start, end, rest[at:upto]))
            at = upto
        order, counts, ids = zip(*found, strict=True)
        return np.concatenate(order).astype(np.int64), np.concatenate(counts).astype(np.int64), np.concatenate(ids)

    def _merged(self, data, start, end, which):
        lists = [merge_one(self.v, self.by_bytes, data[start[k] : end[k]].tobytes().decode()) for k in which]
        return which, np.array([len(x) for x in lists], np.int64), np.array([i for x in lists for i in x], self.kind)

    def _relaxed(self, data, start, end, which):
        size = (end - start)[which]
        high = np.cumsum(size)
        low = high - size
        text = data[np.repeat(start[which] - low, size) + np.arange(high[-1])]
        edges = _with_characters(self.v, text, self.matcher.edges(text, low, high))
        if self.relax is not relax_merges:
            counts, ids = self._read(text, low, high, self.relax(self.v, text, low, high, edges))
            return which, counts, ids
        seg_low, seg_high = _cut_uncrossed(text, low, high, edges)
        lengthy = np.flatnonzero(seg_high - seg_low > self.longest)
        if len(lengthy):
            inside = np.zeros(len(text), bool)
            for k in lengthy:
                inside[seg_low[k] : seg_high[k]] = True
            edges = tuple(e[~inside[edges[0]]] for e in edges)
        last = self.relax(self.v, text, seg_low, seg_high, edges)
        easy = np.setdiff1d(np.arange(len(seg_low)), lengthy)
        counts, parts = np.zeros(len(seg_low), np.int64), []
        counts[easy], ids = self._read(text, seg_low[easy], seg_high[easy], last) if len(easy) else (0, np.empty(0, self.kind))
        if len(lengthy):
            done = np.concatenate([[0], np.cumsum(counts)])
            at = 0
            for k, own in zip(lengthy.tolist(), (self._merged(text, seg_low, seg_high, [k])[2] for k in lengthy), strict=True):
                parts += [ids[at : done[k]], own]
                at, counts[k] = done[k], len(own)
            ids = np.concatenate([*parts, ids[at:]])
        return which, np.add.reduceat(counts, np.searchsorted(seg_low, low)), ids

    def _read(self, text, low, high, last):
        """(tokens per word, ids): follow the last pieces back from the words' ends."""
        lead = (text & 0xC0) != 0x80
        behind = np.maximum.accumulate(np.where(lead, np.arange(len(text)), 0))  # first byte of the character at a byte
        at, word, steps = high.copy(), np.arange(len(low)), []
        while len(at):
            piece = last[at]
            size = np.where(piece < self.v.unknown, self.length[np.minimum(piece, self.v.unknown - 1)], at - behind[at - 1])
            steps.append((word, at - size, piece, size))
            at = at - size
            go = at > low[word]
            at, word = at[go], word[go]
        word, begin, piece, size = (np.concatenate(c) for c in zip(*steps, strict=True))
        by = np.argsort(begin, kind="stable")
        word, begin, piece, size = word[by], begin[by], piece[by], size[by]
        times = np.where(piece == self.v.unknown, size, 1)
        which = np.repeat(np.arange(len(piece)), times)
        nth = np.arange(len(which)) - np.repeat(np.cumsum(times) - times, times)
        ids = np.where(piece[which] == self.v.unknown, self.v.byte_id[text[begin[which] + nth]], piece[which])
        return np.bincount(word, weights=times, minlength=len(low)).astype(np.int64), ids.astype(self.kind)


def with_prefix(column: pa.Array) -> pa.Array:
    """Texts as the encoder takes them: a space before every text that isn't empty, U+2581 read as a space."""
    text = pc.replace_substring(pc.fill_null(column, ""), "▁", " ")
    return pc.if_else(pc.equal(pc.binary_length(text), 0), text, pc.binary_join_element_wise(" ", text, ""))


class Decoder:
    """Texts of id sequences, vectorised over a batch."""

    def __init__(self, v: Vocabulary):
        parts = list(v.pieces)
        for b, i in enumerate(v.byte_id.tolist()):
            parts[i] = bytes([b])
        self.size = np.array([len(p) for p in parts])
        self.at = np.cumsum(self.size) - self.size
        self.bytes = np.frombuffer(b"".join(parts), np.uint8)

    def __call__(self, ids: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(bytes, offsets) of the documents, each with the leading space that encoding added."""
        size = self.size[ids]
        before = np.concatenate([[0], np.cumsum(size)])
        return self.bytes[np.repeat(self.at[ids] - before[:-1], size) + np.arange(before[-1])], before[bounds]


_ENCODERS: dict[int, SentencePieceEncoder] = {}


def _encoder(v: Vocabulary) -> SentencePieceEncoder:
    """The encoder of this Python worker for a vocabulary; its memo outlives a task."""
    key = zlib.crc32(v.pair_key.tobytes(), v.unknown)
    if key not in _ENCODERS:
        _ENCODERS[key] = SentencePieceEncoder(v)
    return _ENCODERS[key]


def encode_documents(docs: DataFrame, model: str = "piece_bpe_32k.model", slab_bytes: int = 512 << 10, with_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_crc32, round_trip[, ids]): encode whole texts, decode the ids and compare."""
    v = load_vocabulary(model)
    names = ["doc_id", "n_tokens", "ids_crc32", "round_trip"] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, decode = _encoder(v), Decoder(v)
        for batch in batches:
            source, source_at = tn.utf8_buffers(batch.column("text"))
            for low, high in tn.slabs(source_at, slab_bytes):
                data, cut = tn.utf8_buffers(with_prefix(batch.column("text").slice(low, high - low)))
                ids, bounds = encode(data, cut)
                text, at = decode(ids, bounds)
                crc = [zlib.crc32(ids[bounds[k] : bounds[k + 1]].astype("<u4").tobytes()) for k in range(high - low)]
                same = [np.array_equal(text[at[k] + (at[k + 1] > at[k]) : at[k + 1]], source[source_at[low + k] : source_at[low + k + 1]]) for k in range(high - low)]
                cols = [batch.column("doc_id").slice(low, high - low), pa.array(np.diff(bounds)), pa.array(crc, pa.int64()), pa.array(same)]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(cols, names=names)
            tn.give_back()

    ddl = "doc_id bigint, n_tokens bigint, ids_crc32 bigint, round_trip boolean" + ", ids array<int>" * with_ids
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, ddl)
