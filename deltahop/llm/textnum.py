"""Vectorised text primitives: words, lines and n-gram hashes of many documents at once in numpy.

A word is a maximal run of bytes outside the ASCII white space 0x20 and 0x09-0x0D. All separators are ASCII,
so splitting UTF-8 bytes gives the same words as splitting code points. Hashes are 64 bits wide.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, *range(0x09, 0x0E)]] = True

# Odd multipliers of the mixing steps.
_BASE = 0x9E3779B97F4A7C15
_MIX_A = U(0xBF58476D1CE4E5B9)
_MIX_B = U(0x94D049BB133111EB)

_POWERS: dict[str, np.ndarray] = {"p": np.ones(1, U), "q": np.ones(1, U)}


def give_back() -> None:
    """Return freed memory to the system: workers are reused by later tasks, and freed arrays would stay theirs."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x ^ (x >> U(30))
    x *= _MIX_A
    x ^= x >> U(27)
    x *= _MIX_B
    x ^= x >> U(31)
    return x


def combine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Ordered hash of two hash arrays."""
    return mix(a * U(_BASE) + (b ^ (b >> U(29))) * _MIX_B + U(1))


def _byte_table(lower: bool) -> np.ndarray:
    table = mix(np.arange(1, 257, dtype=U) * U(_BASE))
    if lower:
        table[65:91] = table[97:123]
    return table


_PLAIN = _byte_table(False)
_LOWER = _byte_table(True)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64, for positions 0..n-1."""
    if len(_POWERS["p"]) < n:
        size = max(n, 1 << 16)
        for key, base in (("p", _BASE), ("q", pow(_BASE, -1, 1 << 64))):
            out = np.empty(size, U)
            out[0] = 1
            done = 1
            while done < size:
                take = min(done, size - done)
                out[done : done + take] = out[:take] * U(pow(base, done, 1 << 64))
                done += take
            _POWERS[key] = out
    return _POWERS["p"][:n], _POWERS["q"][:n]


def utf8_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary Arrow column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, starts, data = column.buffers()
    n = len(column)
    if n == 0 or starts is None:
        return np.empty(0, np.uint8), np.zeros(n + 1, np.int64)
    offsets = np.frombuffer(starts, kind)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slabs(offsets: np.ndarray, limit: int) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts hold at most `limit` bytes together; a longer text stands alone."""
    n, row = len(offsets) - 1, 0
    while row < n:
        end = int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1
        end = min(max(end, row + 1), n)
        yield row, end
        row = end


class Words:
    """Words of a slab of documents: start, end (byte positions), doc (row within the slab), hash."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, lower: bool = False):
        self.data, self.offsets = data, offsets
        self.n_docs = len(offsets) - 1
        n = len(data)
        if n == 0:
            self.start = self.end = self.doc = np.empty(0, np.int64)
            self.hash = np.empty(0, U)
            self.sep = np.empty(0, bool)
            self.first = np.zeros(self.n_docs + 1, np.int64)
            return
        self.sep = SEPARATOR[data]
        inside = ~self.sep
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        begins = inside.copy()
        begins[1:] &= self.sep[:-1] | edge[1:-1]
        finishes = inside.copy()
        finishes[:-1] &= self.sep[1:] | edge[1:-1]
        self.start = np.flatnonzero(begins)
        self.end = np.flatnonzero(finishes) + 1
        self.first = np.searchsorted(self.start, offsets)
        self.doc = np.repeat(np.arange(self.n_docs), np.diff(self.first))
        self.hash = span_hash(data, self.start, self.end, lower)

    def __len__(self) -> int:
        return len(self.start)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def code_points(self) -> np.ndarray:
        """Code points of each word."""
        lead = np.concatenate([[0], np.cumsum((self.data & 0xC0) != 0x80, dtype=np.int64)])
        return lead[self.end] - lead[self.start]

    def ngram_hash(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(first word, hash) of every window of n words that lies in one document."""
        m = len(self.hash) - n + 1
        if m <= 0:
            return np.empty(0, np.int64), np.empty(0, U)
        at = np.flatnonzero(self.doc[:m] == self.doc[n - 1 :])
        out = self.hash[at]
        for k in range(1, n):
            out = combine(out, self.hash[at + k])
        return at, out


def span_hash(data: np.ndarray, start: np.ndarray, end: np.ndarray, lower: bool = False, block: int = 1 << 19) -> np.ndarray:
    """Hash of the bytes of disjoint ascending spans, a block of bytes at a time; a longer span is summed up piece by piece."""
    total = np.empty(len(start), U)
    table, low = _LOWER if lower else _PLAIN, 0
    while low < len(start):
        begin = int(start[low])
        high = int(np.searchsorted(end, begin + block, side="right"))
        if high > low:
            finish = int(end[high - 1])
            p, q = _powers(finish - begin + 1)
            run = np.zeros(finish - begin + 1, U)
            np.cumsum(table[data[begin:finish]] * p[:-1], dtype=U, out=run[1:])
            total[low:high] = (run[end[low:high] - begin] - run[start[low:high] - begin]) * q[start[low:high] - begin]
        else:
            high, finish, sums = low + 1, int(end[low]), 0
            for at in range(begin, finish, block):
                piece = table[data[at : min(at + block, finish)]]
                sums += int((piece * _powers(len(piece))[0]).sum(dtype=U)) * pow(_BASE, at - begin, 1 << 64)
            total[low] = sums % (1 << 64)
        low = high
    return mix(total + (end - start).astype(U) * _MIX_B)


def lines(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, doc) of the newline-separated lines of each document, empty ones included."""
    breaks = np.flatnonzero(data == 10)
    n_docs = len(offsets) - 1
    owner = np.searchsorted(offsets, breaks, side="right") - 1
    start = np.concatenate([offsets[:-1], breaks + 1])
    end = np.concatenate([offsets[1:], breaks])
    doc = np.concatenate([np.arange(n_docs), owner])
    start = start[np.lexsort((start, doc))]
    end = end[np.lexsort((end, doc))]
    return start, end, np.sort(doc, kind="stable")


def repeated(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(group size, is not the first) of each key, ties in input order."""
    n = len(keys)
    if n == 0:
        return np.empty(0, np.int64), np.empty(0, bool)
    order = np.argsort(keys, kind="stable")
    ranked = keys[order]
    heads = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
    sizes = np.diff(np.append(heads, n))
    size, later = np.empty(n, np.int64), np.ones(n, bool)
    size[order] = np.repeat(sizes, sizes)
    later[order[heads]] = False
    return size, later


def per_doc(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs given by n+1 boundaries; empty runs give zero."""
    total = np.concatenate([np.zeros(1, values.dtype if values.dtype.kind == "f" else np.int64), np.cumsum(values, dtype=values.dtype if values.dtype.kind == "f" else np.int64)])
    return total[first[1:]] - total[first[:-1]]
