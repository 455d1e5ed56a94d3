"""Packed exchange: large numbers of small keys travel as a few compressed blobs instead of rows.

Documents are gathered into chunks that are written once to the shared folder, so that every later pass sees the same chunks even
after executors were lost. A pass sends each chunk's distinct keys to hash buckets and gets answers in the order of the keys.
All tables between passes have the columns (key, kind, origin, payload).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn

DDL = "key bigint, kind int, origin bigint, payload binary"
SCHEMA = pa.schema([("key", pa.int64()), ("kind", pa.int32()), ("origin", pa.int64()), ("payload", pa.binary())])
_ZSTD = pa.ipc.IpcWriteOptions(compression="zstd")


def pack(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=_ZSTD) as writer:
        writer.write_batch(batch)
    return sink.getvalue().to_pybytes()


def unpack(raw: bytes) -> pa.RecordBatch:
    table = pa.ipc.open_stream(raw).read_all().combine_chunks()
    return table.to_batches()[0] if table.num_rows else pa.RecordBatch.from_arrays([pa.array([], f.type) for f in table.schema], schema=table.schema)


def pack_arrays(*arrays: np.ndarray) -> bytes:
    """Arrays of any lengths, each as byte planes so that equal high bytes compress away."""
    out = [np.array([len(arrays)], np.int64).tobytes()]
    for a in arrays:
        planes = np.ascontiguousarray(np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.dtype.itemsize).T).tobytes()
        body = pa.Codec("zstd", 1).compress(planes, asbytes=True) if planes else b""
        out += [np.array([len(a), len(body), np.dtype(a.dtype).num], np.int64).tobytes(), body]
    return b"".join(out)


_TYPES = {np.dtype(t).num: np.dtype(t) for t in (np.uint8, np.uint16, np.uint32, np.uint64, np.int8, np.int16, np.int32, np.int64, np.float32, np.float64)}


def unpack_arrays(raw: bytes) -> list[np.ndarray]:
    (n,), at, out = np.frombuffer(raw, np.int64, 1), 8, []
    for _ in range(n):
        size, length, kind = map(int, np.frombuffer(raw, np.int64, 3, at))
        at += 24
        dtype = _TYPES[kind]
        planes = pa.decompress(raw[at : at + length], decompressed_size=size * dtype.itemsize, codec="zstd", asbytes=True) if size else b""
        out.append(np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(dtype.itemsize, size).T).view(dtype).ravel())
        at += length
    return out


def rows(items: list[tuple[int, int, int, bytes]]) -> pa.RecordBatch:
    cols = list(zip(*items, strict=True)) if items else [[], [], [], []]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, SCHEMA, strict=True)], schema=SCHEMA)


def chunk_documents(docs: DataFrame, chunk_bytes: int, make: Callable[[pa.RecordBatch], bytes] = pack, measure: str = "text") -> DataFrame:
    """Rows (key = chunk, kind 0, origin = text bytes, payload = make(documents)); to be stored before use."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seq, held, size = TaskContext.get().partitionId(), 0, [], 0

        def emit() -> pa.RecordBatch:
            whole = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            return rows([((part << 32) | seq, 0, size, make(whole))])

        for batch in batches:
            if not batch.num_rows:
                continue
            col = batch.column(measure)
            length = np.asarray(pa.compute.fill_null(pa.compute.binary_length(col), 0)).astype(np.int64)
            ends = np.concatenate([[0], np.cumsum(length)])
            low = 0
            while low < batch.num_rows:
                high = int(np.searchsorted(ends, ends[low] + chunk_bytes - size, side="right")) - 1
                high = min(max(high, low + (size == 0)), batch.num_rows)
                if high > low:
                    held.append(batch.slice(low, high - low))
                    size += int(ends[high] - ends[low])
                    low = high
                if low < batch.num_rows:
                    yield emit()
                    seq, held, size = seq + 1, [], 0
        if held:
            yield emit()
        held = []
        tn.give_back()

    return docs.mapInArrow(run, DDL)


def exchange(sent: DataFrame, answer: Callable[[int, list[tuple[int, int, bytes]]], list[tuple[int, int, int, bytes]]]) -> DataFrame:
    """Group rows by key; answer(key, [(kind, origin, payload)]) gives the new rows."""

    def run(group: pa.Table) -> pa.Table:
        key = group.column("key")[0].as_py()
        parts = sorted(zip(group.column("kind").to_pylist(), group.column("origin").to_pylist(), group.column("payload").to_pylist(), strict=True), key=lambda x: x[:2])
        out = pa.Table.from_batches([rows(answer(key, parts))])
        tn.give_back()
        return out

    return sent.groupBy("key").applyInArrow(run, DDL)


def bucket_count(total_bytes: int, per_bucket: int, least: int = 1) -> int:
    return max(least, -(-int(total_bytes or 0) // per_bucket))


def total_size(chunks: DataFrame) -> int:
    return chunks.agg(F.sum("origin")).first()[0] or 0


def split_by_bucket(bucket: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, starts): order[starts[b]:starts[b+1]] are the entries of bucket b, in their order."""
    rows = max(0, len(bucket) - 1).bit_length()
    key = np.sort(bucket.astype(tn.U) << tn.U(rows) | np.arange(len(bucket), dtype=tn.U))  # bucket and row as one number
    return (key & tn.U((1 << rows) - 1)).astype(np.int64), np.searchsorted(key >> tn.U(rows), np.arange(n + 1, dtype=tn.U))
