"""Token-ID / binary output: sorted-string-table shards of token ids keyed by document.

Documents are dealt out by ranges of doc_id and sorted; each task encodes its texts and writes shard files. A shard is

    data blocks    entries (shared key bytes, new key bytes, value bytes as varints, key rest, value), whole key
                   every `restart` entries, restart offsets and their count at the end; zstd, then crc32
    index block    last key, offset and size of every data block
    filter block   Bloom filter over the keys
    footer         offsets and sizes of both, document and token counts, id width, magic (fixed 64 bytes)

so a lookup reads footer, filter and index once, then one block by binary search. Keys are the order-preserving 8 bytes of
doc_id; a null doc_id has the empty key and comes first. A manifest table lists the files of tasks that succeeded, so
files of lost or repeated task attempts are never read.

Defined results: null and empty texts hold the end id alone; repeated ids are all kept, ordered by text; an empty table
gives a manifest without rows; other columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn
from deltahop.llm.workdir import fresh_path, stored

MAGIC = b"DHSSTBL1"
FOOTER = struct.Struct("<QQQQQQI4x8s")
_CODEC = "zstd"


def encode_key(doc_id: int | None) -> bytes:
    return b"" if doc_id is None else struct.pack(">Q", (doc_id + (1 << 63)) & ((1 << 64) - 1))


def decode_key(key: bytes) -> int | None:
    return None if not key else struct.unpack(">Q", key)[0] - (1 << 63)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(raw: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = raw[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


class Bloom:
    """Bit array with k positions a key, from two independent hashes."""

    def __init__(self, bits: np.ndarray, k: int = 7):
        self.bits, self.k = bits, k

    @staticmethod
    def _hash(key: bytes) -> tuple[int, int]:
        a, b = struct.unpack("<QQ", hashlib.blake2b(key, digest_size=16).digest())
        return a, b | 1

    @classmethod
    def of(cls, keys: list[bytes], per_key: int = 10) -> Bloom:
        bits = np.zeros(max(64, (len(keys) * per_key + 7) // 8 * 8), np.uint8)
        for key in keys:
            a, b = cls._hash(key)
            bits[[(a + i * b) % len(bits) for i in range(7)]] = 1
        return cls(bits)

    def __contains__(self, key: bytes) -> bool:
        a, b = self._hash(key)
        return all(self.bits[(a + i * b) % len(self.bits)] for i in range(self.k))

    def dump(self) -> bytes:
        return np.packbits(self.bits).tobytes()

    @classmethod
    def load(cls, raw: bytes) -> Bloom:
        return cls(np.unpackbits(np.frombuffer(raw, np.uint8)))


class ShardWriter:
    """Appends entries in key order to an open output stream."""

    def __init__(self, sink, width: int, block_bytes: int = 64 << 10, restart: int = 16):
        self.sink, self.width, self.block_bytes, self.restart = sink, width, block_bytes, restart
        self.at = self.tokens = self.docs = 0
        self.keys: list[bytes] = []
        self.index: list[tuple[bytes, int, int]] = []
        self._begin()

    def _begin(self) -> None:
        self.block, self.restarts, self.n, self.last = bytearray(), [], 0, b""

    def add(self, key: bytes, value: bytes) -> None:
        shared = 0
        if self.n % self.restart == 0:
            self.restarts.append(len(self.block))
        else:
            most = min(len(key), len(self.last))
            while shared < most and key[shared] == self.last[shared]:
                shared += 1
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.last, self.n = key, self.n + 1
        self.keys.append(key)
        self.docs += 1
        self.tokens += len(value) // self.width
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _write(self, raw: bytes) -> tuple[int, int]:
        packed = struct.pack("<Q", len(raw)) + pa.compress(raw, codec=_CODEC, asbytes=True)
        packed += struct.pack("<I", zlib.crc32(packed))
        self.sink.write(packed)
        self.at += len(packed)
        return self.at - len(packed), len(packed)

    def _flush(self) -> None:
        if self.n:
            raw = bytes(self.block) + struct.pack(f"<{len(self.restarts)}Q", *self.restarts) + struct.pack("<I", len(self.restarts))
            self.index.append((self.last, *self._write(raw)))
            self._begin()

    def close(self) -> None:
        self._flush()
        index = self._write(b"".join(_varint(len(k)) + k + _varint(a) + _varint(n) for k, a, n in self.index))
        bloom = self._write(Bloom.of(self.keys).dump())
        self.sink.write(FOOTER.pack(*index, *bloom, self.docs, self.tokens, self.width, MAGIC))


def _unpacked(raw: bytes) -> bytes:
    if zlib.crc32(raw[:-4]) != struct.unpack("<I", raw[-4:])[0]:
        raise ValueError("a block's check sum differs")
    (size,) = struct.unpack("<Q", raw[:8])
    return pa.decompress(raw[8:-4], decompressed_size=size, codec=_CODEC, asbytes=True) if size else b""


class ShardReader:
    """Reads a shard through a random-access file."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        index_at, index_n, bloom_at, bloom_n, self.n_docs, self.n_tokens, self.width, magic = FOOTER.unpack(self._at(size - FOOTER.size, FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard of this format")
        self._bloom = (bloom_at, bloom_n)
        raw, at = _unpacked(self._at(index_at, index_n)), 0
        self.last, self.blocks = [], []
        while at < len(raw):
            n, at = _read_varint(raw, at)
            key = raw[at : at + n]
            offset, at = _read_varint(raw, at + n)
            length, at = _read_varint(raw, at)
            self.last.append(key)
            self.blocks.append((offset, length))

    def _at(self, offset: int, n: int) -> bytes:
        self.source.seek(offset)
        return self.source.read(n)

    @staticmethod
    def _entries(raw: bytes, at: int, end: int) -> Iterator[tuple[bytes, bytes]]:
        key = b""
        while at < end:
            shared, at = _read_varint(raw, at)
            rest, at = _read_varint(raw, at)
            size, at = _read_varint(raw, at)
            key = key[:shared] + raw[at : at + rest]
            at += rest
            yield key, raw[at : at + size]
            at += size

    def _block(self, k: int) -> tuple[bytes, list[int], int]:
        raw = _unpacked(self._at(*self.blocks[k]))
        (n,) = struct.unpack("<I", raw[-4:])
        end = len(raw) - 4 - 8 * n
        return raw, list(struct.unpack(f"<{n}Q", raw[end:-4])), end

    def scan(self) -> Iterator[tuple[bytes, bytes]]:
        for k in range(len(self.blocks)):
            raw, _, end = self._block(k)
            yield from self._entries(raw, 0, end)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """Token ids of every document with this key, by filter, index and binary search within blocks."""
        key, out = encode_key(doc_id), []
        if not hasattr(self, "bloom"):
            self.bloom = Bloom.load(_unpacked(self._at(*self._bloom)))
        if key not in self.bloom:
            return out
        for k in range(bisect.bisect_left(self.last, key), len(self.blocks)):
            raw, restarts, end = self._block(k)
            whole = [next(self._entries(raw, r, end))[0] for r in restarts] if len(restarts) < 8 else _Keys(raw, restarts, end)
            first = max(0, bisect.bisect_left(whole, key) - 1)
            passed = False
            for found, value in self._entries(raw, restarts[first], end):
                if found == key:
                    out.append(np.frombuffer(value, f"<u{self.width}"))
                elif found > key:
                    passed = True
                    break
            if passed:
                break
        return out


class _Keys:
    """The restart keys of a block, decoded when looked at."""

    def __init__(self, raw: bytes, restarts: list[int], end: int):
        self.raw, self.restarts, self.end = raw, restarts, end

    def __len__(self) -> int:
        return len(self.restarts)

    def __getitem__(self, i: int) -> bytes:
        return next(ShardReader._entries(self.raw, self.restarts[i], self.end))[0]


class MemoEncoder:
    """Encodes texts as the joined encodings of their pieces, each distinct piece once.

    `pieces` cuts texts and `encode_new` encodes cut-out byte ranges. Pieces are told apart by 64-bit hashes; the memo is bounded
    and starts anew when full.
    """

    def __init__(self, width: int, memo_size: int):
        self.kind, self.memo_size = np.dtype(f"<u{width}"), memo_size
        self._clear()

    def _clear(self) -> None:
        self.known = np.empty(0, tn.U)
        self.at, self.size = np.empty(0, np.int64), np.empty(0, np.int64)
        self.ids, self.used = np.empty(1 << 16, self.kind), 0

    def pieces(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(starts, alone): first byte of every piece, and which pieces stand at an end of their text."""
        raise NotImplementedError

    def encode_new(self, data, start, end, alone) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(order, counts, ids): ids of the pieces one after another in some order, and how many each has."""
        raise NotImplementedError

    def __call__(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, bounds): the ids of document k are ids[bounds[k]:bounds[k+1]]."""
        if not len(data):
            return np.empty(0, self.kind), np.zeros(len(offsets), np.int64)
        if len(self.known) > self.memo_size:
            self._clear()
        start, alone = self.pieces(data, offsets)
        end = np.append(start[1:], len(data))
        distinct, sample, place = np.unique(tn.span_hash(data, start, end), return_index=True, return_inverse=True)
        spot = np.searchsorted(self.known, distinct)
        hit = spot < len(self.known)
        hit[hit] = self.known[spot[hit]] == distinct[hit]
        new = np.flatnonzero(~hit)
        if len(new):
            order, counts, found = self.encode_new(data, start[sample[new]], end[sample[new]], alone[sample[new]])
            self._remember(distinct[new], spot[new], order, counts, found)
            spot = np.searchsorted(self.known, distinct)
        at, size = self.at[spot][place], self.size[spot][place]
        before = np.concatenate([[0], np.cumsum(size)])
        ids = self.ids[np.repeat(at - before[:-1], size) + np.arange(before[-1])]
        return ids, before[np.searchsorted(start, offsets)]

    def _remember(self, name, spot, order, counts, found) -> None:
        while self.used + len(found) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.empty(len(self.ids), self.kind)])
        self.ids[self.used : self.used + len(found)] = found
        at, size = np.empty(len(name), np.int64), np.empty(len(name), np.int64)
        at[order], size[order] = self.used + np.cumsum(counts) - counts, counts
        self.used += len(found)
        self.known, self.at, self.size = np.insert(self.known, spot, name), np.insert(self.at, spot, at), np.insert(self.size, spot, size)


class PieceEncoder(MemoEncoder):
    """Byte-level encoder that asks the library once for each distinct piece of text, many documents at a time.

    The library's pattern starts a new token group at every space between two characters that aren't white space, so the
    encodings of the pieces between such places join to the encoding of the whole text. New pieces are encoded joined to long strings and told apart by the byte lengths of their tokens; the first and the
    last piece of a text, which other pieces could merge with, are encoded alone.
    """

    def __init__(self, tokenizer, width: int, memo_size: int = 3_000_000, joined: int = 1 << 14):
        super().__init__(width, memo_size)
        self.tokenizer, self.joined = tokenizer, joined
        vocabulary = tokenizer.get_vocab(with_added_tokens=True)
        self.token_bytes = np.zeros(max(vocabulary.values()) + 1, np.int64)
        for token, i in vocabulary.items():
            self.token_bytes[i] = len(token)

    def pieces(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(data)
        pad = np.concatenate([np.zeros(3, np.uint8), data, np.zeros(3, np.uint8)])
        space = np.flatnonzero(data == 32) + 3
        # white space beyond ASCII: two bytes C2 85 and C2 A0, three bytes led by E1, E2 or E3 (no cut near any of those leads)
        b1, b2, b3 = pad[space - 1], pad[space - 2], pad[space - 3]
        a1, a2 = pad[space + 1], pad[space + 2]
        wide = (np.uint8(0xE1), np.uint8(0xE3))
        before = _WHITE[b1] | ((b2 == 0xC2) & ((b1 == 0x85) | (b1 == 0xA0))) | ((b1 >= 0x80) & (b2 >= 0x80) & (b3 >= wide[0]) & (b3 <= wide[1]))
        after = _WHITE[a1] | ((a1 == 0xC2) & ((a2 == 0x85) | (a2 == 0xA0))) | ((a1 >= wide[0]) & (a1 <= wide[1]))
        cut = np.zeros(n + 1, bool)
        cut[space[~before & ~after] - 3] = True
        cut[offsets] = True
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        start = np.flatnonzero(cut[:-1])
        end = np.append(start[1:], n)[: len(start)]
        return start, edge[start] | edge[end]

    def encode_new(self, data, start, end, alone) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        ask, groups = [], []
        for k in np.flatnonzero(alone):
            ask.append(data[start[k] : end[k]].tobytes())
            groups.append(np.array([k]))
        inner = np.flatnonzero(~alone)
        size = (end - start)[inner]
        run = np.repeat(start[inner] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum()) if len(inner) else np.empty(0, np.int64)
        flat, ends = data[run], np.cumsum(size)
        low = 0
        while low < len(inner):
            begin = int(ends[low] - size[low])
            high = max(low + 1, int(np.searchsorted(ends, begin + self.joined)))
            ask.append(flat[begin : ends[high - 1]].tobytes())
            groups.append(inner[low:high])
            low = high
        counts, order, found = [], [], []
        for raw, group, encoding in zip(ask, groups, self.tokenizer.encode_batch_fast([r.decode() for r in ask], add_special_tokens=False), strict=True):
            ids = np.array(encoding.ids, self.kind)
            if len(group) == 1:
                counts.append(np.array([len(ids)]))
            else:
                reached = np.cumsum(self.token_bytes[ids])
                bounds = np.searchsorted(reached, np.cumsum((end - start)[group]), side="right")
                counts.append(np.diff(np.concatenate([[0], bounds])))
            order.append(group)
            found.append(ids)
        return np.concatenate(order), np.concatenate(counts), np.concatenate(found)


_WHITE = np.zeros(256, bool)
_WHITE[[0x20, *range(0x09, 0x0E), *range(0x1C, 0x20)]] = True
_ENCODERS: dict[tuple[str, int], PieceEncoder] = {}


def piece_encoder(name: str, width: int) -> PieceEncoder:
    """The encoder of this Python worker, whose memo outlives a task."""
    if (name, width) not in _ENCODERS:
        _ENCODERS[name, width] = PieceEncoder(load_tokenizer(name), width)
    return _ENCODERS[name, width]


def load_tokenizer(name: str):
    """A public tokenizer by file name, or any tokenizer file by its path."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(name if os.path.sep in name else public_tokenizers.path(name))


def _open(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


MANIFEST = "path string, first_id bigint, first_text_hash bigint, part int, seq int, n_docs bigint, n_tokens bigint"


def write_token_tables(docs: DataFrame, path: str | None = None, tokenizer: str = "byte_bpe_50k.json", end_id: int | None = 2, shard_bytes: int = 256 << 20, slab_bytes: int = 1 << 20) -> DataFrame:
    """Encode and write shards in ascending doc_id order; returns the manifest, one row a shard file."""
    spark = docs.sparkSession
    path = path or fresh_path(spark, "token-table")
    width = 2 if load_tokenizer(tokenizer).get_vocab_size() <= 1 << 16 else 4
    end = b"" if end_id is None else np.array([end_id], f"<u{width}").tobytes()
    keyed = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # equal ids are told apart by a hash of the text, so that a hot id is split between ranges
    dealt = keyed.withColumn("tie", F.xxhash64("text")).repartitionByRange(F.asc_nulls_first("doc_id"), F.asc("tie")).sortWithinPartitions(F.asc_nulls_first("doc_id"), F.asc("tie"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filesystem, root = _open(path)
        encode = piece_encoder(tokenizer, width)
        part, seq, writer, made = TaskContext.get().partitionId(), 0, None, []

        def finish() -> None:
            writer.close()
            writer.sink.close()
            made.append((f"{path}/{name}", *head, part, seq, writer.docs, writer.tokens))

        for batch in batches:
            data, offsets = tn.utf8_buffers(batch.column(1))
            for low, high in tn.slabs(offsets, slab_bytes):
                cut = offsets[low : high + 1]
                ids, bounds = encode(data[cut[0] : cut[-1]], cut - cut[0])
                docs_of = batch.slice(low, high - low)
                for k, (doc_id, tie) in enumerate(zip(docs_of.column(0).to_pylist(), docs_of.column(2).to_pylist(), strict=True)):
                    if writer is None:
                        if seq == 0:
                            filesystem.create_dir(root, recursive=True)
                        name, head = f"{part:06d}-{seq:04d}-{uuid.uuid4().hex[:8]}.sst", (doc_id, tie)
                        writer = ShardWriter(filesystem.open_output_stream(f"{root}/{name}"), width)
                    writer.add(encode_key(doc_id), ids[bounds[k] : bounds[k + 1]].tobytes() + end)
                    if writer.at >= shard_bytes:
                        finish()
                        seq, writer = seq + 1, None
        if writer is not None:
            finish()
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*made, strict=True), (pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=["path", "first_id", "first_text_hash", "part", "seq", "n_docs", "n_tokens"])

    return stored(dealt.mapInArrow(run, MANIFEST), "token-manifest")[0]


def read_token_tables(manifest: DataFrame, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document, read back from the shards.

    The manifest has a row for each shard file of up to shard_bytes, so its rows go through the driver for the running totals.
    """
    spark = manifest.sparkSession
    shards = sorted(manifest.collect(), key=lambda r: (r.part, r.seq))
    start, rows = 0, []
    for r in shards:
        rows.append((r.path, start))
        start += r.n_tokens
    kinds = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.list_(pa.int32()))] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, begin in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                filesystem, name = _open(uri)
                with filesystem.open_input_file(name) as source:
                    shard = ShardReader(source)
                    out: list[tuple] = []
                    for key, value in shard.scan():
                        ids = np.frombuffer(value, f"<u{shard.width}").astype("<u4")
                        out.append((decode_key(key), begin, len(ids), zlib.crc32(ids.tobytes()), *([ids.astype(np.int32)] * with_ids)))
                        begin += len(ids)
                        if len(out) == 2000:
                            yield _batch(out, kinds)
                            out = []
                    if out:
                        yield _batch(out, kinds)

    ddl = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint" + ", ids array<int>" * with_ids
    listed = spark.createDataFrame(rows, "path string, start bigint")
    return listed.repartition(max(1, min(len(rows), 4096))).mapInArrow(run, ddl)


def _batch(rows: list[tuple], kinds: list[tuple[str, pa.DataType]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), kinds, strict=True)], names=[n for n, _ in kinds])


def lookup(manifest: DataFrame, doc_ids: list[int]) -> dict[int, list[np.ndarray]]:
    """Token ids of a few documents by binary search in the shards whose ranges can hold them."""
    shards = sorted(manifest.collect(), key=lambda r: (r.part, r.seq))
    out: dict[int, list[np.ndarray]] = {d: [] for d in doc_ids}
    low = [encode_key(r.first_id) for r in shards]
    for d in doc_ids:
        key = encode_key(d)
        for k in range(max(0, bisect.bisect_left(low, key) - 1), bisect.bisect_right(low, key)):
            filesystem, name = _open(shards[k].path)
            with filesystem.open_input_file(name) as source:
                out[d] += ShardReader(source).get(d)
    return out
