"""Token tables: whole-text encodings, round trip, look-up and file format."""

import io
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from deltahop.llm import token_table as tt

TOKENIZER = tt.load_tokenizer("byte_bpe_50k.json")


ENCODE = tt.PieceEncoder(TOKENIZER, 2, memo_size=3000, joined=50)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet=st.sampled_from(list("aZ é\n\t漢'1#  \x00\x1c\x85\u00a0\u3000\u2003 à")), max_size=30), max_size=6))
def test_piece_encoding_equals_whole_text_encoding(texts):
    raw = [t.encode() for t in texts]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    ids, bounds = ENCODE(np.frombuffer(b"".join(raw), np.uint8), offsets)
    for k, text in enumerate(texts):
        assert ids[bounds[k] : bounds[k + 1]].tolist() == TOKENIZER.encode(text, add_special_tokens=False).ids


def test_round_trip_in_order(spark, odd_docs):
    manifest = tt.write_token_tables(odd_docs, shard_bytes=2000)
    rows = sorted(tt.read_token_tables(manifest, with_ids=True).collect(), key=lambda r: r.start)
    source = sorted(odd_docs.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0))
    assert [r.doc_id for r in rows] == [r.doc_id for r in source]
    start = 0
    for r, s in zip(rows, source, strict=True):
        ids = [*TOKENIZER.encode(s.text or "", add_special_tokens=False).ids, 2]
        assert r.ids == ids and r.start == start and r.n_tokens == len(ids)
        assert r.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    found = tt.lookup(manifest, [1, 7, 55])
    assert len(found[1]) == 2 and len(found[7]) == 1 and found[55] == []
    assert tt.read_token_tables(tt.write_token_tables(odd_docs.limit(0))).collect() == []


class _Memory(io.BytesIO):
    def size(self):
        return len(self.getvalue())


def test_shard_lookup_and_damage():
    sink = _Memory()
    writer = tt.ShardWriter(sink, 2, block_bytes=300, restart=4)
    keys = sorted({*range(-50, 300, 7), 5, 1 << 40})
    for k in keys:
        writer.add(tt.encode_key(k), np.arange(k % 9, dtype="<u2").tobytes())
    writer.close()
    shard = tt.ShardReader(sink)
    assert [tt.decode_key(k) for k, _ in shard.scan()] == keys and shard.n_docs == len(keys)
    for k in range(-60, 310):
        assert [v.tolist() for v in shard.get(k)] == ([list(range(k % 9))] if k in keys else [])
    raw = bytearray(sink.getvalue())
    raw[20] ^= 1
    with pytest.raises((ValueError, OSError)):
        list(tt.ShardReader(_Memory(bytes(raw))).scan())


def test_bloom_filter_rarely_errs():
    keys = [tt.encode_key(7 * k) for k in range(20_000)]
    bloom = tt.Bloom.load(tt.Bloom.of(keys).dump())
    assert all(k in bloom for k in keys)
    assert sum(tt.encode_key(7 * k + 3) in bloom for k in range(20_000)) < 400
