"""Suffix arrays, longest previous factors and removed bytes against brute force."""

import hashlib
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from deltahop.llm import packed, suffix_dedup
from deltahop.llm.suffix_dedup import SuffixConfig


@settings(max_examples=100, deadline=None)
@given(st.binary(max_size=60).map(lambda b: bytes(x % 3 + 97 for x in b)))
def test_suffix_array_and_previous_factors(raw):
    data = np.frombuffer(raw, np.uint8)
    assert suffix_dedup.suffix_array(data).tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
    want = []
    for i in range(len(raw)):
        best = 0
        for j in range(i):
            n = 0
            while i + n < len(raw) and raw[j + n] == raw[i + n]:
                n += 1
            best = max(best, n)
        want.append(best)
    assert suffix_dedup.longest_previous_factor(data).tolist() == want


@given(st.lists(st.integers(0, 6), max_size=40))
def test_previous_smaller(values):
    got = suffix_dedup.previous_smaller(np.array(values, np.int64)).tolist()
    assert got == [next((j for j in range(i - 1, -1, -1) if values[j] < values[i]), -1) for i in range(len(values))]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.binary(max_size=40).map(lambda b: bytes(x % 2 + 97 for x in b)), min_size=1, max_size=5), st.integers(3, 20), st.sampled_from([7, 1 << 30]))
def test_earlier_factors(texts, length, at_once):
    data = np.frombuffer(b"".join(texts), np.uint8)
    ends = np.cumsum([len(t) for t in texts])
    spots = [(d, int(ends[d]) - len(t) + i) for d, t in enumerate(texts) for i in range(len(t) - length + 1)]
    got = suffix_dedup.earlier_factors(data, np.array([s for _, s in spots], np.int64), np.array([d for d, _ in spots], np.int64), length, at_once)
    raw = data.tobytes()
    for (d, s), have in zip(spots, got.tolist(), strict=True):
        best = max((next((n for n in range(length) if raw[s + n] != raw[o + n]), length) for e, o in spots if e < d), default=0)
        assert have == best or at_once == 7 and have < min(8, length) and best < min(8, length)


def brute(rows, n=50):
    first = {}
    for i, text in rows:
        raw = (text or "").encode()
        for k in range(len(raw) - n + 1):
            w = raw[k : k + n]
            key = i if i is not None else 1 << 62
            first[w] = min(first.get(w, 1 << 63), key)
    out = []
    for i, text in rows:
        raw = (text or "").encode()
        gone = bytearray(len(raw))
        for k in range(len(raw) - n + 1):
            if first[raw[k : k + n]] < (i if i is not None else 1 << 62):
                gone[k : k + n] = b"\1" * n
        spans = sum(gone[k] and (k == 0 or not gone[k - 1]) for k in range(len(raw)))
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        out.append((i, len(raw), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=repr)


def corpus(seed):
    rng = random.Random(seed)
    words = ["the", "of", "lorem", "ipsum", "é", "漢字", "x", "repetition", "a"]
    passages = [" ".join(rng.choice(words) for _ in range(rng.randint(9, 40))) for _ in range(6)]
    rows = []
    for i in range(70):
        parts = []
        for _ in range(rng.randint(0, 4)):
            if rng.random() < 0.5:
                p = rng.choice(passages)
                a = rng.randint(0, 12)
                parts.append(p[a : len(p) - rng.randint(0, 12)])
            else:
                parts.append(" ".join(f"{rng.choice(words)}{rng.randrange(90)}" for _ in range(rng.randint(1, 30))))
        rows.append((i * 3 % 70, rng.choice([" ", "\n", ""]).join(parts)))
    long = "ab" * 300
    return rows + [(80, long), (81, long + "c"), (81, long), (90, None), (91, ""), (None, passages[0]), (None, passages[0]), (95, "ab" * 30), (96, "z" * 49), (97, "z" * 50), (98, "z" * 51)]


@pytest.mark.parametrize("hot", [20000, 2])
def test_removed_bytes_match_brute_force(spark, hot):
    rows = corpus(4)
    config = SuffixConfig(chunk_bytes=3000, bucket_bytes=5000, slab_bytes=1000, hot_cells=hot, sorted_at_once=100)
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df, config).collect()), key=repr)
    assert got == brute(rows)
    assert any(r[2] for r in got)


def test_text_and_other_columns_stay(spark, odd_docs):
    out = suffix_dedup.remove_repeats(odd_docs.withColumnRenamed("score", "n_bytes"), with_text=True)
    assert out.count() == odd_docs.count()
    out = {r.doc_id: r for r in suffix_dedup.remove_repeats(odd_docs, with_text=True).collect()}
    assert out[6].kept_text.startswith("é ü 漢字") and out[6].score == "q" and out[5].n_removed == 0
    assert suffix_dedup.remove_repeats(odd_docs.limit(0)).collect() == []


def test_packed_arrays_round_trip():
    arrays = [np.arange(5, dtype=np.uint64) << np.uint64(40), np.empty(0, np.int32), np.array([1, 255], np.uint8)]
    for a, b in zip(arrays, packed.unpack_arrays(packed.pack_arrays(*arrays)), strict=True):
        assert a.dtype == b.dtype and a.tolist() == b.tolist()
