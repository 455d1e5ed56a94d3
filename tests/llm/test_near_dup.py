"""Near-duplicate components against all pairs."""

import random

import numpy as np
import pytest

from deltahop.llm import near_dup
from deltahop.llm import textnum as tn


def brute(rows, n):
    sets = {}
    for i, text in rows:
        words = [w for w in (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).replace("\t", " ").replace("\n", " ").split(" ") if w]
        sets[i] = {tuple(words[k : k + n]) for k in range(len(words) - n + 1)} if len(words) >= n else ({tuple(words)} if words else set())
    comp = {i: i for i in sets}
    ids = sorted(sets)
    change = True
    pairs = [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    while change:
        change = False
        for a, b in pairs:
            low = min(comp[a], comp[b])
            if comp[a] != low or comp[b] != low:
                comp[a] = comp[b] = low
                change = True
    return {i: (len(sets[i]), comp[i]) for i in ids}


def corpus(seed):
    rng = random.Random(seed)
    rows, base = [], []
    for i in range(260):
        if base and rng.random() < 0.6:
            words = list(rng.choice(base))
            for _ in range(rng.randint(0, 1 + len(words) // 12)):
                words[rng.randrange(len(words))] = f"w{rng.randrange(60)}"
        else:
            words = [f"w{rng.randrange(300)}" for _ in range(rng.choice([1, 2, 3, 8, 40, 120]))]
        base.append(words)
        rows.append((i, " ".join(w.upper() if rng.random() < 0.1 else w for w in words)))
    return rows + [(900, None), (901, ""), (902, " \n ")]


@pytest.mark.parametrize("n", [2, 5])
def test_components_match_all_pairs(spark, n):
    rows = corpus(n)
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), near_dup.NearDupConfig(shingle=n)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute(rows, n)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


@pytest.mark.parametrize("large", [1, 10**9])
def test_large_and_small_buckets_join_alike(spark, monkeypatch, large):
    """With 1 no bucket counts as large, with 10**9 every one does."""
    monkeypatch.setattr(near_dup, "LARGE", large)
    rows = corpus(11)[:160]
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), near_dup.NearDupConfig(shingle=2, block=7, members=3)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute(rows, 2)


def test_odd_rows(spark, odd_docs):
    got = near_dup.near_duplicates(odd_docs).collect()
    assert len(got) == odd_docs.count()
    assert {r.component_id for r in got if r.doc_id == 1} == {1}
    assert all(r.n_shingles == 0 and r.kept for r in got if r.doc_id in (2, 3, 4))
    assert near_dup.near_duplicates(odd_docs.limit(0)).collect() == []


def test_odd_sketch_estimates_similarity():
    config = near_dup.NearDupConfig()
    rng = np.random.default_rng(1)
    for share in (0.95, 0.8):
        common = int(2000 * share)
        key = tn.mix(rng.integers(0, 1 << 62, 4000 - common, dtype=np.int64).view(tn.U))
        a, b = np.sort(key[:2000]), np.sort(np.concatenate([key[:common], key[2000:]]))
        s = near_dup.minhash(np.concatenate([a, b]), np.array([0, 2000, 4000]), config)
        j = common / (4000 - common)
        assert abs((s[0] == s[1]).mean() - j) < 0.15
        odd = int(np.unpackbits(near_dup.odd_sketch(s, 256)[0] ^ near_dup.odd_sketch(s, 256)[1]).sum())
        estimate = 1 + 256 / (4 * config.samples) * np.log(max(1e-9, 1 - 2 * odd / 256))
        assert abs(estimate - (s[0] == s[1]).mean()) < 0.12
