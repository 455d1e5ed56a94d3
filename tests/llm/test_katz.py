"""Katz backoff against a direct evaluation, and that probabilities add up to one."""

import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from deltahop.llm import katz


def brute(rows, order):
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 if i is not None else False for i, _ in rows}
    docs = [(i, (t or "").lower().split() + ["</s>"]) for i, t in rows]
    counts = [Counter() for _ in range(order + 1)]
    for i, words in docs:
        if not held[i]:
            padded = ["<s>"] * (order - 1) + words
            for j in range(len(words)):
                for n in range(1, order + 1):
                    counts[n][tuple(padded[j + order - n : j + order])] += 1
    total = sum(counts[1].values())
    d = [None] + [katz.good_turing(np.array([0] + [sum(c == r for c in counts[n].values()) for r in range(1, 7)])) for n in range(1, order + 1)]
    ratio = lambda n, c: d[n][c] if c <= 5 else 1.0
    seen = defaultdict(list)
    for n in range(2, order + 1):
        for g, c in counts[n].items():
            seen[g[:-1]].append((g[-1], c))
    left = 1 - sum(c * ratio(1, c) for c in counts[1].values()) / total
    whole = total
    if left < 1e-12:  # nothing is discounted: one occurrence is set aside
        whole, left = total + 1, 1 / (total + 1)

    def p(context, word):
        n = len(context) + 1
        if n == 1:
            c = counts[1][(word,)]
            return c * ratio(1, c) / whole if c else left
        after = seen.get(context)
        low = p(context[1:], word)
        if not after:
            return low
        t = sum(c for _, c in after)
        mass = sum(c * ratio(n, c) for _, c in after)
        if t - mass < 1e-9:
            t += 1
        c = counts[n][(*context, word)]
        if c:
            return c * ratio(n, c) / t
        return (1 - mass / t) / (1 - sum(p(context[1:], w) for w, _ in after)) * low

    out = {}
    for i, words in docs:
        padded = ["<s>"] * (order - 1) + words
        score = sum(math.log10(p(tuple(padded[j : j + order - 1]), w)) for j, w in enumerate(words))
        base = sum(math.log10((counts[1][(w,)] + 1) / (total + len(counts[1]) + 1)) for w in words)
        out[i] = (held[i], len(words), sum(counts[1][(w,)] > 0 for w in words), total, base, score)
    vocabulary = [g[0] for g in counts[1]] + ["unknown word"]
    for context in list(seen)[:40]:
        assert abs(sum(p(context, w) for w in vocabulary) - 1) < 1e-9
    return out


@pytest.mark.parametrize("order", [1, 2, 3])
def test_scores_match_direct_evaluation(spark, order):
    rng = random.Random(order)
    words = [f"w{int(60 * rng.random() ** 3)}" for _ in range(4000)]
    rows = [(i, " ".join(rng.choice(words).upper() if rng.random() < 0.1 else rng.choice(words) for _ in range(rng.randrange(40)))) for i in range(120)] + [(500, None), (501, "new words only"), (502, "")]
    config = katz.KatzConfig(order=order, chunk_bytes=4000, bucket_bytes=2000)
    got = katz.score_documents(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3), config).collect()
    want = brute(rows, order)
    assert len(got) == len(rows)
    for r in got:
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == want[r.doc_id][:4]
        assert math.isclose(r.base_score, want[r.doc_id][4], rel_tol=1e-9) and math.isclose(r.score, want[r.doc_id][5], rel_tol=1e-7), r


def test_odd_rows(spark, odd_docs):
    got = katz.score_documents(odd_docs).collect()
    assert len(got) == odd_docs.count() and all(np.isfinite(r.score) for r in got)
    assert {r.n_tokens for r in got if r.doc_id in (2, 3, 4)} == {1}
    assert katz.score_documents(odd_docs.limit(0)).collect() == []


@pytest.mark.parametrize("order", [2, 3])
def test_split_contexts_score_alike(spark, order):
    rng = random.Random(9)
    rows = [(i, " ".join(f"as the w{rng.randrange(40)}" for _ in range(60))) for i in range(80)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = katz.score_documents(df, katz.KatzConfig(order=order, chunk_bytes=5000, bucket_bytes=100))  # many buckets, so "as the" is split
    want = brute(rows, order)
    got = got.collect()
    for r in got:
        assert math.isclose(r.score, want[r.doc_id][5], rel_tol=1e-7)
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
