"""The sorts behind the counts of n-grams: pairs sorted as one number, and each chunk's 2-grams sorted once."""

import numpy as np
import pytest

from deltahop.llm import katz, packed


@pytest.mark.parametrize("high", [3, 1 << 20, 1 << 31, 1 << 45])
def test_sorted_pairs_of_any_width(high):
    rng = np.random.default_rng(high)
    a, b = rng.integers(0, 40, 500) * (high // 3), rng.integers(0, high, 500)
    b[::3] = 1
    order, fresh_a, fresh = katz._sorted_pairs(a, b)
    pairs = list(zip(a[order].tolist(), b[order].tolist(), strict=True))
    assert pairs == sorted(zip(a.tolist(), b.tolist(), strict=True)) and sorted(order.tolist()) == list(range(500))
    assert fresh.tolist() == [i == 0 or pairs[i] != pairs[i - 1] for i in range(500)]
    assert fresh_a.tolist() == [i == 0 or pairs[i][0] != pairs[i - 1][0] for i in range(500)]


@pytest.mark.parametrize("n", [0, 1, 1000])
def test_split_by_bucket_keeps_order(n):
    bucket = np.random.default_rng(n).integers(0, 7, n).astype(np.uint64)
    order, at = packed.split_by_bucket(bucket, 7)
    assert order.tolist() == np.argsort(bucket, kind="stable").tolist()
    assert at.tolist() == [int((bucket < b).sum()) for b in range(8)]


def test_words_before_a_token_are_the_two_gram_before_it(monkeypatch):
    """Their numbers follow (nearer, older) word, and only distinct 2-grams are sorted for them."""
    rng = np.random.default_rng(1)
    counts = np.array([1, 400, 2, 300])
    local = rng.integers(0, 9, counts.sum()).astype(np.uint32)
    number, often = rng.permutation(9).astype(np.int64) * 5 + 1, np.full(9, 3, np.int64)
    raw = packed.pack_arrays(np.arange(4), np.zeros(4, np.uint8), np.zeros(4, np.uint8), counts, local, number, often)
    stream = katz.Stream(raw, 3, katz.Order(np.zeros(7, np.int64)))
    stream._grams(2, katz.Order(np.zeros(7, np.int64)), 1000)
    ranks = [stream._before(stream.rank, j, 0) for j in (1, 2)]
    sizes, sort = [], katz._sorted_pairs
    monkeypatch.setattr(katz, "_sorted_pairs", lambda a, b: sizes.append(len(a)) or sort(a, b))
    got = stream._near_pairs(ranks)
    assert sizes == [len(stream.pairs[1])] and sizes[0] < len(local)
    wanted = np.unique(ranks[0] * 100 + ranks[1], return_inverse=True)[1]
    assert len(np.unique(np.column_stack([got, wanted]), axis=0)) == len(np.unique(got)) == len(np.unique(wanted))
    assert (np.argsort(got, kind="stable") == np.argsort(wanted, kind="stable")).all()
