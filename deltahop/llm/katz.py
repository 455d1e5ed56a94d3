"""LM scoring: Katz backoff over Good-Turing discounted n-gram counts.

P_k(w | u) is d(c) c(u w) / c(u) for an n-gram seen in training and alpha(u) P_{k-1}(w | u') otherwise, down to the discounted
unigrams, whose left mass belongs to the one class of unknown words. alpha(u) is exact: the mass that the discounts leave,
over the lower-order mass of all words not seen after u, so every context's probabilities add up to one. Where none of a
context's counts is discounted, one further occurrence is set aside for unseen words.

Tables of counts are partitioned by a hash of the context and are built and asked in one exchange per order: a chunk of documents
sends its distinct n-grams with their training counts, a bucket adds them up and answers with the corpus counts, for each
context its divisor and, where an n-gram of it was never seen, what its backoff weight is made of. Contexts that hold more than a
share of all tokens are split by word, so no bucket gathers a frequent context. All counts come from all training rows.

Defined results: null and empty texts are the end token alone; a null doc_id is a training row; repeated rows count as often as
they occur; an empty table gives no rows; without training rows all words are unknown and have probability one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltahop.llm import packed
from deltahop.llm import textnum as tn
from deltahop.llm.workdir import drop_path, stored

START = 0  # word id of the start of a text, a context only
END = tn.U(0x5EED0E0D5EED0E0D)  # hash that stands for the end token
SUMMARY, SPLIT = 8, 9  # kinds of rows that the driver reads


@dataclass(frozen=True)
class KatzConfig:
    order: int = 3
    discounted: int = 5  # counts above it aren't discounted
    chunk_bytes: int = 8 << 20
    bucket_bytes: int = 8 << 20
    slab_bytes: int = 1 << 20


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 7 == 2, F.lit(False))


def good_turing(n_of: np.ndarray) -> np.ndarray:
    """Katz's discount ratios d[1..k] from n_of[r], the number of n-grams seen r times (r = 1..k+1); index 0 is unused.

    Where counts of counts are too few or irregular for a ratio in (0, 1), half an occurrence is taken off instead.
    """
    k = len(n_of) - 2
    d = np.ones(k + 1)
    common = (k + 1) * n_of[k + 1] / n_of[1] if n_of[1] else 1.0
    for r in range(1, k + 1):
        value = ((r + 1) * n_of[r + 1] / (r * n_of[r]) - common) / (1 - common) if n_of[r] and common < 1 else -1.0
        d[r] = value if 0 < value < 1 else (r - 0.5) / r
    return d


@dataclass
class Order:
    """What the driver knows of one order: counts of counts, discounts and the sums of split contexts."""

    n_of: np.ndarray
    tokens: int = 0
    types: int = 0
    documents: int = 0
    split: dict[int, np.ndarray] = field(default_factory=dict)

    @property
    def d(self) -> np.ndarray:
        return good_turing(self.n_of)


def _discounted(count: np.ndarray, d: np.ndarray) -> np.ndarray:
    ratio = np.where(count < len(d), d[np.minimum(count, len(d) - 1)], 1.0)
    return count * ratio


def unigram(count: np.ndarray, first: Order) -> np.ndarray:
    """P_1 of words with these training counts; unknown words share what the discounts leave."""
    if not first.tokens:
        return np.ones(len(count))
    d = first.d
    r = np.arange(1, len(d))
    left = (first.n_of[1 : len(d)] * r * (1 - d[1:])).sum() / first.tokens
    scale = 1.0 if left > 0 else first.tokens / (first.tokens + 1)
    left = left if left > 0 else 1 / (first.tokens + 1)
    return np.where(count > 0, scale * _discounted(count, d) / first.tokens, left)


def backoff(stats: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(alpha, divisor) of contexts from rows (total, m_1..m_k, lower mass of the words seen)."""
    total, seen = stats[:, 0], stats[:, -1]
    r = np.arange(1, len(d))
    taken = (stats[:, 1 : len(d)] * (r * (1 - d[1:]))).sum(1)
    none = (taken <= 0) & (total > 0)  # only large counts: one occurrence is set aside for unseen words
    divisor = np.where(none, total + 1, np.maximum(total, 1))
    left = np.where(total > 0, np.where(none, 1.0, taken) / divisor, 1.0)
    return left / np.maximum(1 - seen, 1e-12), divisor


# ---- chunks of documents as word numbers


def tokenised(batch: pa.RecordBatch, slab_bytes: int) -> bytes:
    """ids, training flags, tokens per document, word numbers by local frequency, and the words' hashes."""
    data, offsets = tn.utf8_buffers(batch.column("text"))
    hashes, counts = [], []
    for low, high in tn.slabs(offsets, slab_bytes):
        part = offsets[low : high + 1]
        words = tn.Words(data[part[0] : part[-1]], part - part[0], lower=True)
        ends = words.first[1:] + np.arange(words.n_docs)  # where end tokens go
        out = np.empty(len(words) + words.n_docs, tn.U)
        place = np.ones(len(out), bool)
        place[ends] = False
        out[place], out[ends] = words.hash, END
        hashes.append(out)
        counts.append(words.counts + 1)
    stream = np.concatenate(hashes) if hashes else np.empty(0, tn.U)
    vocabulary, local, often = np.unique(stream, return_inverse=True, return_counts=True)
    order = np.argsort(-often, kind="stable")
    rank = np.empty(len(order), np.uint32)
    rank[order] = np.arange(len(order), dtype=np.uint32)
    ids = batch.column("doc_id")
    return packed.pack_arrays(
        np.asarray(ids.fill_null(0)).astype(np.int64), np.asarray(ids.is_null()).astype(np.uint8), np.asarray(batch.column("held")).astype(np.uint8),
        np.concatenate(counts).astype(np.int64) if counts else np.empty(0, np.int64), rank[local], vocabulary[order],
    )


class Chunk:
    """A chunk's tokens before their words have numbers."""

    def __init__(self, raw: bytes, buckets: int):
        self.ids, self.no_id, self.held, self.counts, self.local, self.vocabulary = packed.unpack_arrays(raw)
        self.buckets = buckets
        self.order = np.argsort(self.vocabulary)
        self.by, self.at = packed.split_by_bucket(self.vocabulary[self.order] % tn.U(buckets), buckets)

    def ask_words(self, key: int) -> list[tuple[int, int, int, bytes]]:
        train = np.repeat(self.held == 0, self.counts)
        often = np.bincount(self.local, weights=train, minlength=len(self.vocabulary)).astype(np.uint32)
        out = []
        for b in np.flatnonzero(np.diff(self.at)):
            pick = self.order[self.by[self.at[b] : self.at[b + 1]]]
            out.append((int(b), 0, key, packed.pack_arrays(self.vocabulary[pick], often[pick])))
        out.append((int(key % self.buckets), 1, key, packed.pack_arrays(np.array([(self.held == 0).sum()], np.int64))))
        return out

    def numbered(self, answers: list[tuple[int, bytes]]) -> bytes:
        """The chunk with the number and the training count of each word in place of its hash."""
        number, count = np.zeros(len(self.vocabulary), np.int64), np.zeros(len(self.vocabulary), np.int64)
        for b, raw in answers:
            pick = self.order[self.by[self.at[b] : self.at[b + 1]]]
            number[pick], count[pick] = packed.unpack_arrays(raw)
        return packed.pack_arrays(self.ids, self.no_id, self.held, self.counts, self.local, number, count)


def context_key(words: list[np.ndarray]) -> np.ndarray:
    """One number per context, from its words, the nearest first."""
    key = words[0].astype(tn.U)
    for older in words[1:]:
        key = tn.combine(key, older.astype(tn.U))
    return key


def _runs(columns: list[np.ndarray]) -> np.ndarray:
    """Where rows differ from the row before."""
    fresh = np.zeros(len(columns[0]), bool)
    fresh[:1] = True
    for c in columns:
        fresh[1:] |= c[1:] != c[:-1]
    return fresh


def _bits(values: np.ndarray) -> int:
    return int(values.max()).bit_length() if len(values) else 0


def _sorted_pairs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, fresh_a, fresh): rows in ascending order of (a, b), where a is new in it, and where the pair is. No negative values.

    Where both values and the row fit 64 bits they are sorted as one number, which is several times faster than sorting rows by a key.
    """
    wide, rows = _bits(b), max(0, len(a) - 1).bit_length()
    if _bits(a) + wide + rows <= 64:
        key = a.astype(tn.U) << tn.U(wide) | b.astype(tn.U)
        key = np.sort(key << tn.U(rows) | np.arange(len(a), dtype=tn.U)) if rows else key
        order, key = (key & tn.U((1 << rows) - 1)).astype(np.int64), key >> tn.U(rows)
        return order, _runs([key >> tn.U(wide)]), _runs([key])
    if _bits(a) + wide <= 64:
        key = a.astype(tn.U) << tn.U(wide) | b.astype(tn.U)
        order = np.argsort(key)
        key = key[order]
        return order, _runs([key >> tn.U(wide)]), _runs([key])
    order = np.lexsort((b, a))
    fresh_a = _runs([a[order]])
    return order, fresh_a, fresh_a | _runs([b[order]])


def _numbered(order: np.ndarray, fresh: np.ndarray) -> np.ndarray:
    """The number of each row's run in the order."""
    number = np.empty(len(order), np.int64)
    number[order] = np.cumsum(fresh) - 1
    return number


def _ranks(values: np.ndarray) -> np.ndarray:
    """1 for the smallest value, 2 for the next; values differ."""
    out = np.empty(len(values), np.int64)
    out[np.argsort(values)] = np.arange(1, len(values) + 1)
    return out


class Stream:
    """A chunk's tokens and what is known of them so far: probability, count and divisor of the longest n-gram looked up."""

    def __init__(self, raw: bytes, buckets: int, first: Order):
        self.ids, self.no_id, held, self.counts, local, number, count = packed.unpack_arrays(raw)
        self.held = held.astype(bool)
        self.buckets = buckets
        self.train = np.repeat(~self.held, self.counts)
        ends = np.cumsum(self.counts)
        self.at = np.arange(len(local)) - np.repeat(ends - self.counts, self.counts)  # place within the document
        self.word, self.count = number[local], count[local]
        self.rank = _ranks(number)[local]  # in the order of the words' numbers, but small
        self.pairs = None
        self.p = unigram(count, first)[local]
        self.lower, self.divisor = self.count, np.zeros(len(local), np.int64)

    def _before(self, values: np.ndarray, j: int, start: int) -> np.ndarray:
        shifted = np.concatenate([np.zeros(min(j, len(values)), values.dtype), values[: max(0, len(values) - j)]])
        return np.where(self.at >= j, shifted, start)

    def _before_at(self, rows: np.ndarray, at: np.ndarray, values: np.ndarray, j: int, start: int) -> np.ndarray:
        """_before for some rows only; at: their places."""
        return np.where(at >= j, values[rows - j], start)

    def _grams(self, k: int, first: Order, limit: int):
        """Distinct n-grams of the chunk, ordered by context word (the nearest first) and word, and where they are sent. `head` is a
        token of each; contexts' numbers, their words and parts are those of the distinct n-grams.

        N-grams of one nearest word go to one bucket, so that its sorted numbers pack well; those of a frequent one are dealt
        out by the older word, and those of a frequent context by the word that follows.
        """
        ranks = [self._before(self.rank, j, START) for j in range(1, min(k, 3))]
        if k == 2:
            order, fresh_context, fresh = _sorted_pairs(ranks[0], self.rank)
            gram, head = _numbered(order, fresh), order[fresh]
            self.pairs = gram, ranks[0][head], self.rank[head]
        else:
            gram = self._near_pairs(ranks)
            for j in range(3, k):
                order, _, fresh = _sorted_pairs(gram, self._before(self.rank, j, START))
                gram = _numbered(order, fresh)
            order, fresh_context, fresh = _sorted_pairs(gram, self.rank)
            gram, head = _numbered(order, fresh), order[fresh]
        context = np.cumsum(fresh_context[fresh])
        at = self.at[head]
        back = [self._before_at(head, at, self.word, j, START) for j in range(1, k)]
        parts = 1 + self._before_at(head, at, self.lower, 1, first.documents) // limit  # lower: how often the context itself occurs
        part, many = np.full(len(head), -1), np.flatnonzero(parts > 1)
        part[many] = self.word[head[many]] % parts[many]
        spot = back[0].astype(tn.U)
        if k > 2:
            near = 1 + self._before_at(head, at, self.count, 1, first.documents) // limit
            turn, many = np.zeros(len(head), np.int64), np.flatnonzero(near > 1)
            turn[many] = back[1][many] % near[many]
            spot = tn.combine(spot, turn.astype(tn.U))
        bucket = tn.mix(spot + (part + 1).astype(tn.U) * tn.U(0x9E3779B97F4A7C15)) % tn.U(self.buckets)
        by, at = packed.split_by_bucket(bucket, self.buckets)
        return gram, head, context, back, part, by, at

    def _near_pairs(self, ranks: list[np.ndarray]) -> np.ndarray:
        """A number for the two words before each token, ordered by the nearer one first. They are the 2-gram that ends there, so only the
        distinct 2-grams are sorted once these are known; a text's first token has 0."""
        if self.pairs is None:
            order, _, fresh = _sorted_pairs(*ranks)
            return _numbered(order, fresh)
        gram, older, nearer = self.pairs
        order, _, _ = _sorted_pairs(nearer, older)
        number = np.empty(len(order), np.int64)
        number[order] = np.arange(1, len(order) + 1)
        return self._before(number[gram], 1, 0)

    def ask_grams(self, key: int, k: int, first: Order, limit: int) -> list[tuple[int, int, int, bytes]]:
        """Per bucket: the n-grams' words, how often they occur here, and count and divisor of their shorter n-grams."""
        gram, head, _, back, part, by, at = self._grams(k, first, limit)
        often = np.bincount(gram, weights=self.train, minlength=len(head)).astype(np.uint32)
        lower, divisor = (np.where(often > 0, x[head], 0) for x in (self.lower, self.divisor))
        out = []
        for b in np.flatnonzero(np.diff(at)):
            pick = by[at[b] : at[b + 1]]
            own = head[pick]
            out.append((int(b), 0, key, packed.pack_arrays(self.word[own], often[pick], lower[pick], divisor[pick], (part[pick] >= 0).astype(np.uint8), *(c[pick] for c in back))))
        return out

    def learn_grams(self, answers: list[tuple[int, bytes]], k: int, first: Order, limit: int, known: Order) -> None:
        """Probabilities of order k for every token, from the answers by bucket."""
        gram, head, context, back, part, by, at = self._grams(k, first, limit)
        d = known.d
        count, divisor, p = np.zeros(len(head), np.int64), np.zeros(len(head), np.int64), self.p[head].copy()
        for b, raw in answers:
            pick = by[at[b] : at[b + 1]]
            count[pick], whole, asked, *columns = packed.unpack_arrays(raw)
            edge = _runs([context[pick]])
            row, whole, alpha = np.cumsum(edge) - 1, whole.astype(np.int64), np.ones(int(edge.sum()))
            if len(columns[0]):
                alpha[asked.astype(bool)] = backoff(np.column_stack(columns).astype(np.float64), d)[0]
            cut = np.flatnonzero(edge & (part[pick] >= 0))
            for i, name in zip(cut, context_key([c[pick[cut]] for c in back]).tolist(), strict=True):
                (alpha[row[i]],), (whole[row[i]],) = backoff(known.split[name][None], d)
            c = count[pick]
            divisor[pick] = whole[row]
            p[pick] = np.where(c > 0, _discounted(c, d) / np.maximum(whole[row], 1), alpha[row] * p[pick])
        self.p, self.lower, self.divisor = p[gram], count[gram], divisor[gram]

    def scores(self, first: Order) -> pa.Table:
        starts = np.cumsum(self.counts) - self.counts
        add = lambda x: np.add.reduceat(x, starts) if len(starts) else x
        base = np.log10((self.count + 1) / (first.tokens + first.types + 1))
        n = len(self.ids)
        return pa.table({
            "doc_id": pa.array(self.ids, mask=self.no_id.astype(bool)),
            "held_out": pa.array(self.held),
            "n_tokens": pa.array(self.counts),
            "n_known": pa.array(add((self.count > 0).astype(np.int64)), pa.int64()),
            "train_tokens": pa.array(np.full(n, first.tokens, np.int64)),
            "base_score": pa.array(add(base), pa.float64()),
            "score": pa.array(add(np.log10(self.p)), pa.float64()),
        })


# ---- buckets


def _count_words(config: KatzConfig, buckets: int):
    def answer(bucket: int, parts: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int, bytes]]:
        asked = [(origin, *packed.unpack_arrays(raw)) for kind, origin, raw in parts if kind == 0]
        documents = sum(int(packed.unpack_arrays(raw)[0][0]) for kind, _, raw in parts if kind == 1)
        out, n_of, tokens, types = [], np.zeros(config.discounted + 2, np.int64), 0, 0
        if asked:
            words, place = np.unique(np.concatenate([h for _, h, _ in asked]), return_inverse=True)
            count = np.bincount(place, weights=np.concatenate([c for *_, c in asked]), minlength=len(words)).astype(np.int64)
            number = np.empty(len(words), np.int64)
            number[np.argsort(-count, kind="stable")] = np.arange(len(words))  # frequent words get small numbers
            number = number * buckets + bucket + 1
            n_of += np.bincount(np.minimum(count, len(n_of)), minlength=len(n_of) + 1)[: len(n_of)]
            tokens, types = int(count.sum()), int((count > 0).sum())
            at = 0
            for origin, h, _ in asked:
                pick = place[at : at + len(h)]
                at += len(h)
                out.append((origin, 1, bucket, packed.pack_arrays(number[pick], count[pick])))
        out.append((-1, SUMMARY, bucket, packed.pack_arrays(n_of, np.array([tokens, types, documents], np.int64))))
        return out

    return answer


def _count_grams(config: KatzConfig, order_k: int, first: Order, below: np.ndarray | None):
    """below: the discounts of the next shorter order, None for words alone."""
    k = config.discounted

    def answer(bucket: int, parts: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int, bytes]]:
        asked = [(origin, packed.unpack_arrays(raw)) for _, origin, raw in parts]
        word, often, lower, divisor, split, *back = (np.concatenate([a[i] for _, a in asked]) for i in range(len(asked[0][1])))
        sizes = [len(a[0]) for _, a in asked]
        asked = [origin for origin, _ in asked]
        near = back[0]
        for older in back[1:]:
            order, _, fresh = _sorted_pairs(near, older)
            near = _numbered(order, fresh)
        order, fresh_ctx, fresh = _sorted_pairs(near, word)
        gram = _numbered(order, fresh)
        at = np.flatnonzero(fresh)
        count = np.bincount(gram, weights=often, minlength=len(at)).astype(np.int64)
        lower, divisor = (np.maximum.reduceat(x[order], at) for x in (lower, divisor))  # chunks without training rows send none
        mass = unigram(lower, first) if below is None else _discounted(lower, below) / np.maximum(divisor, 1)
        row = np.cumsum(fresh_ctx[fresh]) - 1  # context of each distinct n-gram
        n = int(row[-1]) + 1
        add = lambda x: np.bincount(row, weights=x, minlength=n)
        stats = [add(count), *(add(count == r) for r in range(1, k + 1)), add(np.where(count > 0, mass, 0.0))]
        whole = (stats[0] + ((stats[0] > 0) & (sum(stats[1:-1]) == 0))).astype(np.int64)  # as in backoff
        n_of = np.bincount(np.minimum(count, k + 2), minlength=k + 3)[: k + 2].astype(np.int64)
        out = [(-1, SUMMARY, bucket, packed.pack_arrays(n_of, np.array([count.sum(), (count > 0).sum(), 0], np.int64)))]
        tops = order[fresh_ctx]
        parted = split[tops] > 0
        if parted.any():
            out.append((-1, SPLIT, bucket, packed.pack_arrays(context_key([c[tops[parted]] for c in back]), *(s[parted] for s in stats))))
        low = 0
        for origin, size in zip(asked, sizes, strict=True):
            pick = gram[low : low + size]
            low += size
            edge = _runs([row[pick]])
            rows, unseen = row[pick][edge], np.logical_or.reduceat(count[pick] == 0, np.flatnonzero(edge))
            weigh = unseen & (whole[rows] > 0) & ~parted[rows]  # a backoff weight is asked for unseen n-grams only
            asked_stats = [s[rows[weigh]] for s in stats]
            out.append((origin, order_k, bucket, packed.pack_arrays(count[pick], whole[rows], weigh.astype(np.uint8), *(s.astype(np.int64) for s in asked_stats[:-1]), asked_stats[-1])))
        return out

    return answer


def _summary(answers: DataFrame, config: KatzConfig) -> Order:
    """Adds up the buckets' summaries: a row each of some hundred bytes, and the few split contexts."""
    known = Order(np.zeros(config.discounted + 2, np.int64))
    for r in answers.where("key = -1").select("kind", "payload").toLocalIterator():
        got = packed.unpack_arrays(r.payload)
        if r.kind == SUMMARY:
            known.n_of += got[0]
            known.tokens, known.types, known.documents = (a + int(b) for a, b in zip((known.tokens, known.types, known.documents), got[1], strict=True))
        else:
            for i, context in enumerate(got[0].tolist()):
                sums = np.array([c[i] for c in got[1:]], np.float64)
                known.split[context] = known.split.get(context, 0) + sums
    return known


def score_documents(docs: DataFrame, config: KatzConfig | None = None) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10)."""
    config = config or KatzConfig()
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out(F.col("doc_id")).alias("held"))
    chunks, chunk_path = stored(packed.chunk_documents(texts, config.chunk_bytes, lambda batch: tokenised(batch, config.slab_bytes)), "katz-chunks")
    buckets = packed.bucket_count(packed.total_size(chunks), config.bucket_bytes)

    def each_row(answer):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for key, payload in zip(batch.column("key").to_pylist(), batch.column("payload"), strict=True):
                    yield packed.rows(answer(payload.as_py(), key))
                    tn.give_back()

        return run

    asked = chunks.mapInArrow(each_row(lambda raw, key: Chunk(raw, buckets).ask_words(key)), packed.DDL)
    answers, answer_path = stored(packed.exchange(asked, _count_words(config, buckets)), "katz-words", free=True)
    first = _summary(answers, config)

    def number(key: int, parts: list[tuple[int, int, bytes]]) -> list[tuple[int, int, int, bytes]]:
        raw = next(raw for kind, _, raw in parts if kind == 0)
        return [(key, 0, 0, Chunk(raw, buckets).numbered([(origin, raw) for kind, origin, raw in parts if kind == 1]))]

    together, _ = stored(packed.exchange(chunks.unionByName(answers.where("key >= 0")), number), "katz-numbered", free=True)
    for path in (chunk_path, answer_path):
        drop_path(spark, path)
    known: list[Order] = []
    limit = max(1000, first.tokens // (4 * buckets))

    def opened(parts: list[tuple[int, int, bytes]], orders: list[Order]) -> Stream:
        stream = Stream(next(raw for kind, _, raw in parts if kind == 0), buckets, first)
        for k, order in enumerate(orders, 2):
            stream.learn_grams([(origin, raw) for kind, origin, raw in parts if kind == k], k, first, limit, order)
        return stream

    for k in range(2, config.order + 1):
        if known:
            so_far = list(known)
            asked = packed.exchange(together, lambda key, parts, k=k, so_far=so_far: opened(parts, so_far).ask_grams(key, k, first, limit))
        else:
            asked = together.mapInArrow(each_row(lambda raw, key: Stream(raw, buckets, first).ask_grams(key, 2, first, limit)), packed.DDL)
        answers, _ = stored(packed.exchange(asked, _count_grams(config, k, first, known[-1].d if known else None)), "katz-grams", free=True)
        known.append(_summary(answers, config))
        together = together.unionByName(answers.where("key >= 0"))

    def finish(group: pa.Table) -> pa.Table:
        parts = sorted(zip(group.column("kind").to_pylist(), group.column("origin").to_pylist(), group.column("payload").to_pylist(), strict=True), key=lambda x: x[:2])
        return opened(parts, known).scores(first)

    return together.groupBy("key").applyInArrow(finish, "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")
