"""Quality classifier: a sparse rule ensemble.

Small regression trees are boosted on text statistics; every path of every tree becomes a conjunctive rule; a lasso
logistic regression keeps a few rules with weights; the kept rules are compiled into Spark column expressions, so scoring
is one projection over the statistics. Statistics are computed in numpy for a slab of whole documents at once.

Training reads a bounded sample of labelled rows (`max_rows`, chosen by hash order); statistics and scores cover all rows.
Defined results: null and empty texts have zero statistics and get a score like any other; without labels the score is 0.5;
repeated labels of a document count once (the largest); one class alone gives its smoothed share as the score.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltahop.llm import textnum as tn

STATISTICS = ["words", "word_length", "symbols", "marks", "bars", "capitals", "digits", "stops", "other_bytes", "line_words", "repeat_words", "repeat_next", "repeat_windows", "repeat_lines", "distinct_words", "short_words", "long_words"]


def _table(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_CLASS = {"symbols": _table(b"#*$%&<>"), "marks": _table(b"!?"), "bars": _table(b"|"), "capitals": _table(bytes(range(65, 91))), "digits": _table(bytes(range(48, 58))), "stops": _table(b".,;:"), "other_bytes": np.arange(256) >= 128}


def statistics(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Matrix (documents, STATISTICS) of one slab; shares of bytes or words, and log counts."""
    words = tn.Words(data, offsets)
    n_docs, count = words.n_docs, words.counts
    size = np.diff(offsets)
    per_byte, per_word = np.maximum(size, 1), np.maximum(count, 1)
    col = {"words": np.log1p(count), "word_length": tn.per_doc(words.end - words.start, words.first) / per_word}
    for name, table in _CLASS.items():
        run = np.concatenate([[0], np.cumsum(table[data], dtype=np.int32)])
        col[name] = (run[offsets[1:]] - run[offsets[:-1]]) / per_byte
    salt = tn.mix(words.doc.astype(tn.U) + tn.U(11))
    _, later = tn.repeated(words.hash ^ salt)
    col["repeat_words"] = tn.per_doc(later, words.first) / per_word
    col["distinct_words"] = np.log1p(tn.per_doc(~later, words.first))
    same = np.zeros(len(words), bool)
    if len(words) > 1:
        same[1:] = (words.hash[1:] == words.hash[:-1]) & (words.doc[1:] == words.doc[:-1])
    col["repeat_next"] = tn.per_doc(same, words.first) / per_word
    at, key = words.ngram_hash(4)
    _, later = tn.repeated(key ^ salt[at])
    col["repeat_windows"] = np.bincount(words.doc[at[later]], minlength=n_docs) / per_word
    start, end, doc = tn.lines(data, offsets)
    filled = end > start
    start, end, doc = start[filled], end[filled], doc[filled]
    n_lines = np.bincount(doc, minlength=n_docs)
    _, later = tn.repeated(tn.span_hash(data, start, end) ^ tn.mix(doc.astype(tn.U) + tn.U(11)))
    col["repeat_lines"] = np.bincount(doc[later], minlength=n_docs) / np.maximum(n_lines, 1)
    col["line_words"] = np.log1p(count / np.maximum(n_lines, 1))
    length = words.end - words.start
    col["short_words"] = tn.per_doc(length <= 2, words.first) / per_word
    col["long_words"] = tn.per_doc(length >= 12, words.first) / per_word
    return np.column_stack([col[name] for name in STATISTICS]).astype(np.float64) if n_docs else np.empty((0, len(STATISTICS)))


def with_statistics(docs: DataFrame, slab_bytes: int = 512 << 10) -> DataFrame:
    """All columns of docs plus `stats`, a struct of the statistics."""
    schema = T.StructType([*docs.schema.fields, T.StructField("stats", T.StructType([T.StructField(s, T.DoubleType()) for s in STATISTICS]))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tn.utf8_buffers(batch.column("text"))
            blocks = [statistics(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in tn.slabs(offsets, slab_bytes)]
            matrix = np.concatenate(blocks) if blocks else np.empty((0, len(STATISTICS)))
            stats = pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(matrix[:, k])) for k in range(len(STATISTICS))], names=STATISTICS)
            yield pa.RecordBatch.from_arrays([*batch.columns, stats], names=[*batch.schema.names, "stats"])
        tn.give_back()

    return docs.mapInArrow(run, schema)


@dataclass(frozen=True)
class Rule:
    """A conjunction of (statistic, limit, above) conditions."""

    conditions: tuple[tuple[str, float, bool], ...]

    def column(self, stats: str) -> Column:
        out = None
        for name, limit, above in self.conditions:
            test = F.col(f"{stats}.{name}") > limit if above else F.col(f"{stats}.{name}") <= limit
            out = test if out is None else out & test
        return out

    def values(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for name, limit, above in self.conditions:
            v = x[:, STATISTICS.index(name)]
            out &= (v > limit) if above else (v <= limit)
        return out


@dataclass
class RuleEnsemble:
    intercept: float = 0.0
    rules: list[tuple[Rule, float]] = field(default_factory=list)

    def score(self, stats: str = "stats") -> Column:
        """The probability of label 1 as a column expression, without Python."""
        total = F.lit(float(self.intercept))
        for rule, weight in self.rules:
            total = total + F.when(rule.column(stats), F.lit(float(weight))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.intercept)
        for rule, weight in self.rules:
            total += weight * rule.values(x)
        return 1 / (1 + np.exp(-total))


def _grow(bins: np.ndarray, cuts: list[np.ndarray], grad: np.ndarray, hess: np.ndarray, rows: np.ndarray, depth: int, least: int, path: tuple, leaves: list) -> None:
    """Split on the largest gain of a histogram search; collect (path, rows, value) of every leaf and inner node."""
    g, h = grad[rows].sum(), hess[rows].sum()
    leaves.append((path, rows, g / (h + 1.0), depth))
    if depth == 0 or len(rows) < 2 * least:
        return
    best = (1e-6, None, None)
    for k, limits in enumerate(cuts):
        if not len(limits):
            continue
        b = bins[rows, k]
        gs = np.bincount(b, grad[rows], len(limits) + 1).cumsum()[:-1]
        hs = np.bincount(b, hess[rows], len(limits) + 1).cumsum()[:-1]
        ns = np.bincount(b, minlength=len(limits) + 1).cumsum()[:-1]
        gain = gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g * g / (h + 1)
        gain[(ns < least) | (len(rows) - ns < least)] = -1
        top = int(gain.argmax())
        if gain[top] > best[0]:
            best = (gain[top], k, top)
    _, k, cut = best
    if k is None:
        return
    low = bins[rows, k] <= cut
    for side, above in ((rows[low], False), (rows[~low], True)):
        _grow(bins, cuts, grad, hess, side, depth - 1, least, (*path, (STATISTICS[k], float(cuts[k][cut]), above)), leaves)


def extract_rules(x: np.ndarray, y: np.ndarray, trees: int = 30, depth: int = 3, rate: float = 0.3, n_bins: int = 48, least: int = 10) -> list[Rule]:
    """Boost small trees on the logistic loss and return every distinct path as a rule."""
    cuts = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, n_bins + 1)[1:-1])) for k in range(x.shape[1])]
    bins = np.column_stack([np.searchsorted(c, x[:, k], side="left") for k, c in enumerate(cuts)])
    margin = np.full(len(y), math.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    found: dict[Rule, None] = {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        leaves: list = []
        _grow(bins, cuts, y - p, p * (1 - p), np.arange(len(y)), depth, least, (), leaves)
        paths = {path for path, *_ in leaves}
        for path, rows, value, _ in leaves:
            if path:
                found[Rule(path)] = None
            if not any(len(q) > len(path) and q[: len(path)] == path for q in paths):
                margin[rows] += rate * value
    return list(found)


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Weights minimising mean log loss + penalty * |w|, by accelerated proximal gradient; the intercept is free."""
    n, m = z.shape
    mean, scale = z.mean(0), np.maximum(z.std(0), 1e-3)
    zs = (z - mean) / scale
    lip = 0.25 * (np.linalg.norm(zs, 2) ** 2 / n if m else 1.0) + 0.25
    w = v = np.zeros(m)
    b = c = math.log((y.sum() + 1) / (n - y.sum() + 1))
    t = 1.0
    for _ in range(steps):
        r = (1 / (1 + np.exp(-(c + zs @ v))) - y) / n
        w_new = v - zs.T @ r / lip
        w_new = np.sign(w_new) * np.maximum(np.abs(w_new) - penalty / lip, 0)
        b_new = c - r.sum() / lip
        t_new = (1 + math.sqrt(1 + 4 * t * t)) / 2
        v, c = w_new + (t - 1) / t_new * (w_new - w), b_new + (t - 1) / t_new * (b_new - b)
        w, b, t = w_new, b_new, t_new
    raw = w / scale
    return float(b - raw @ mean), raw


def fit_matrix(x: np.ndarray, y: np.ndarray, penalty: float = 0.002, max_rules: int = 60) -> RuleEnsemble:
    if not len(y):
        return RuleEnsemble()
    if y.min() == y.max():
        return RuleEnsemble(math.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    rules = extract_rules(x, y)
    if not rules:
        return RuleEnsemble(math.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    z = np.column_stack([r.values(x) for r in rules]).astype(np.float64)
    _, w = lasso_logistic(z, y, penalty)
    keep = [k for k in np.argsort(-np.abs(w)) if w[k] != 0][:max_rules]
    if not keep:
        return RuleEnsemble(math.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    intercept, w = lasso_logistic(z[:, keep], y, penalty / 4)
    return RuleEnsemble(intercept, [(rules[k], float(w[i])) for i, k in enumerate(keep) if w[i] != 0])


def held_out(doc_id: Column) -> Column:
    """Rows that labels are never learned from: crc32 of the id as text, remainder 2 modulo 4."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", max_rows: int = 12000) -> RuleEnsemble:
    """Fit on at most `max_rows` labelled rows that are not held out; the sample is the first by a hash of doc_id."""
    target = labels.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col(label).cast("double").alias("_y")).where(F.col("_y").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    target = target.groupBy("doc_id").agg(F.max("_y").alias("_y"))
    sample = target.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id")
    texts = texts.groupBy("doc_id", "_y").agg(F.min("text").alias("text"))  # of repeated ids one text
    rows = with_statistics(texts).select("doc_id", "_y", "stats").toPandas()  # max_rows x 17 numbers at most
    rows = rows.sort_values("doc_id", kind="stable")
    x = np.array([[r[s] for s in STATISTICS] for r in rows["stats"]]).reshape(len(rows), len(STATISTICS))
    return fit_matrix(x, rows["_y"].to_numpy(float))


def score_documents(docs: DataFrame, model: RuleEnsemble, threshold: float = 0.7) -> DataFrame:
    """All columns of docs plus score and predicted."""
    kept = [c for c in docs.columns if c not in ("score", "predicted", "stats")]
    scored = with_statistics(docs.select(*kept)).withColumn("score", F.round(model.score(), 9))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int")).drop("stats")
