"""Quality rules: repetition coverage.

Hashes of word n-grams of several lengths are computed in numpy for a slab of documents at once; the measures are
the characters inside duplicated n-grams and lines, as shares of the characters of all words. Whole texts are used.
Only n-grams whose (n-1)-gram prefix repeats can repeat themselves, so each longer length sorts far fewer keys.

Defined results: a null or empty text has zero words, fails the base rule and has coverage 0; a repeated row gives a
repeated result row; further columns are carried only if asked for.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True


@dataclass(frozen=True)
class RepetitionRules:
    """Limits on shares of word characters, the published values of common web-corpus filters: 20, 18 and 16 % for the most frequent
    2- to 4-grams, 15 % for duplicated 5-grams and a point less for each further word, so that long repeats are allowed least."""

    top: dict[int, float] = field(default_factory=lambda: {2: 0.20, 3: 0.18, 4: 0.16})
    duplicated: dict[int, float] = field(default_factory=lambda: {n: (20 - n) / 100 for n in range(5, 11)})
    line_chars: float = 0.20
    top_count: int = 3  # a most frequent n-gram that occurs less often is no repetition
    min_words: int = 10
    max_window_percent: int = 20
    slab_bytes: int = 1 << 20


BASE = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()), ("n_repeat_words", pa.int64()), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("line_coverage", pa.float64())]


def _schema(rules: RepetitionRules) -> pa.Schema:
    return pa.schema(BASE + [(f"top_{n}", pa.float64()) for n in rules.top] + [(f"coverage_{n}", pa.float64()) for n in rules.duplicated])


def measure(data: np.ndarray, offsets: np.ndarray, rules: RepetitionRules) -> dict[str, np.ndarray]:
    """All measures of the documents of one slab."""
    words = tn.Words(data, offsets)
    n_docs, n_words = words.n_docs, words.counts
    chars = words.code_points() if len(words) else np.empty(0, np.int64)
    run = np.concatenate([[0], np.cumsum(chars)])
    word_chars = run[words.first[1:]] - run[words.first[:-1]]
    share = np.maximum(word_chars, 1)
    marks = np.concatenate([[0], np.cumsum(SYMBOLS[data])])
    out = {"n_words": n_words, "word_chars": word_chars, "n_symbols": marks[offsets[1:]] - marks[offsets[:-1]]}

    lengths = sorted({*rules.top, *rules.duplicated, 5})
    at, key = np.flatnonzero(np.ones(len(words), bool)), words.hash
    salt = salt_of(words.doc)
    for n in range(2, max(lengths) + 1):
        stay = at + n - 1 < len(words)
        at, key = at[stay], key[stay]
        same = words.doc[at] == words.doc[at + n - 1]
        at, key = at[same], key[same]
        key = tn.combine(key, words.hash[at + n - 1])
        size, _ = tn.repeated(key ^ salt[at])
        twice = size > 1
        at, key, size = at[twice], key[twice], size[twice]
        if n in rules.top:
            found = np.where(size >= rules.top_count, size * (run[at + n] - run[at]), 0)
            best = np.zeros(n_docs, np.int64)
            np.maximum.at(best, words.doc[at], found)
            out[f"top_{n}"] = np.minimum(best / share, 1.0)
        if n in rules.duplicated or n == 5:
            step = np.zeros(len(words) + 1, np.int64)
            np.add.at(step, at, 1)
            np.add.at(step, at + n, -1)
            covered = np.cumsum(step[:-1]) > 0
            if n == 5:
                out["n_repeat_words"] = tn.per_doc(covered, words.first)
            if n in rules.duplicated:
                out[f"coverage_{n}"] = tn.per_doc(np.where(covered, chars, 0), words.first) / share

    start, end, doc = tn.lines(data, offsets)
    first, last = np.searchsorted(words.start, start), np.searchsorted(words.start, end)
    filled = last > first
    start, end, doc, first, last = start[filled], end[filled], doc[filled], first[filled], last[filled]
    _, later = tn.repeated(tn.span_hash(data, start, end) ^ salt_of(doc))
    out["n_dup_lines"] = np.bincount(doc[later], minlength=n_docs).astype(np.int64)
    out["line_coverage"] = np.bincount(doc[later], weights=(run[last] - run[first])[later], minlength=n_docs) / share

    out["base_failed"] = (n_words < rules.min_words) | (100 * out["n_repeat_words"] > rules.max_window_percent * n_words)
    kept = ~out["base_failed"] & (out["line_coverage"] <= rules.line_chars)
    for n, limit in rules.top.items():
        kept &= out[f"top_{n}"] <= limit
    for n, limit in rules.duplicated.items():
        kept &= out[f"coverage_{n}"] <= limit
    out["kept"] = kept
    return out


def salt_of(doc: np.ndarray) -> np.ndarray:
    return tn.mix(doc.astype(tn.U) + tn.U(7))


def repetition_coverage(docs: DataFrame, rules: RepetitionRules | None = None) -> DataFrame:
    """One row per document: base counts, coverage of every n-gram length and of lines, and the verdict `kept`."""
    rules = rules or RepetitionRules()
    schema = _schema(rules)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tn.utf8_buffers(batch.column("text"))
            for low, high in tn.slabs(offsets, rules.slab_bytes):
                part = offsets[low : high + 1]
                found = measure(data[part[0] : part[-1]], part - part[0], rules)
                found["doc_id"] = batch.column("doc_id").slice(low, high - low)
                yield pa.RecordBatch.from_arrays([pa.array(found[f.name]).cast(f.type) for f in schema], schema=schema)

    ddl = ", ".join(f"{f.name} {'bigint' if f.type == pa.int64() else 'boolean' if f.type == pa.bool_() else 'double'}" for f in schema)
    return docs.select(F.col("doc_id").cast("bigint"), F.col("text").cast("string")).mapInArrow(run, ddl)
