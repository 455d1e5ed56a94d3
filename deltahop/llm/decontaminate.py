"""Benchmark decontamination by template canonicalisation.

Numbers, capitalised names and units of a text become typed placeholders; windows of the resulting template tokens are looked up
by hash among the windows of all benchmark items. This is done word by word and with runs (a name of several words, a number
and its unit) collapsed into one slot each. Hits of an item at several shifts count together if they lie in order and near each other.
For each alignment, values that recur in the item must mostly be replaced by the same new value, so a question with new numbers and
names is found while chance hits of a template are not; unchanged slots and words that begin a sentence are no evidence against it, and
an alignment in which most of the item is unchanged needs none.

Windows of documents and items meet in a Spark join on their hashes, of any size on both sides; documents send only windows that a
bitmap of the items' hashes, of fixed size, lets pass. The documents and items that meet are then aligned and judged group by group.
Defined results: null and empty texts match nothing; an item of fewer tokens than a window is one window; items without
literal tokens only match unchanged; repeated items and repeated documents give rows of their own; an empty table on either side
gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn
from deltahop.llm.workdir import stored

# Unit words that fill a unit slot.
UNITS = "mm cm m km in ft mi inch inches foot feet yard yards mile miles meter meters metre metres kilometer kilometers kilometre kilometres g kg mg lb lbs oz gram grams kilogram kilograms pound pounds ounce ounces ton tons l ml liter liters litre litres gallon gallons s ms min h second seconds minute minutes hour hours day days week weeks month months year years dollar dollars euro euros cent cents usd eur percent degree degrees celsius fahrenheit mph kph watt watts volt volts joule joules hz khz mhz ghz byte bytes kb mb gb tb".split()

_PUNCTUATION = np.zeros(256, bool)
_PUNCTUATION[list(b"!\"'()*,-.:;<=>?[]_`{|}~#&/\\")] = True
_NUMERIC = np.zeros(256, bool)
_NUMERIC[list(b"0123456789.,:/%+-$^")] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[list(b"0123456789")] = True
_STOP = np.zeros(256, bool)
_STOP[list(b".!?:")] = True
SPREAD = tn.U(0x9E3779B97F4A7C15)
NUMBER, NAME, UNIT = tn.U(1), tn.U(2), tn.U(3)  # template tokens of the slots


@dataclass(frozen=True)
class LeakRules:
    window: int = 8
    literals: int = 4  # literal tokens that a window needs to say anything
    coverage: float = 0.5  # share of an item's tokens inside matching windows
    agreement: float = 0.5  # share of the recurrences of changed values that are replaced alike
    verbatim: float = 0.8  # share of an item's tokens that is a copy whatever the rest is
    slab_bytes: int = 512 << 10
    bits: int = 1 << 25  # of the bitmap, a power of two
    parts: int = 16  # that a window's documents are dealt out to
    pairs: int = 500  # documents and items judged by one task call, about


class Template:
    """Template tokens of a slab: token hash, value hash (what fills a slot), head hash (the value's part that must recur), slot flag,
    flag of the first word of a sentence; words as in textnum."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        w = tn.Words(data, offsets, lower=True)
        self.doc, self.first, self.n_docs = w.doc, w.first, w.n_docs
        start, end = w.start.copy(), w.end.copy()
        while True:
            trim = np.flatnonzero((start < end) & _PUNCTUATION[data[np.minimum(start, len(data) - 1)]]) if len(start) else start
            if not len(trim):
                break
            start[trim] += 1
        while True:
            trim = np.flatnonzero((start < end) & _PUNCTUATION[data[np.maximum(end - 1, 0)]]) if len(start) else start
            if not len(trim):
                break
            end[trim] -= 1
        bare = start == end
        start[bare], end[bare] = w.start[bare], w.end[bare]
        self.value = tn.span_hash(data, start, end, lower=True)
        self.head = self.value
        self.token = self.value.copy()
        if not len(start):
            self.slot = self.initial = self.glued = self.apart = np.empty(0, bool)
            self.number = self.value
            return
        run = lambda flags: np.concatenate([[0], np.cumsum(flags[data], dtype=np.int64)])
        size, digits, numeric = end - start, run(_DIGIT), run(_NUMERIC)
        number = (digits[end] > digits[start]) & (numeric[end] - numeric[start] == size)
        head, follow = data[start], data[np.minimum(start + 1, len(data) - 1)]
        after = data[np.minimum(start + 2, len(data) - 1)]
        plain = (head >= 65) & (head <= 90) & (size > 1) & ((follow >= 97) & (follow <= 122) | (follow >= 128))
        accented = (head == 0xC3) & (follow >= 0x80) & (follow <= 0x9E) & (size > 3) & ((after >= 97) & (after <= 122) | (after >= 128))
        unit = np.isin(self.value, UNIT_HASHES)
        self.token[plain | accented] = NAME
        self.token[unit] = UNIT
        self.token[number] = NUMBER
        self.slot = self.token <= UNIT

        opens = np.concatenate([[True], self.doc[1:] != self.doc[:-1]])
        stops = np.concatenate([[0], np.cumsum(_STOP[data], dtype=np.int64)])
        self.initial = opens | np.concatenate([[False], (stops[w.end] > stops[end])[:-1]])
        self.apart = opens | (start > w.start) | np.concatenate([[False], (end < w.end)[:-1]])
        other = np.append(np.flatnonzero(~_NUMERIC[data]), len(data))
        middle = np.minimum(other[np.searchsorted(other, start)], end)
        self.glued = (middle < end) & (digits[middle] > digits[start]) & np.isin(tn.span_hash(data, middle, end, lower=True), UNIT_HASHES)
        self.number = np.where(self.glued, tn.span_hash(data, start, middle, lower=True), self.value)

    def collapsed(self) -> Template:
        """The same template with one token for the words of a name, and for a number and its units."""
        out = object.__new__(Template)
        token = np.where(self.glued, NUMBER, self.token)
        joined = np.zeros(len(token), bool)
        before, here = token[:-1], token[1:]
        joined[1:] = (here == before) & (here <= NAME) | (here == UNIT) & (before == NUMBER) & ~self.glued[:-1]
        joined &= ~self.apart
        head = np.flatnonzero(~joined)
        within = np.arange(len(token)) - np.repeat(head, np.diff(np.append(head, len(token))))
        out.value = np.add.reduceat(tn.mix(self.value + within.astype(tn.U) * SPREAD), head) if len(head) else self.value
        out.head, out.token, out.doc, out.initial = self.number[head], token[head], self.doc[head], self.initial[head]
        out.first, out.n_docs = np.searchsorted(head, self.first), self.n_docs
        out.slot = out.token <= UNIT
        return out

    def windows(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        m = len(self.token) - n + 1
        if m <= 0:
            return np.empty(0, np.int64), np.empty(0, tn.U)
        at = np.flatnonzero(self.doc[:m] == self.doc[n - 1 :])
        out = self.token[at]
        for k in range(1, n):
            out = tn.combine(out, self.token[at + k])
        return at, out


def _hashes(words: list[str]) -> np.ndarray:
    raw = [w.encode() for w in words]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    return np.sort(tn.span_hash(np.frombuffer(b"".join(raw), np.uint8), offsets[:-1], offsets[1:], lower=True))


UNIT_HASHES = _hashes(UNITS)


class Benchmark:
    """Windows of a block of items, sorted by hash for each window length, word by word and of the collapsed template (`runs`)."""

    def __init__(self, words: Template, ids: list[int | None], rules: LeakRules):
        self.ids = ids
        self._tabulate(words, rules, np.ones(len(ids), bool))
        self.runs = object.__new__(Benchmark)
        runs = words.collapsed()
        # items without literals match unchanged only, which is found word by word
        self.runs._tabulate(runs, rules, np.bincount(runs.doc[~runs.slot], minlength=len(ids)) > 0)

    def _tabulate(self, t: Template, rules: LeakRules, wanted: np.ndarray) -> None:
        self.token, self.value, self.head, self.slot, self.initial, self.first = t.token, t.value, t.head, t.slot, t.initial, t.first
        counts = np.diff(t.first)
        self.tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        literal = np.concatenate([[0], np.cumsum(~t.slot)])
        for n in sorted({min(rules.window, int(c)) for c in counts if c}):
            at, name = t.windows(n)
            item = t.doc[at]
            fit = (np.minimum(counts[item], rules.window) == n) & wanted[item]
            if n == rules.window:
                telling = literal[at + n] - literal[at] >= rules.literals
                any_telling = np.bincount(item[fit & telling], minlength=t.n_docs) > 0
                fit &= telling | ~any_telling[item]
            at, name = at[fit], name[fit]
            order = np.argsort(name, kind="stable")
            self.tables[n] = (name[order], at[order])


def find_leaks(docs: Template, bench: Benchmark, rules: LeakRules) -> list[tuple[int, int, int, float, bool, bool]]:
    """(document row, item row, windows, coverage, exact, leaked) of the best alignment of each pair with a hit."""
    best: dict[tuple[int, int], tuple] = {}
    for template, items in ((docs, bench), (docs.collapsed(), bench.runs)):
        for key, found in _alignments(template, items, rules):
            best[key] = max(best.get(key, (False, -1.0, False, 0)), found)
    return [(d, i, int(n), float(share), bool(exact), bool(leaked)) for (d, i), (leaked, share, exact, n) in sorted(best.items())]


def _alignments(docs: Template, bench: Benchmark, rules: LeakRules) -> Iterator[tuple[tuple[int, int], tuple]]:
    """((document row, item row), (leaked, coverage, exact, windows)) of every shift and every longest chain of shifts."""
    spots, places, sizes = [], [], []
    for n, (name, at) in bench.tables.items():
        where, windows = docs.windows(n)
        low = np.searchsorted(name, windows)
        hit = np.flatnonzero(low < len(name))
        hit = hit[name[low[hit]] == windows[hit]]
        times = np.searchsorted(name, windows[hit], side="right") - low[hit]
        run = np.repeat(low[hit] - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum()) if len(hit) else hit
        spots.append(np.repeat(where[hit], times))
        places.append(at[run])
        sizes.append(np.full(len(run), n))
    if not spots or not sum(map(len, spots)):
        return
    spot, place, size = np.concatenate(spots), np.concatenate(places), np.concatenate(sizes)
    item = np.searchsorted(bench.first, place, side="right") - 1
    order = np.lexsort((place, spot - place, item, docs.doc[spot]))
    spot, place, size, item = spot[order], place[order], size[order], item[order]
    doc, shift = docs.doc[spot], spot - place
    pair = np.concatenate([[True], (doc[1:] != doc[:-1]) | (item[1:] != item[:-1])])
    turn = pair | np.concatenate([[True], shift[1:] != shift[:-1]])
    part = np.flatnonzero(turn | np.concatenate([[True], place[1:] > place[:-1] + size[:-1]]))
    upto = np.append(part[1:], len(spot))
    # passages without a gap at one shift: item tokens from..to, windows
    passages = list(zip(place[part].tolist(), (place[upto - 1] + size[part]).tolist(), shift[part].tolist(), (upto - part).tolist(), strict=True))
    heads = np.flatnonzero(pair[part])
    for low, high in zip(heads.tolist(), np.append(heads[1:], len(part)).tolist(), strict=True):
        key = (int(doc[part[low]]), int(item[part[low]]))
        length = int(bench.first[key[1] + 1] - bench.first[key[1]])
        for chain in _chains(passages[low:high], length):
            yield key, _judged(docs, bench, rules, chain, length)


def _chains(passages: list[tuple[int, int, int, int]], length: int) -> Iterator[list[tuple[int, int, int, int]]]:
    """Passages of each shift; then the chains of most item tokens, in order in both texts and at most an item's length apart."""
    by_shift: dict[int, list] = {}
    for p in passages:
        by_shift.setdefault(p[2], []).append(p)
    yield from by_shift.values()
    if len(by_shift) == 1:
        return
    rows = sorted(passages, key=lambda p: (p[0] + p[2], p[0]))
    total, back = [p[1] - p[0] for p in rows], [-1] * len(rows)
    for i, (start, end, shift, _) in enumerate(rows):
        for j in range(i - 1, -1, -1):
            begun, done, other, _ = rows[j]
            if start + shift - (begun + other) > 2 * length:
                break
            if begun > start or done >= end or done + other >= end + shift or start + shift - (done + other) > length:
                continue
            gain = end - max(start, done, done + other - shift)
            if total[j] + gain > total[i]:
                total[i], back[i] = total[j] + gain, j
    inner = set(back)
    for i in range(len(rows)):
        if i in inner or back[i] < 0:
            continue
        chain, k = [], i
        while k >= 0:
            start, end, shift, n = rows[k]
            if back[k] >= 0:
                _, done, other, _ = rows[back[k]]
                start = max(start, done, done + other - shift)
            chain.append((start, end, shift, n))
            k = back[k]
        yield chain[::-1]


def _judged(docs: Template, bench: Benchmark, rules: LeakRules, chain: list[tuple[int, int, int, int]], length: int) -> tuple[bool, float, bool, int]:
    """(leaked, coverage, exact, windows) of an alignment."""
    ours = np.concatenate([np.arange(a, b) for a, b, _, _ in chain])
    theirs = np.concatenate([np.arange(a + shift, b + shift) for a, b, shift, _ in chain])
    slot = bench.slot[ours]
    same = ~slot | (bench.value[ours] == docs.value[theirs])
    exact = bool(same.all()) and len({p[2] for p in chain}) == 1
    telling = exact or bool((~slot).any())
    vote = ~same & ~bench.initial[ours] & ~docs.initial[theirs]
    pairs, times = np.unique(np.stack([bench.head[ours][vote], docs.head[theirs][vote]]), axis=1, return_counts=True)
    begins = np.flatnonzero(np.concatenate([[True], pairs[0, 1:] != pairs[0, :-1]])) if len(times) else []
    agree = int((np.maximum.reduceat(times, begins) - 1).sum()) if len(times) else 0
    recur = int(times.sum()) - len(begins)
    consistent = agree >= rules.agreement * recur
    verbatim = np.count_nonzero(same) >= rules.verbatim * length
    share = len(ours) / length
    return bool(share >= rules.coverage and telling and (consistent or verbatim)), share, exact, sum(p[3] for p in chain)


RESULT = "doc_id bigint, item_id bigint, n_windows bigint, coverage double, exact boolean, leaked boolean"
FORMS = (tn.U(0), tn.U(0x5A5A5A5A5A5A5A5A))  # tells windows of words and of collapsed templates apart


def _marked(positions: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(bits, bool)
    out[positions] = True
    return np.packbits(out)


def _items(benchmark: DataFrame) -> DataFrame:
    """(item_no, item_id, text) of the items that have a text, written once so that their numbers stay."""
    rows = benchmark.select(F.monotonically_increasing_id().alias("item_no"), F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text"))
    return stored(rows.where(F.col("text").isNotNull()), "leak-items")[0]


def _item_windows(items: DataFrame, rules: LeakRules) -> DataFrame:
    """(name, size, item_no): window hashes of both forms of every item."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tn.utf8_buffers(batch.column("text"))
            for low, high in tn.slabs(offsets, rules.slab_bytes):
                cut = offsets[low : high + 1]
                bench = Benchmark(Template(data[cut[0] : cut[-1]], cut - cut[0]), [None] * (high - low), rules)
                numbers = batch.column("item_no").to_numpy()[low:high]
                for form, tables in zip(FORMS, (bench, bench.runs), strict=True):
                    for n, (name, at) in tables.tables.items():
                        item = np.searchsorted(tables.first, at, side="right") - 1
                        yield pa.RecordBatch.from_arrays([pa.array((name ^ form).view(np.int64)), pa.array(np.full(len(name), n, np.int32)), pa.array(numbers[item])], names=["name", "size", "item_no"])

    return items.mapInArrow(run, "name bigint, size int, item_no bigint").distinct()


def _doc_windows(texts: DataFrame, sizes: list[int], marks: np.ndarray, rules: LeakRules) -> DataFrame:
    """(name, doc_key): the windows of each document whose place in the bitmap is marked, each once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tn.utf8_buffers(batch.column("text"))
            keys = batch.column("doc_key").to_numpy()
            for low, high in tn.slabs(offsets, rules.slab_bytes):
                cut = offsets[low : high + 1]
                words = Template(data[cut[0] : cut[-1]], cut - cut[0])
                for form, template in zip(FORMS, (words, words.collapsed()), strict=True):
                    for n in sizes:
                        at, name = template.windows(n)
                        name = name ^ form
                        spot = name & tn.U(8 * len(marks) - 1)
                        hit = np.flatnonzero((marks[(spot >> tn.U(3)).astype(np.int64)] >> (7 - (spot & tn.U(7))).astype(np.uint8)) & 1)
                        if len(hit):
                            row, name = template.doc[at[hit]], name[hit].view(np.int64)
                            order = np.lexsort((name, row))
                            fresh = np.ones(len(order), bool)
                            fresh[1:] = (row[order][1:] != row[order][:-1]) | (name[order][1:] != name[order][:-1])
                            pick = order[fresh]
                            yield pa.RecordBatch.from_arrays([pa.array(name[pick]), pa.array(keys[low + row[pick]])], names=["name", "doc_key"])
            tn.give_back()

    return texts.mapInArrow(run, "name bigint, doc_key bigint")


def _keyed(docs: DataFrame) -> DataFrame:
    """(doc_key, doc_id, text); equal rows have equal keys, and equal results."""
    plain = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return plain.select(document_key().alias("doc_key"), "doc_id", "text")


def document_key() -> Column:
    return F.xxhash64(F.col("doc_id").cast("bigint"), F.col("text").cast("string"))


def candidates(docs: DataFrame, items: DataFrame, rules: LeakRules) -> DataFrame:
    """(doc_key, item_no) of documents and items with a common window: a hash join of their window tables.

    Documents send only windows that a bitmap of fixed size (`bits`) marks as a possible item's; the join decides.
    """
    windows, _ = stored(_item_windows(items, rules), "leak-windows")
    sizes = sorted(r["size"] for r in windows.select("size").distinct().collect())  # at most `window` values
    if not sizes:
        return docs.sparkSession.createDataFrame([], "doc_key bigint, item_no bigint")
    spots = windows.select(F.col("name").bitwiseAND(F.lit(rules.bits - 1)).cast("int").alias("spot")).distinct().toPandas()["spot"]  # at most `bits`
    found = _doc_windows(_keyed(docs).select("doc_key", "text"), sizes, _marked(spots.to_numpy(), rules.bits), rules)
    # documents with one window, a third of all perhaps, are dealt out; the items' table is the small side and goes to every part
    found = found.withColumn("part", F.pmod("doc_key", F.lit(rules.parts)).cast("int"))
    spread = windows.select("name", "item_no", F.explode(F.sequence(F.lit(0), F.lit(rules.parts - 1))).alias("part"))
    return found.join(spread, ["name", "part"]).select("doc_key", "item_no").distinct()


def _judge_pairs(docs: DataFrame, items: DataFrame, pairs: DataFrame, rules: LeakRules) -> DataFrame:
    """The rows of leaks, with doc_key, for the documents and items of the pairs, some hundred pairs a task call."""
    count = pairs.count()
    groups = max(1, -(-count // rules.pairs))
    group = F.pmod("doc_key", F.lit(groups)).cast("int").alias("group")
    keyed = _keyed(docs)
    once = keyed.join(pairs.select("doc_key").distinct(), "doc_key", "left_semi").groupBy("doc_key").agg(F.first("doc_id").alias("doc_id"), F.first("text").alias("text"), F.count("*").alias("times"))
    texts = once.select(group, "doc_key", "doc_id", "text", "times")
    wanted = pairs.select(group, "item_no").distinct().join(items, "item_no")

    def judge(ours: pa.Table, theirs: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if ours.num_rows and theirs.num_rows:
            data, offsets = tn.utf8_buffers(theirs.column("text"))
            bench = Benchmark(Template(data, offsets), theirs.column("item_id").to_pylist(), rules)
            ids, keys, times = (ours.column(c).to_pylist() for c in ("doc_id", "doc_key", "times"))
            data, offsets = tn.utf8_buffers(ours.column("text"))
            for low, high in tn.slabs(offsets, rules.slab_bytes):
                cut = offsets[low : high + 1]
                template = Template(data[cut[0] : cut[-1]], cut - cut[0])
                rows += [(keys[low + d], times[low + d], ids[low + d], bench.ids[i], *rest) for d, i, *rest in find_leaks(template, bench, rules)]
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.bool_())
        cols = list(zip(*rows, strict=True)) if rows else [[]] * len(kinds)
        names = ["doc_key", "times", "doc_id", "item_id", "n_windows", "coverage", "exact", "leaked"]
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    judged = texts.groupBy("group").cogroup(wanted.groupBy("group")).applyInArrow(judge, f"doc_key bigint, times bigint, {RESULT}")
    return judged.withColumn("times", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("times")))).drop("times")


def leaks(docs: DataFrame, benchmark: DataFrame, rules: LeakRules | None = None) -> DataFrame:
    """A row for each document and item with a common template window."""
    return _leaks(docs, benchmark, rules or LeakRules()).drop("doc_key")


def _leaks(docs: DataFrame, benchmark: DataFrame, rules: LeakRules) -> DataFrame:
    items = _items(benchmark)
    pairs, _ = stored(candidates(docs, items, rules), "leak-pairs")
    return _judge_pairs(docs, items, pairs, rules)


def without_leaks(docs: DataFrame, benchmark: DataFrame, rules: LeakRules | None = None) -> DataFrame:
    """The documents, all their columns unchanged, in which no item leaked."""
    gone, _ = stored(_leaks(docs, benchmark, rules or LeakRules()).where("leaked").select(F.col("doc_key").alias("leaked_key")).distinct(), "leak-documents")
    return docs.join(gone, document_key() == gone["leaked_key"], "left_anti")
