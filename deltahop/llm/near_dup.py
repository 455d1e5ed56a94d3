"""MinHash near-dedup with odd sketches.

Whole texts become sets of word shingles. MinHash samples give band keys for candidates and are folded into a parity bitmap
(odd sketch) per text; the population count of the XOR of two bitmaps estimates how many samples differ and drops
candidates far below the limit. What stays is confirmed on the full sets.

    1  texts with equal sets form a class; only one of each class goes on
    2  in every band bucket each class meets the smallest one; each class keeps the partner it shares most buckets with
    3  confirmed links give components; in buckets that still hold several components all pairs across them are looked at
       through parity bitmaps of the full sets: the XOR of two has at most as many bits as the sets differ by, so a pair whose
       count is too high is no link, without loss; bitmaps have two bits or more per shingle and fold to smaller ones
    4  for a few rounds each class offers its closest partner of another component alone, which joins groups whose
       members are linked without listing their pairs; then all pairs left are confirmed, and components are joined

Step 3 looks at every candidate pair whose ends aren't connected already, so no link that joins components is lost, while the
pairs within a connected group are never listed. Large buckets are dealt out as pairs of blocks of bounded size. With 32 bands of 4 samples a pair at similarity 0.8 shares no bucket
with probability 5e-8.

Defined results: null, empty and wordless texts have an empty set and link with nothing; texts with fewer words than a shingle
have their whole word sequence as one; rows that repeat an id count as one document of that id; a null id never names a
component; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltahop.llm import textnum as tn
from deltahop.llm.components import connected_components
from deltahop.llm.workdir import drop_path, stored


LARGE = 1000  # a bucket with more than one part in so many of all members is joined by broadcast


@dataclass(frozen=True)
class NearDupConfig:
    shingle: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 4
    sketch_bits: int = 256
    slab_bytes: int = 1 << 20
    members: int = 200  # links confirmed by one task call
    rounds: int = 2  # of closest partners
    block: int = 3000  # members of a bucket compared by one task call
    seed: int = 5

    @property
    def samples(self) -> int:
        return self.bands * self.rows

    @property
    def most_odd_bits(self) -> int:
        """Odd bits that a pair at the limit exceeds with probability below 1e-9."""
        k, n, miss = self.samples, self.sketch_bits, 1 - self.percent / 100
        differ = min(k, k * miss + 6.5 * (k * miss * (1 - miss)) ** 0.5)
        mean = n / 2 * (1 - (1 - 2 / n) ** (2 * differ))
        return int(mean + 4 * (n / 4) ** 0.5)


def shingle_sets(words: tn.Words, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first): the distinct shingles of document k are hashes[first[k]:first[k+1]], ascending."""
    at, key = words.ngram_hash(n)
    doc = words.doc[at]
    short = np.flatnonzero((words.counts > 0) & (words.counts < n))
    if len(short):
        whole = words.hash[words.first[short]]
        for k in range(1, n - 1):
            more = words.counts[short] > k
            whole[more] = tn.combine(whole[more], words.hash[words.first[short][more] + k])
        doc, key = np.concatenate([doc, short]), np.concatenate([key, tn.mix(whole + tn.U(n))])
    order = np.lexsort((key, doc))
    doc, key = doc[order], key[order]
    keep = np.ones(len(key), bool)
    keep[1:] = (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])
    doc, key = doc[keep], key[keep]
    return key, np.searchsorted(doc, np.arange(words.n_docs + 1))


def _segments(values: np.ndarray, first: np.ndarray, ufunc, empty) -> np.ndarray:
    out = np.full(len(first) - 1, empty, values.dtype)
    full = np.flatnonzero(np.diff(first))
    if len(full):
        out[full] = ufunc.reduceat(values, first[full])
    return out


def minhash(key: np.ndarray, first: np.ndarray, config: NearDupConfig) -> np.ndarray:
    """(documents, samples) smallest values of as many 32-bit hash functions; empty sets have the largest value."""
    rng = np.random.default_rng(config.seed)
    a = (rng.integers(0, 1 << 32, config.samples, np.uint64) | np.uint64(1)).astype(np.uint32)
    b = rng.integers(0, 1 << 32, config.samples, np.uint64).astype(np.uint32)
    x = (key >> tn.U(32)).astype(np.uint32)
    full = np.flatnonzero(np.diff(first))
    out = np.full((config.samples, len(first) - 1), 0xFFFFFFFF, np.uint32)
    for k in range(config.samples if len(full) else 0):
        out[k, full] = np.minimum.reduceat(x * a[k] + b[k], first[full])
    return out.T


def odd_sketch(samples: np.ndarray, bits: int) -> np.ndarray:
    """Parity bitmaps: sample i toggles the bit that a hash of (i, value) names."""
    n, k = samples.shape
    spot = tn.mix(samples.astype(tn.U) + (np.arange(k, dtype=tn.U) << tn.U(32))) % tn.U(bits)
    flat = np.bincount((np.arange(n)[:, None] * bits + spot.astype(np.int64)).ravel(), minlength=n * bits)
    return np.packbits((flat & 1).astype(np.uint8).reshape(n, bits), axis=1)


def band_keys(samples: np.ndarray, config: NearDupConfig) -> np.ndarray:
    """(documents, bands) signed 64-bit keys."""
    n = len(samples)
    cube = samples.reshape(n, config.bands, config.rows).astype(tn.U)
    out = np.broadcast_to(np.arange(config.bands, dtype=tn.U), (n, config.bands)).copy()
    for r in range(config.rows):
        out = tn.combine(out, cube[:, :, r])
    return out.view(np.int64)


def set_identity(key: np.ndarray, first: np.ndarray) -> np.ndarray:
    """A 64-bit name of each set, from two independent sums over its members and its size."""
    one = _segments(tn.mix(key), first, np.add, 0)
    two = _segments(tn.mix(key ^ tn.U(0xA5A5A5A5A5A5A5A5)), first, np.add, 0)
    return tn.combine(tn.combine(one, two), np.diff(first).astype(tn.U)).view(np.int64)


def _each_slab(batches: Iterator[pa.RecordBatch], config: NearDupConfig):
    for batch in batches:
        data, offsets = tn.utf8_buffers(batch.column("text"))
        for low, high in tn.slabs(offsets, config.slab_bytes):
            part = offsets[low : high + 1]
            words = tn.Words(data[part[0] : part[-1]], part - part[0], lower=True)
            key, first = shingle_sets(words, config.shingle)
            yield batch, low, high, key, first
    tn.give_back()


def signatures(docs: DataFrame, config: NearDupConfig) -> DataFrame:
    """(doc_id, n_shingles, node, bands, sketch); node names the class of equal sets and is null for empty ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, low, high, key, first in _each_slab(batches, config):
            samples = minhash(key, first, config)
            size = np.diff(first)
            bands = band_keys(samples, config)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id").slice(low, high - low),
                    pa.array(size.astype(np.int64)),
                    pa.array(set_identity(key, first), mask=size == 0),
                    pa.ListArray.from_arrays(pa.array((np.arange(len(size) + 1) * config.bands).astype(np.int32)), pa.array(bands.ravel())),
                    pa.array([s.tobytes() for s in odd_sketch(samples, config.sketch_bits)], pa.binary()),
                ],
                names=["doc_id", "n_shingles", "node", "bands", "sketch"],
            )

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id bigint, n_shingles bigint, node bigint, bands array<bigint>, sketch binary")


def _texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    ids = wanted.select(F.col("doc_id").alias("_id")).distinct()
    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.join(ids, F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")


def _sets(docs: DataFrame, wanted: DataFrame, config: NearDupConfig) -> DataFrame:
    """(node, members, bits) of the wanted nodes (node, doc_id): six bytes of every shingle hash, ascending, and a bitmap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, _, key, first in _each_slab(batches, config):
            node = set_identity(key, first)
            full = np.flatnonzero(np.diff(first))
            blobs = [(np.sort(key[first[k] : first[k + 1]] >> tn.U(16))).view(np.uint8).reshape(-1, 8)[:, :6].tobytes() for k in full]
            bits = [parity_bitmap(key[first[k] : first[k + 1]]).tobytes() for k in full]
            yield pa.RecordBatch.from_arrays([pa.array(node[full]), pa.array(blobs, pa.binary()), pa.array(bits, pa.binary())], names=["node", "members", "bits"])

    made = _texts_of(docs, wanted).mapInArrow(run, "node bigint, members binary, bits binary")
    return made.groupBy("node").agg(F.first("members").alias("members"), F.first("bits").alias("bits"))


def parity_bitmap(key: np.ndarray) -> np.ndarray:
    """Parity of the number of members at each of n places, n a power of two of at least two bits a member."""
    n = max(64, 1 << int(2 * len(key) - 1).bit_length())
    return np.packbits((np.bincount((key & tn.U(n - 1)).astype(np.int64), minlength=n) & 1).astype(np.uint8), bitorder="little")


def _possible(bits: list[np.ndarray], size: np.ndarray, comp: np.ndarray, block: np.ndarray, one: int, two: int, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, distance) of pairs of different components, from blocks one and two, whose bitmaps leave the limit possible."""
    width = np.array([len(b) for b in bits])
    stack = {w: np.stack([bits[i] for i in np.flatnonzero(width == w)]) for w in np.unique(width)}
    for w, x in stack.items():
        ix = np.flatnonzero(width == w)
        for v in (w, 2 * w):
            if v not in stack:
                continue
            iy, y = np.flatnonzero(width == v), stack[v]
            if v != w:
                y = y[:, :w] ^ y[:, w:]
            x8, y8 = np.ascontiguousarray(x).view(np.uint64), np.ascontiguousarray(y).view(np.uint64)
            step = max(1, (4 << 20) // max(1, y8.size))
            for low in range(0, len(ix), step):
                i = ix[low : low + step]
                odd = np.bitwise_count(x8[low : low + step, None, :] ^ y8[None]).sum(-1, dtype=np.int64)
                fit = odd * (100 + percent) <= (size[i][:, None] + size[iy][None]) * (100 - percent)
                fit &= comp[i][:, None] != comp[iy][None]
                if v == w:
                    fit &= i[:, None] < iy[None]
                if one != two:
                    fit &= block[i][:, None] != block[iy][None]
                a, b = np.nonzero(fit)
                if len(a):
                    yield i[a], iy[b], odd[a, b] / (size[i[a]] + size[iy[b]])


def across_components(placed: DataFrame, nodes: DataFrame, sets: DataFrame, config: NearDupConfig, closest: bool) -> DataFrame:
    """Pairs (a, b) of different components that share a band bucket and whose full sets may reach the limit.

    placed: (band, size, node, comp) of the buckets that hold several components. closest: only each node's closest partner.
    """
    member = placed.withColumn("n", F.ceil(F.col("size") / config.block).cast("int")).withColumn("block", F.pmod(F.xxhash64("node"), F.col("n")).cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda k: F.struct(F.least(k, F.col("block")).alias("one"), F.greatest(k, F.col("block")).alias("two")))
    dealt = member.withColumn("pair", F.explode(pair)).select("band", "pair.one", "pair.two", "block", "node", "comp")
    full = dealt.join(nodes.select("node", "n_shingles", "bands"), "node").join(sets.select("node", "bits"), "node")

    def run(group: pa.Table) -> pa.Table:
        node = group.column("node").to_numpy()
        bits = [np.frombuffer(b, np.uint8) for b in group.column("bits").to_pylist()]
        size, comp, block = (group.column(c).to_numpy() for c in ("n_shingles", "comp", "block"))
        keys = np.stack([np.asarray(b) for b in group.column("bands").to_pylist()])
        here = int(np.flatnonzero(keys[0] == group.column("band")[0].as_py())[0])
        best, partner, kept = np.full(len(node), np.inf), np.full(len(node), -1), [(np.empty(0, np.int64),) * 2]
        for i, j, far in _possible(bits, size, comp, block, group.column("one")[0].as_py(), group.column("two")[0].as_py(), config.percent):
            # a pair counts in the first of its common buckets alone
            own = (keys[i] == keys[j]).argmax(1) == here
            i, j, far = i[own], j[own], far[own]
            if not len(i):
                continue
            if not closest:
                kept.append((i, j))
                continue
            for x, y in ((i, j), (j, i)):
                order = np.lexsort((node[y], far, x))
                x, y, d = x[order], y[order], far[order]
                head = np.concatenate([[True], x[1:] != x[:-1]])
                x, y, d = x[head], y[head], d[head]
                closer = d < best[x]
                best[x[closer]], partner[x[closer]] = d[closer], y[closer]
        if closest:
            i = np.flatnonzero(partner >= 0)
            return pa.table({"a": node[i], "b": node[partner[i]], "far": best[i]})
        i, j = (np.concatenate(c) for c in zip(*kept, strict=True))
        return pa.table({"a": node[i], "b": node[j], "far": np.zeros(len(i))})

    found = full.groupBy("band", "one", "two").applyInArrow(run, "a bigint, b bigint, far double")
    if closest:
        found = found.groupBy("a").agg(F.min_by("b", F.struct("far", "b")).alias("b"))
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _unpack(blob: bytes) -> np.ndarray:
    wide = np.zeros((len(blob) // 6, 8), np.uint8)
    wide[:, :6] = np.frombuffer(blob, np.uint8).reshape(-1, 6)
    return wide.view(tn.U).ravel()


def confirm(pairs: DataFrame, sets: DataFrame, config: NearDupConfig) -> DataFrame:
    """The pairs (a, b) whose full sets reach the limit. Partners of one `a` are dealt out in groups of bounded size."""
    many = pairs.groupBy("a").agg(F.ceil(F.count("*") / config.members).cast("int").alias("parts"))
    spread = pairs.join(many, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int").alias("part"))
    sets = sets.select("node", "members")
    theirs = spread.join(sets.withColumnRenamed("node", "b"), "b").select("a", "part", "b", "members")
    own = many.select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).join(sets.withColumnRenamed("node", "a"), "a")
    rows = theirs.unionByName(own.select("a", "part", F.lit(None).cast("bigint").alias("b"), "members"))
    percent = config.percent

    def run(group: pa.Table) -> pa.Table:
        a, b, members = group.column("a")[0].as_py(), group.column("b").to_pylist(), group.column("members")
        if None not in b:
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        mine = _unpack(members[b.index(None)].as_py())
        out = []
        for other, blob in zip(b, members, strict=True):
            if other is not None:
                theirs = _unpack(blob.as_py())
                at = np.minimum(np.searchsorted(mine, theirs), len(mine) - 1)
                both = int((mine[at] == theirs).sum())
                if 100 * both >= percent * (len(mine) + len(theirs) - both):
                    out.append(other)
        return pa.table({"a": pa.array([a] * len(out), pa.int64()), "b": pa.array(out, pa.int64())})

    return rows.groupBy("a", "part").applyInArrow(run, "a bigint, b bigint")


def _likely(pairs: DataFrame, nodes: DataFrame, config: NearDupConfig) -> DataFrame:
    """Candidate pairs that their odd sketches and set sizes leave possible."""
    side = lambda n: nodes.select(F.col("node").alias(n), F.col("n_shingles").alias(f"n_{n}"), F.col("sketch").alias(f"s_{n}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b")
    both = both.where(F.least("n_a", "n_b") * 100 >= F.greatest("n_a", "n_b") * config.percent)
    hexed = lambda c, k: F.conv(F.substring(F.hex(c), 1 + 12 * k, 12), 16, 10).cast("bigint")
    words = -(-config.sketch_bits // 48)
    odd = sum((F.bit_count(hexed("s_a", k).bitwiseXOR(hexed("s_b", k))) for k in range(words)), F.lit(0))
    return both.where(odd <= config.most_odd_bits).select("a", "b")


def near_duplicates(docs: DataFrame, config: NearDupConfig | None = None) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    config = config or NearDupConfig()
    signed, _ = stored(signatures(docs, config), "near-signatures")
    full = signed.where(F.col("node").isNotNull())
    # Any row of a class has the same bands and sketch; ids and counts need no text.
    nodes, _ = stored(
        full.groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch")),
        "near-nodes",
    )
    spread = nodes.select("node", F.explode("bands").alias("band"))
    buckets, bucket_path = stored(
        spread.groupBy("band").agg(F.min("node").alias("a"), F.max("node").alias("high"), F.count("*").alias("size")).where("a <> high").select("band", "a", "size"),
        "near-buckets",
    )
    # Buckets above a thousandth of all members are fewer than a thousand, whatever the input: their members join without a shuffle.
    large = (buckets.agg(F.sum("size")).first()[0] or 0) / LARGE
    hot = F.broadcast(buckets.where(F.col("size") > large))
    cold = spread.join(hot.select("band"), "band", "left_anti").join(buckets.where(F.col("size") <= large), "band")
    shared, shared_path = stored(spread.join(hot, "band").unionByName(cold).select("band", "size", "a", F.col("node").alias("b")), "near-shared", free=True)
    drop_path(docs.sparkSession, bucket_path)

    star = shared.where("a <> b").groupBy("a", "b").agg(F.count("*").alias("n"))
    star, star_path = stored(_likely(star.select("a", "b", "n"), nodes, config).join(star, ["a", "b"]).groupBy("b").agg(F.max_by("a", F.struct("n", F.negative("a"))).alias("a")).select("a", "b"), "near-star")
    ends = lambda pairs: pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct()
    sets = lambda pairs: _sets(docs, nodes.join(ends(pairs), "node", "left_semi").select("node", "doc_id"), config)
    links, links_path = stored(confirm(star, sets(star), config), "near-links", free=True)
    used = [shared_path, star_path, links_path]
    comps = connected_components(links)

    members = shared.select("band", "size", F.col("b").alias("node"))

    def contested(comps: DataFrame) -> DataFrame:
        every, path = stored(members.join(comps, "node", "left").select("band", "size", "node", F.coalesce("comp", "node").alias("comp")), "near-members")
        mixed = every.groupBy("band", "size").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y").select("band", "size")
        hot = F.broadcast(mixed.where(F.col("size") > large).select("band"))
        some = every.where(F.col("size") > large).join(hot, "band", "left_semi")
        rest = every.where(F.col("size") <= large).join(mixed.where(F.col("size") <= large).select("band"), "band", "left_semi")
        out = stored(some.unionByName(rest), "near-placed")
        drop_path(docs.sparkSession, path)
        return out

    placed, placed_path = contested(comps)
    done = star.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    wanted = nodes.join(placed.select("node").distinct(), "node", "left_semi").select("node", "doc_id")
    full_sets, sets_path = stored(_sets(docs, wanted, config), "near-sets", free=True)
    turns, closest = 0, True
    while True:
        pairs, pairs_path = stored(across_components(placed, nodes, full_sets, config, closest).join(done, ["a", "b"], "left_anti"), "near-pairs")
        more, more_path = stored(confirm(pairs, full_sets, config), "near-more", free=True)
        used += [pairs_path, more_path]
        links, done, turns = links.unionByName(more), done.unionByName(pairs), turns + 1
        found = more.limit(1).count() > 0
        if found:
            comps = connected_components(links)
        if not closest:
            break
        if found:
            drop_path(docs.sparkSession, placed_path)
            placed, placed_path = contested(comps)
        closest = found and turns < config.rounds
    for path in (*used, placed_path, sets_path):
        drop_path(docs.sparkSession, path)
    named = nodes.select("node", "doc_id").join(comps, "node", "left").select("node", "doc_id", F.coalesce("comp", "node").alias("comp"))
    least = named.groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    by_node = named.join(least, "comp").select("node", "component_id")
    out = signed.select("doc_id", "n_shingles", "node").join(by_node, "node", "left")
    component = F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(False)).alias("kept"))
