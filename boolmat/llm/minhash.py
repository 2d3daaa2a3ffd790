"""Near-duplicate documents by MinHash, banding, verification on full sets and connected components.

1. Every text becomes its set of word shingles, many universal hash minima over that set, one key per band of minima,
   a 128-bit fingerprint of the set and one bit per minimum.
2. Documents with equal sets form a class; only classes go on, named by their smallest document id.
3. Classes that share a band key are candidates. No bucket is turned into all its pairs: first every member is compared
   with the bucket's smallest one; then, in buckets whose members are not yet in one component, members outside the
   largest component are compared with the members of other components, in large buckets block by block without a row
   per pair. So every pair of a bucket is either verified or already known to be connected.
4. Candidates are sifted by size and by the bits, then verified by intersecting full shingle sets.
5. Components come from alternating large-star and small-star steps.

The number of bands follows from the threshold, so that a pair at it is missed with a probability of at most MISSED.

Defined cases: a text without words (null, empty, blanks) has no shingles and links with nothing; fewer words than a
shingle give one shingle of all words; equal ids are one node; a null id is a component of its own (null, kept).
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, log, log1p

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import files_for, mixed, remove_table, shingle_hashes, slices, text_buffers, written

#: Bands (for 85 percent) and minima per band; the largest probability of missing a pair at the threshold.
BANDS, ROWS, MISSED = 26, 5, 2.5e-7
#: Open buckets of up to this many members are compared by a join; larger ones by blocks of so many members on each side.
SMALL_BUCKET, ASKED, HELD = 32, 256, 1024
#: Above this number of document ids a table of them is joined by a shuffle instead of a broadcast (16 bytes each).
BROADCAST_IDS = 1_000_000
#: Edges that a file of a table between the steps of connected() holds before another one is begun.
EDGES_A_FILE = 100_000
_SIGNATURE = "doc_id bigint, n bigint, f1 bigint, f2 bigint, bands array<bigint>, bits array<bigint>"


def bands_for(percent: int, rows: int = ROWS) -> int:
    """The fewest bands of `rows` minima that miss a pair at the threshold with a probability of at most MISSED."""
    hit = (percent / 100) ** rows
    return 1 if hit >= 1 else ceil(log(MISSED) / log1p(-hit))


def _sets(raw: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct shingle hashes of all texts, first index per text and the end)."""
    base = offsets[0]
    hashes, owners, _ = shingle_hashes(raw[base : offsets[-1]], offsets - base, size)
    order = np.lexsort((hashes, owners))
    hashes, owners = hashes[order], owners[order]
    fresh = np.ones(len(hashes), bool)
    fresh[1:] = (hashes[1:] != hashes[:-1]) | (owners[1:] != owners[:-1])
    hashes, owners = hashes[fresh], owners[fresh]
    return hashes, np.concatenate([[0], np.cumsum(np.bincount(owners, minlength=len(offsets) - 1))])


class Signer:
    """Universal hash minima: the smallest of a * x + b modulo 2**64, a odd, for bands * rows pairs (a, b)."""

    def __init__(self, bands: int = BANDS, rows: int = ROWS, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.bands, self.rows = bands, rows
        self.a = rng.integers(0, 1 << 63, bands * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.b = rng.integers(0, 1 << 63, bands * rows, dtype=np.uint64)

    def sign(self, hashes: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, ...]:
        """(sizes, fingerprint 1, fingerprint 2, band keys, packed bits) of all sets; empty sets get zeros."""
        sizes = np.diff(first)
        full = np.flatnonzero(sizes)
        n = len(sizes)
        f1, f2 = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        keys, bits = np.zeros((n, self.bands), np.uint64), np.zeros((n, -(-self.bands * self.rows // 64)), np.uint64)
        if len(full):
            begin = first[full]
            f1[full] = np.add.reduceat(mixed(hashes ^ np.uint64(0x1234567)), begin)
            f2[full] = np.add.reduceat(mixed(hashes ^ np.uint64(0x7654321)), begin)
            key, work = np.zeros(len(full), np.uint64), np.empty_like(hashes)
            for i, (a, b) in enumerate(zip(self.a, self.b, strict=True)):
                np.multiply(hashes, a, out=work)
                np.add(work, b, out=work)
                least = np.minimum.reduceat(work, begin)
                key = mixed(key * np.uint64(31) + least)
                bits[full, i // 64] |= (mixed(least) & np.uint64(1)) << np.uint64(i % 64)
                if i % self.rows == self.rows - 1:
                    keys[full, i // self.rows] = mixed(key + np.uint64(i))
                    key = np.zeros(len(full), np.uint64)
        return sizes, f1, f2, keys, bits


def signatures(docs: DataFrame, size: int, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, n, f1, f2, bands, bits) for every row of (doc_id, text)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(bands, rows)
        for batch in batches:
            raw, offsets = text_buffers(batch.column(1))
            for a, b in slices(offsets):
                n, f1, f2, keys, bits = signer.sign(*_sets(raw, offsets[a : b + 1], size))
                lists = [pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.ravel().view(np.int64))) for x in (keys, bits)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(n, pa.int64()), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), *lists], names=["doc_id", "n", "f1", "f2", "bands", "bits"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, _SIGNATURE)


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    """(doc_id, f1, items) for every row: the sorted distinct shingle hashes, and the first fingerprint of the set."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, offsets = text_buffers(batch.column(1))
            for a, b in slices(offsets):
                hashes, first = _sets(raw, offsets[a : b + 1], size)
                f1 = np.zeros(b - a, np.uint64)
                full = np.flatnonzero(np.diff(first))
                if len(full):
                    f1[full] = np.add.reduceat(mixed(hashes ^ np.uint64(0x1234567)), first[full])
                items = pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(hashes.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(f1.view(np.int64)), items], names=["doc_id", "f1", "items"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id bigint, f1 bigint, items array<bigint>")


def verified(pairs: DataFrame, docs: DataFrame, size: int, percent: int, files: int = 0) -> DataFrame:
    """The pairs (a, b, fa, fb) with 100 * intersection >= percent * union, as (a, b). a, b: ids; fa, fb: fingerprints. files: as in written()."""
    ends = pairs.select(F.col("a").alias("doc_id"), F.col("fa").alias("f")).unionAll(pairs.select("b", "fb")).distinct()
    ends = written(ends, "near-ends", files)
    few = ends.count() <= BROADCAST_IDS
    wanted = ends.select("doc_id").distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(wanted) if few else wanted, "doc_id", "left_semi")
    sets = written(shingle_sets(texts, size).dropDuplicates(["doc_id", "f1"]), "near-sets", files)
    left = sets.select(F.col("doc_id").alias("a"), F.col("f1").alias("fa"), F.col("items").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("f1").alias("fb"), F.col("items").alias("y"))
    both = pairs.join(right, ["b", "fb"]).join(left, ["a", "fa"])
    common = F.size(F.array_intersect("x", "y"))
    return both.where(100 * common >= percent * (F.size("x") + F.size("y") - common)).select("a", "b")


class _Forest:
    """Joins roots; tells whether a join was new."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        while (y := self.up.get(x, x)) != x:
            self.up[x] = x = self.up.get(y, y)
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        self.up[max(x, y)] = min(x, y)
        return x != y


def linked_blocks(large: DataFrame, docs: DataFrame, size: int, percent: int, files: int = 0) -> DataFrame:
    """(a, b): links that join components, among the members (key, doc, f1, root) of large open buckets.

    Buckets that share members form a cluster. The members outside a cluster's largest component are compared with all
    its members, block by block; a block pair counts common shingles through an index of its first block, and gives only
    links between roots that it has not joined yet, not all its pairs. files: as in written().
    """
    least = large.groupBy("key").agg(F.min("doc").alias("b"))
    cluster = connected(large.join(least, "key").select(F.col("doc").alias("a"), "b").distinct(), files)
    members = large.select("doc", "f1", "root").distinct().join(cluster.select(F.col("node").alias("doc"), F.col("root").alias("c")), "doc", "left").withColumn("c", F.coalesce("c", "doc"))
    members = written(members, "near-clusters", files)
    per_root = members.groupBy("c", "root").agg(F.count("*").alias("k"))
    shape = per_root.groupBy("c").agg(F.max(F.struct("k", "root")).alias("top"), F.sum("k").alias("n")).select("c", F.col("top.root").alias("largest"), F.ceil((F.col("n") - F.col("top.k")) / ASKED).alias("us"), F.ceil(F.col("n") / HELD).alias("vs")).where("us > 0")
    ids = members.select(F.col("doc").alias("doc_id")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, "doc_id", "left_semi")
    sets = shingle_sets(texts, size).dropDuplicates(["doc_id", "f1"]).withColumnRenamed("doc_id", "doc")
    whole = written(members.join(shape, "c").join(sets, ["doc", "f1"]), "near-blocks", files)
    spread = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    asked = whole.where("root <> largest").withColumn("u", F.pmod(F.xxhash64("doc", F.lit(1)), F.col("us"))).withColumn("v", spread("vs")).select("c", "u", "v", "doc", "root", "items")
    held = whole.withColumn("v", F.pmod(F.xxhash64("doc", F.lit(2)), F.col("vs"))).withColumn("u", spread("us")).select("c", "u", "v", "doc", "root", "items")

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[tuple[int, int]] = []
        if left.num_rows and right.num_rows:
            mine = left.column("items").combine_chunks()
            ends = np.asarray(mine.offsets)
            sizes, flat = np.diff(ends), np.asarray(mine.flatten())
            order = np.argsort(flat, kind="stable")
            owner = np.repeat(np.arange(len(sizes)), sizes)[order]
            kinds, first, times = np.unique(flat[order], return_index=True, return_counts=True)
            u_doc, u_root = left.column("doc").to_pylist(), left.column("root").to_pylist()
            forest = _Forest()
            for v_doc, v_root, items in zip(right.column("doc").to_pylist(), right.column("root").to_pylist(), right.column("items"), strict=True):
                theirs = np.asarray(items.values)
                at = np.minimum(np.searchsorted(kinds, theirs), len(kinds) - 1)
                at = at[kinds[at] == theirs]
                n = times[at]
                spots = np.repeat(first[at] - np.cumsum(n) + n, n) + np.arange(n.sum())
                common = np.bincount(owner[spots], minlength=len(sizes))
                for i in np.flatnonzero(100 * common >= percent * (sizes + len(theirs) - common)):
                    if forest.join(u_root[i], v_root):
                        out.append((u_doc[i], v_doc))
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([y for _, y in out], pa.int64())})

    return asked.groupBy("c", "u", "v").cogroup(held.groupBy("c", "u", "v")).applyInArrow(compare, "a bigint, b bigint")


def connected(edges: DataFrame, files: int = 0) -> DataFrame:
    """(node, root) for every node of the edges (a, b), root being the smallest node of its component, by alternating
    large-star and small-star steps until the edges stay the same. Roots themselves have no row. files: as in written(),
    for the first table; no step makes more edges than it was given, so the others follow from the edges' number."""
    now = written(edges.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi <> lo").distinct(), "cc", files)
    state = lambda df: tuple(df.agg(F.count("*"), F.bit_xor(F.xxhash64("hi", "lo")), F.sum(F.col("lo") % 1_000_003)).first())
    before = state(now)
    while before[0]:
        files = -(-before[0] // EDGES_A_FILE)
        both = now.unionAll(now.select(F.col("lo").alias("hi"), F.col("hi").alias("lo"))).toDF("u", "v")
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        large = written(large, "cc", files)
        remove_table(now)
        small_min = large.groupBy("hi").agg(F.min("lo").alias("m"))
        moved = large.join(small_min, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        now = written(moved.unionAll(small_min.select("hi", F.col("m").alias("lo"))).distinct(), "cc", files)
        remove_table(large)
        after = state(now)
        if after == before:
            break
        before = after
    return now.select(F.col("hi").alias("node"), F.col("lo").alias("root"))


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, bands: int | None = None, rows: int = ROWS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of docs. bands: by default those of bands_for()."""
    bands = bands or bands_for(percent, rows)
    signed = written(signatures(docs, size, bands, rows), "near-signatures")
    files = files_for(docs.sparkSession, *signed.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first())
    classes = signed.where("n > 0 AND doc_id IS NOT NULL").groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("doc"), F.any_value("bands").alias("bands"), F.any_value("bits").alias("bits"))
    classes = written(classes, "near-classes", files)
    member = classes.select(F.explode("bands").alias("key"), "doc", "f1", "n", "bits")
    buckets = member.groupBy("key").agg(F.min(F.struct("doc", "f1", "n", "bits")).alias("pivot"), F.count("*").alias("members")).where("members > 1")
    words = -(-bands * rows // 64)
    tolerated = int(bands * rows * (1 - percent / 100) / 2 + 5.5 * (bands * rows * (1 - percent / 100) / 2 * (1 + percent / 100) / 2) ** 0.5)

    def alike(x: str, y: str) -> str:
        apart = " + ".join(f"bit_count({x}.bits[{i}] ^ {y}.bits[{i}])" for i in range(words))
        return f"least({x}.n, {y}.n) * 100 >= {percent} * greatest({x}.n, {y}.n) AND {apart} <= {tolerated}"

    stars = member.alias("m").join(buckets, "key").where("m.doc <> pivot.doc OR m.f1 <> pivot.f1").where(alike("pivot", "m"))
    pairs = written(stars.select(F.col("pivot.doc").alias("a"), F.col("m.doc").alias("b"), F.col("pivot.f1").alias("fa"), F.col("m.f1").alias("fb")).distinct(), "near-pairs", files)
    links = written(verified(pairs, docs, size, percent, files), "near-links", files)
    roots = connected(links, files)
    # buckets that are not yet within one component: the rest of their pairs, without those inside a component
    placed = member.join(buckets.select("key"), "key", "left_semi").join(roots.withColumnRenamed("node", "doc"), "doc", "left").withColumn("root", F.coalesce("root", "doc"))
    per_root = placed.groupBy("key", "root").agg(F.count("*").alias("size"))
    open_keys = per_root.groupBy("key").agg(F.max(F.struct("size", "root")).alias("largest"), F.count("*").alias("roots"), F.sum("size").alias("total")).where("roots > 1").select("key", F.col("largest.root").alias("largest"), "total")
    opened = written(placed.join(open_keys, "key"), "near-open", files)
    few = opened.where(F.col("total") <= SMALL_BUCKET)
    rest = few.where("root <> largest").alias("u").join(few.alias("v"), (F.col("u.key") == F.col("v.key")) & (F.col("u.root") != F.col("v.root")) & ((F.col("v.root") == F.col("v.largest")) | (F.col("u.doc") < F.col("v.doc"))) & F.expr(alike("u", "v")))
    more = rest.select(F.col("u.doc").alias("a"), F.col("v.doc").alias("b"), F.col("u.f1").alias("fa"), F.col("v.f1").alias("fb")).distinct()
    more = written(more.join(pairs, ["a", "b", "fa", "fb"], "left_anti").join(pairs.toDF("b", "a", "fb", "fa"), ["a", "b", "fa", "fb"], "left_anti"), "near-more", files)
    if more.limit(1).count():
        links = links.unionAll(verified(more, docs, size, percent, files))
    large = opened.where(F.col("total") > SMALL_BUCKET).select("key", "doc", "f1", "root")
    if large.limit(1).count():
        links = links.unionAll(written(linked_blocks(large, docs, size, percent, files), "near-links"))
    own = signed.join(classes.select("f1", "f2", "n", "doc"), ["f1", "f2", "n"], "left").select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.coalesce("doc", "doc_id")).alias("doc"))
    own = written(own, "near-members", files)
    # an id that stands on different texts ties their classes together
    twice = own.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("doc").alias("least"), F.max("doc").alias("most")).where("least <> most").select("doc_id")
    tied = own.join(twice, "doc_id").where("doc_id <> doc").select(F.col("doc_id").alias("a"), F.col("doc").alias("b")).distinct()
    roots = connected(links.unionAll(tied), files)
    out = own.join(roots.withColumnRenamed("node", "doc"), "doc", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("root", "doc").alias("component_id"))
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
