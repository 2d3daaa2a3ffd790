"""Nearest neighbours by inner product with query-aware collision counting.

Vectors are dealt to blocks of bounded size. A block holds its distinct vectors projected on random directions, one
sorted array per direction. A query opens a window around its own projection in every array and widens all windows step
by step (virtual rehashing: the windows of a wider step contain those before, only the new edges are visited). A vector
that lies in the windows of enough directions is verified by its exact inner product. The search of a block ends when
the windows are so wide that any vector better than the k-th best found would have collided often enough, with the
stated probability; so the recall does not depend on the size of the data.

Inner product becomes distance: all vectors of a block get one more component that gives them equal length.

Each block answers each query with its k best, which are merged. A task first reads a block's vectors, builds the index
once, and then streams the queries through it; it holds one block and one batch of queries. Every query meets every
block: random directions in many dimensions leave no block out (see the README), so the work is queries times blocks.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite components take no part; a query meets
vectors of its own length only; equal scores go to the smaller id; a query's own row (its id) is no candidate; repeated
query rows of one id and vector are one query, of one id and several vectors several with one ranking each.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from math import erf, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def usable(v: Column) -> Column:
    """Takes part: not null, all components finite numbers, not all zero."""
    wide = v.cast("array<double>")
    bad = F.exists(wide, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(~bad & F.exists(wide, lambda x: x != 0), F.lit(False))


class CollisionIndex:
    """The sorted arrays of one block. threshold: collisions that a vector at the search radius reaches with `surety` sigmas."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, directions: int = 32, reach: float = 0.9, surety: float = 0.9, seed: int = 7):
        order = np.lexsort((ids, *vectors.T[::-1]))
        ids, vectors = ids[order], vectors[order]
        fresh = np.ones(len(ids), bool)
        fresh[1:] = (vectors[1:] != vectors[:-1]).any(1)
        self.first = np.flatnonzero(fresh)  # equal vectors share one entry; members lie in order of their ids
        self.last = np.append(self.first[1:], len(ids))
        self.ids, self.vectors = ids, vectors[self.first]
        self.norms = np.einsum("ij,ij->i", self.vectors, self.vectors)
        self.top = float(self.norms.max())
        wide = np.column_stack([self.vectors, np.sqrt(np.maximum(self.top - self.norms, 0.0))])
        rng = np.random.default_rng(seed)
        self.axes = rng.standard_normal((wide.shape[1], directions))
        self.projected = wide @ self.axes
        self.order = np.argsort(self.projected, axis=0, kind="stable").T.copy()
        # all sorted arrays behind one another, each lifted above the one before: one search serves all directions
        self.floor, self.ceiling = float(self.projected.min()) - 1, float(self.projected.max()) + 1
        self.lift = np.arange(directions) * (self.ceiling - self.floor + 1)
        self.flat = (np.take_along_axis(self.projected, self.order.T, 0).T + self.lift[:, None]).ravel()
        self.probe = rng.choice(len(self.vectors), min(len(self.vectors), 256), replace=False)
        p = erf(reach / sqrt(2))
        self.reach, self.threshold = reach, max(1, int(np.floor(directions * p - surety * sqrt(directions * p * (1 - p)))))

    def spots(self, values: np.ndarray, side: str) -> np.ndarray:
        """Place of one value per direction in its sorted array."""
        n = len(self.vectors)
        found = np.searchsorted(self.flat, np.clip(values, self.floor, self.ceiling) + self.lift, side)
        return np.clip(found - np.arange(len(self.lift)) * n, 0, n)

    def search(self, own: int, query: np.ndarray, k: int, step: float = 1.2) -> list[tuple[float, int]]:
        """The k best of this block as (score, id), best first, without the id `own`."""
        n, (dirs, _) = len(self.vectors), self.order.shape
        at = query @ self.axes[:-1]  # a query's added component is 0
        size2 = float(query @ query)
        counts = np.zeros(n, np.int64)
        seen = np.zeros(n, bool)
        low = high = self.spots(at, "left")
        # the best of a few probes tells about how far the k-th best of the block will be; the first windows are as wide
        near = float((self.vectors[self.probe] @ query).max())
        width = 0.9 * self.reach * sqrt(max(self.top + size2 - 2 * near, 0.0)) + 1e-9 * sqrt(self.top + size2)
        best: list[tuple[float, int]] = []
        while True:
            a, b = self.spots(at - width, "left"), self.spots(at + width, "right")
            edges = [self.order[j, x:y] for j in range(dirs) for x, y in ((a[j], low[j]), (high[j], b[j])) if x < y]
            if edges:
                counts += np.bincount(np.concatenate(edges), minlength=n)
            low, high = np.minimum(a, low), np.maximum(b, high)
            fresh = np.flatnonzero((counts >= self.threshold) & ~seen)
            if len(fresh):
                seen[fresh] = True
                if len(fresh) > 2 * k:  # a fast product only to leave out what is clearly worse
                    rough = self.vectors[fresh] @ query
                    # one more than k, for the query's own row may be among them
                    fresh = fresh[rough >= np.partition(rough, -k - 1)[-k - 1] - 1e-9 * np.sqrt(self.top * size2)]
                # summed in order, so that equal vectors get equal scores in every block
                scores = np.cumsum(self.vectors[fresh] * query, axis=1)[:, -1]
                for i, s in zip(fresh, scores, strict=True):
                    ids = [int(x) for x in self.ids[self.first[i] : min(self.last[i], self.first[i] + k + 1)] if x != own]
                    best += [(float(s), x) for x in ids[:k]]
                best = sorted(best, key=lambda x: (-x[0], x[1]))[:k]
            if seen.all() or (low == 0).all() and (high == n).all():
                return best
            if len(best) >= k:  # distance of the k-th best in the lengthened space
                far = np.sqrt(max(self.top + size2 - 2 * best[-1][0], 0.0))
                if width >= self.reach * far:
                    return best
            width *= step


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, vec_id: str = "vec_id", embedding: str = "embedding", block: int = 16_384, query_block: int = 256, **index) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k largest inner products over all vectors but its own row.

    block: expected rows of a data block; query_block: queries that are worth an index of their own. Scores are double-precision products of the
    original vectors.
    """
    def clean(df: DataFrame) -> DataFrame:
        return df.select(F.col(vec_id).cast("long").alias("id"), F.col(embedding).cast("array<double>").alias("v")).where(usable(F.col("v")) & F.col("id").isNotNull())

    data, asked = clean(vectors), clean(queries).distinct()
    n_data, n_asked = data.count(), asked.count()
    blocks = max(1, -(-n_data // block))
    # a block is dealt to several tasks only where blocks are fewer than cores; each of them indexes it
    shares = max(1, min(-(-vectors.sparkSession.sparkContext.defaultParallelism // blocks), -(-n_asked // query_block)))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint")))
    held = data.select(F.pmod(F.xxhash64("id", "v"), F.lit(blocks).cast("bigint")).alias("b"), every(shares).alias("q"), F.lit(0).alias("side"), "id", "v")
    dealt = asked.select(every(blocks).alias("b"), F.pmod(F.xxhash64("id", "v", F.lit(3)), F.lit(shares).cast("bigint")).alias("q"), F.lit(1).alias("side"), "id", "v")
    both = held.unionAll(dealt).withColumn("slot", (F.col("b") * shares + F.col("q")).cast("int"))
    both = both.repartitionById(blocks * shares, F.col("slot")).sortWithinPartitions("slot", "side").select("slot", "side", "id", "v")
    arrow = pa.schema([("query_id", pa.int64()), ("key", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot, parts, made = None, [], None
        for batch in batches:
            slots, sides = np.asarray(batch.column(0)), np.asarray(batch.column(1))
            cuts = np.flatnonzero((slots[1:] != slots[:-1]) | (sides[1:] != sides[:-1])) + 1
            for a, e in zip([0, *cuts], [*cuts, len(slots)]):
                if a == e:
                    continue
                if slots[a] != slot:
                    slot, parts, made = slots[a], [], None
                ids, lists = np.asarray(batch.column(2).slice(a, e - a)), batch.column(3).slice(a, e - a)
                if sides[a] == 0:
                    parts.append((ids, lists))
                    continue
                made = indexes(parts, index) if made is None else made
                out: list[tuple[int, int, int, float]] = []
                for qid, q in zip(ids.tolist(), lists, strict=True):
                    q = np.asarray(q.values, float)
                    if len(q) in made:
                        out += [(qid, digest(q), x, s) for s, x in made[len(q)].search(qid, q, k)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 4, arrow.types, strict=True)], schema=arrow)

    found = both.mapInArrow(search, "query_id bigint, key bigint, vec_id bigint, score double")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id", "key").orderBy(F.desc("score"), F.asc("vec_id"))))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def digest(vector: np.ndarray) -> int:
    """Tells the vectors of one query id apart."""
    return int.from_bytes(hashlib.blake2b(vector.tobytes(), digest_size=8).digest(), "little", signed=True)


def indexes(parts: list[tuple[np.ndarray, pa.Array]], options: dict) -> dict[int, CollisionIndex]:
    """One index per vector length of a block."""
    if not parts:
        return {}
    ids, lists = np.concatenate([i for i, _ in parts]), [x for _, x in parts]
    sizes = np.concatenate([np.diff(np.asarray(x.offsets)) for x in lists])
    flat = np.concatenate([np.asarray(x.flatten()) for x in lists])
    return {int(w): CollisionIndex(ids[sizes == w], flat[np.repeat(sizes == w, sizes)].reshape(-1, w), **options) for w in np.unique(sizes)}


def nearest_exact(vectors: DataFrame, queries: DataFrame, k: int = 20, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """The same by comparing every pair in sequence order: the yardstick for recall on small tables."""
    data = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).cast("array<double>").alias("v")).where(usable(F.col("v")))
    asked = queries.select(F.col(vec_id).cast("long").alias("query_id"), F.col(embedding).cast("array<double>").alias("w")).where(usable(F.col("w")) & F.col("query_id").isNotNull()).distinct()
    pairs = asked.join(data, (F.col("query_id") != F.col("vec_id")) & (F.size("v") == F.size("w")))
    scored = pairs.select("query_id", "w", "vec_id", F.aggregate(F.zip_with("v", "w", lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x).alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("query_id", "w").orderBy(F.desc("score"), F.asc("vec_id"))))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
