"""Repeated passages by suffix arrays that are built in linear time from Lyndon groups.

A byte is removed if a string of `length` bytes that covers it also starts anywhere else.

The suffix sort. Suffixes start in groups by first character. Groups are taken in descending order; every member of the
group points to the nearest suffix before it that lies in a lower group; the suffixes pointed at leave their groups for
new ones just above, by how many pointers they got: their common prefix has grown by the group's, once per pointer. At
the end a group holds the suffixes that share their Lyndon prefix. The order inside the groups then follows in one
ascending pass along the pointers, without renaming. The two passes run over many independent short texts in step, so
that each step is a handful of NumPy operations.

Spreading it over a cluster.
1. Each window of `length` bytes chooses an anchor: its gram with the smallest hash. Equal windows choose alike, so
   equal windows share an anchor. Anchors whose hash occurs once belong to no repeated window and are left.
2. The windows of an anchor, dealt to fixed cells of their offset from it, form pieces. Pieces are grouped by the bytes
   that all windows of the cell have in common.
3. Pieces that are equal as a whole are one text with a weight; their windows all recur. Where a group holds different
   pieces, their bytes are sorted: neighbours in the suffix array that agree in `length` bytes recur.
4. A group with more bytes than a lane holds is dealt to several lanes. A window that is alone in its lane, and one
   window of each class found there, meet the other lanes' through packed window hashes.
5. The windows found go back to their documents.

Defined cases: null is the empty text; texts shorter than `length` lose nothing; repeated rows (same id, same text) are
repeats of each other like any texts; null ids are ids; no step holds more than a bucket of pieces or one text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import POWERS, keyed_join, mixed, slices, text_buffers, written

GRAM = 24
#: Offsets per cell, bytes per lane and per bucket of lanes.
CELL, LANE, BUCKET = 126, 16_000, 2_000_000
#: Positions within one pass of the anchor kernel: fits the low bits of a key.
_POSITION = 20
_LOW = np.uint64((1 << _POSITION) - 1)


def lyndon_suffix_arrays(text: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Suffix arrays of independent texts, one behind the other.

    text[0] is unused; lane k is text[ends[k - 1]:ends[k]] (from 1 for the first) and ends with a 0 that is its only one.
    Returns the positions of text in order, lane by lane, at the lanes' own places (entry 0 is 0).
    """
    n = len(text)
    begins = np.concatenate([[1], ends[:-1]])
    lane = np.repeat(np.arange(len(ends)), ends - begins)
    key = lane * (int(text.max()) + 1) + text[1:]
    sa = np.concatenate([[0], np.argsort(key, kind="stable") + 1])
    key = np.concatenate([[-1], key[sa[1:] - 1]])
    fresh = np.ones(n, bool)
    fresh[1:] = key[1:] != key[:-1]
    heads = np.flatnonzero(fresh)
    size = np.zeros(n, np.int64)
    size[heads] = np.diff(np.append(heads, n))
    group = np.empty(n, np.int64)
    group[sa] = np.repeat(heads, size[heads])
    place = np.empty(n, np.int64)
    place[sa] = np.arange(n)
    before = np.zeros(n, np.int64)
    moved = np.zeros(n, bool)
    lane_of = np.concatenate([[-1], lane])

    top, low = ends.copy(), begins
    while len(top):
        g = group[sa[top - 1]]
        live = g > low
        if not live.all():
            top, low, g = top[live], low[live], g[live]
            if not len(top):
                break
        count = top - g
        at = np.repeat(g - np.cumsum(count) + count, count) + np.arange(count.sum())
        m, mg = sa[at], np.repeat(g, count)
        j = m - 1
        beyond = np.flatnonzero(group[j] > mg)
        while len(beyond):  # members of groups that are done know where to look next
            j[beyond] = before[j[beyond]]
            beyond = beyond[group[j[beyond]] > mg[beyond]]
        before[m] = j
        same = np.flatnonzero(group[j] == mg)
        while len(same):
            j[same] = before[j[same]]
            before[m[same]] = j[same]
            same = same[group[j[same]] == mg[same]]
        inside = lane_of[j] == lane_of[m]
        if inside.any():
            t, pointers = np.unique(j[inside], return_counts=True)
            order = np.lexsort((pointers, group[t]))
            t, pointers = t[order], pointers[order]
            home = group[t]
            first = np.ones(len(t), bool)
            first[1:] = home[1:] != home[:-1]
            f = np.flatnonzero(first)
            leaving = np.diff(np.append(f, len(t)))
            floor = np.repeat(home[f] + size[home[f]] - leaving, leaving)
            slot = floor + np.arange(len(t)) - np.repeat(f, leaving)
            moved[t] = True
            there, old = sa[slot], place[t]
            pushed, free = there[~moved[there]], old[old < floor]
            moved[t] = False
            sa[free], place[pushed] = pushed, free
            sa[slot], place[t] = t, slot
            size[home[f]] -= leaving
            run = first.copy()
            run[1:] |= pointers[1:] != pointers[:-1]
            r = np.flatnonzero(run)
            length = np.diff(np.append(r, len(t)))
            size[slot[r]] = length
            group[t] = np.repeat(slot[r], length)
        top = g

    out, fill = np.zeros(n, np.int64), np.arange(n)
    placed = np.zeros(n, bool)
    placed[0] = placed[ends - 1] = True
    out[begins] = ends - 1
    order = np.argsort(begins - ends, kind="stable")
    starts, lengths = begins[order], (ends - begins)[order]
    active = len(starts)
    for i in range(int(lengths[0]) if active else 0):
        while lengths[active - 1] <= i:
            active -= 1
        j = out[starts[:active] + i] - 1
        j = j[~placed[j]]
        while len(j):
            g = group[j]
            spot = fill[g]
            out[spot], fill[g], placed[j] = j, spot + 1, True
            j = before[j]
            j = j[~placed[j]]
    return out


def _same(data: np.ndarray, x: np.ndarray, y: np.ndarray, length: int) -> np.ndarray:
    """Whether the `length` bytes from x[i] and from y[i] agree, by words; pairs that differ drop out early."""
    if len(data) < length:
        return np.zeros(len(x), bool)
    words = np.lib.stride_tricks.as_strided(np.append(data, np.zeros(8, np.uint8)).copy(), (len(data) + 1, 8), (1, 1))
    alive = np.arange(len(x))
    for at in [*range(0, length - 8, 8), max(0, length - 8)]:
        a, b = np.ascontiguousarray(words[x[alive] + at]).view(np.uint64), np.ascontiguousarray(words[y[alive] + at]).view(np.uint64)
        alive = alive[(a == b).ravel()]
        if not len(alive):
            break
    out = np.zeros(len(x), bool)
    out[alive] = True
    return out


def anchor_runs(data: np.ndarray, cuts: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(text number, anchor, first start, last start, anchor hash) of every run of window starts with one anchor.

    Positions are within data. Texts longer than a pass of the kernel are taken in overlapping parts.
    """
    most = (1 << _POSITION) - length
    if len(data) > (1 << _POSITION):
        parts = []
        for t in range(len(cuts) - 1):
            for c in range(int(cuts[t]), max(int(cuts[t]) + 1, int(cuts[t + 1]) - length + 1), most):
                e = min(int(cuts[t + 1]), c + most + length - 1)
                _, p, lo, hi, h = anchor_runs(data[c:e], np.array([0, e - c]), length)
                parts.append((np.full(len(p), t), p + c, lo + c, hi + c, h))
        return tuple(np.concatenate(c) for c in zip(*parts, strict=True))
    gram = min(GRAM, length)
    width = length - gram + 1
    n = len(data)
    none = np.zeros(0, np.int64)
    if n < length:
        return none, none, none, none, none.astype(np.uint64)
    prefix = POWERS.prefix(data)
    grams = mixed((prefix[gram:] - prefix[:-gram]) * POWERS.down[: n - gram + 1])
    keys = (grams & ~_LOW) | np.arange(len(grams), dtype=np.uint64)
    padded = np.full(-(-len(keys) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[: len(keys)] = keys
    grid = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    back = np.minimum.accumulate(grid, axis=1).ravel()
    m = n - length + 1
    anchor = (np.minimum(ahead[:m], back[width - 1 : width - 1 + m]) & _LOW).astype(np.int64)
    owner = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))[:m]
    start = np.flatnonzero(np.arange(m) + length <= cuts[owner + 1])
    if not len(start):
        return none, none, none, none, none.astype(np.uint64)
    a, o = anchor[start], owner[start]
    fresh = np.ones(len(start), bool)
    fresh[1:] = (a[1:] != a[:-1]) | (o[1:] != o[:-1])
    f = np.flatnonzero(fresh)
    last = np.append(f[1:], len(start)) - 1
    return o[f], a[f], start[f], start[last], grams[a[f]]


def pieces(prefix: np.ndarray, p: np.ndarray, lo: np.ndarray, hi: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(run number, common hash, whole hash, first start, number of starts) of the runs' pieces."""
    width = length - min(GRAM, length) + 1
    zero = p - (width - 1)
    out = []
    for cell in range(-(-width // CELL)):
        top = min((cell + 1) * CELL, width) - 1
        a, b = np.maximum(lo, zero + cell * CELL), np.minimum(hi, zero + top)
        r = np.flatnonzero(a <= b)
        a, b = a[r], b[r]
        common = mixed(POWERS.span(prefix, zero[r] + top, zero[r] + cell * CELL + length) + np.uint64(cell + 1))
        whole = mixed(POWERS.span(prefix, a, b + length) ^ ((a - zero[r]).astype(np.uint64) << np.uint64(32)))
        out.append((r, common, whole, a, b - a + 1))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _runs(sorted_starts: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first, last index) of the stretches of consecutive numbers with one key."""
    if not len(sorted_starts):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    fresh = np.ones(len(sorted_starts), bool)
    fresh[1:] = (sorted_starts[1:] != sorted_starts[:-1] + 1) | (keys[1:] != keys[:-1])
    f = np.flatnonzero(fresh)
    return f, np.append(f[1:], len(fresh)) - 1


_FOUND = pa.schema([("c", pa.int64()), ("s", pa.int64()), ("a", pa.int32()), ("b", pa.int32()), ("slot", pa.int32()), ("packed", pa.binary())])
_FOUND_SQL = "c bigint, s bigint, a int, b int, slot int, packed binary"
_PACK = np.dtype([("w", "<u8"), ("c", "<i8"), ("s", "<i8"), ("off", "<i4"), ("known", "<i4")])


def sort_bucket(table: pa.Table, length: int, slots: int) -> pa.Table:
    """Recurring windows of a bucket's lanes. Columns of table: c, s, lane, split, n, body (bytes of a piece)."""
    order = np.argsort(np.asarray(table.column("lane")), kind="stable")
    table = table.take(pa.array(order)).combine_chunks()
    c, s, lane, n = (np.asarray(table.column(x)) for x in ("c", "s", "lane", "n"))
    split = np.asarray(table.column("split"))
    raw, offsets = text_buffers(table.column("body"))
    raw, offsets = raw[offsets[0] : offsets[-1]], offsets - offsets[0]
    count = len(c)
    body = np.diff(offsets)
    starts = offsets[:-1] + np.arange(count) + 1  # of the pieces in text: one separator behind each, one unused place ahead
    text = np.ones(int(offsets[-1]) + count + 1, np.int64)
    text[np.repeat(starts - offsets[:-1], body) + np.arange(len(raw))] = raw.astype(np.int64) + 2
    closing = np.flatnonzero(np.append(lane[1:] != lane[:-1], True))
    ends = starts[closing] + body[closing] + 1
    text[ends - 1] = 0
    sa = lyndon_suffix_arrays(text, ends)
    owner = np.full(len(text), -1)
    owner[np.repeat(starts, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)] = np.repeat(np.arange(count), n)
    data = np.where(text >= 2, text - 2, 0).astype(np.uint8)
    x, y = sa[1:-1], sa[2:]
    both = np.flatnonzero((owner[x] >= 0) & (owner[y] >= 0))
    both = both[lane[owner[x[both]]] == lane[owner[y[both]]]]
    equal = both[_same(data, x[both], y[both], length)]
    found = np.zeros(len(text), bool)
    found[x[equal]] = found[y[equal]] = True
    spots = np.flatnonzero(found)
    f, last = _runs(spots, owner[spots])
    who = owner[spots[f]]
    out = [pa.table({"c": c[who], "s": s[who], "a": (spots[f] - starts[who]).astype(np.int32), "b": (spots[last] - starts[who]).astype(np.int32), "slot": pa.nulls(len(f), pa.int32()), "packed": pa.nulls(len(f), pa.binary())}, schema=_FOUND)]
    follows = np.zeros(len(text), bool)  # all of a class but its first
    follows[y[equal]] = True
    alone = np.flatnonzero((owner >= 0) & ~follows)
    alone = alone[split[owner[alone]]]
    if len(alone):
        who = owner[alone]
        pack = np.empty(len(alone), _PACK)
        pack["w"] = mixed(POWERS.span(POWERS.prefix(data), alone, alone + length) ^ c[who].view(np.uint64))
        pack["c"], pack["s"], pack["off"], pack["known"] = c[who], s[who], alone - starts[who], found[alone]
        slot = (pack["w"] % np.uint64(slots)).astype(np.int64)
        for k in np.unique(slot):
            out.append(pa.table({"c": pa.nulls(1, pa.int64()), "s": pa.nulls(1, pa.int64()), "a": pa.nulls(1, pa.int32()), "b": pa.nulls(1, pa.int32()), "slot": pa.array([k], pa.int32()), "packed": pa.array([pack[slot == k].tobytes()], pa.binary())}, schema=_FOUND))
    return pa.concat_tables(out)


def meet_lanes(table: pa.Table) -> pa.Table:
    """Windows of different lanes with one hash, as runs; only those not known yet."""
    pack = np.frombuffer(b"".join(table.column("packed").to_pylist()), _PACK)
    pack = pack[np.argsort(pack["w"], kind="stable")]
    w = pack["w"]
    again = np.zeros(len(w), bool)
    again[1:] = w[1:] == w[:-1]
    again[:-1] |= again[1:]
    hit = pack[again & (pack["known"] == 0)]
    hit = hit[np.lexsort((hit["off"], hit["s"], hit["c"]))]
    f, last = _runs(hit["off"].astype(np.int64), hit["c"] ^ (hit["s"] * 31))
    return pa.table({"c": hit["c"][f], "s": hit["s"][f], "a": hit["off"][f], "b": hit["off"][last]}, schema=pa.schema([("c", pa.int64()), ("s", pa.int64()), ("a", pa.int32()), ("b", pa.int32())]))


def _by_text(batch: pa.RecordBatch, column: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    raw, offsets = text_buffers(batch.column(column))
    for a, b in slices(offsets, 1 << 19):
        yield a, b, raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]


def repeated_windows(docs: DataFrame, length: int) -> DataFrame:
    """(id0, t, spans): for each text with repeats, the ranges [start, end) of starts of windows that recur elsewhere.

    docs: (id0, t, text), t a hash of the text; equal (id0, t) are repeated rows and have one result row.
    """
    def anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, cuts in _by_text(batch, 2):
                owner, _, _, _, h = anchor_runs(data, cuts, length)
                ends = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=b - a))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.ListArray.from_arrays(pa.array(ends), pa.array(h.view(np.int64)))], names=["id0", "t", "hs"])

    long = docs.where(F.octet_length("text") >= length).select("id0", "t", "text")
    marked = written(long.mapInArrow(anchors, "id0 bigint, t bigint, hs array<bigint>"), "anchors")
    flat = marked.select("id0", "t", F.posexplode("hs").alias("i", "h"))
    common = written(marked.select(F.explode("hs").alias("h")).groupBy("h").agg(F.count("*").alias("n")).where("n > 1"), "common")
    chosen = keyed_join(flat, common, ["h"], "n").groupBy("id0", "t").agg(F.array_distinct(F.collect_list("i")).alias("runs"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("c", pa.int64()), ("s", pa.int64()), ("lo", pa.int64()), ("n", pa.int32())])
        for batch in batches:
            for a, b, data, cuts in _by_text(batch, 2):
                owner, p, lo, hi, _ = anchor_runs(data, cuts, length)
                first = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=b - a))])
                wanted = batch.column(3).slice(a, b - a)
                pick = np.sort(np.asarray(wanted.flatten(), dtype=np.int64) + np.repeat(first[:-1], np.diff(np.asarray(wanted.offsets))))
                r, c, s, at, n = pieces(POWERS.prefix(data), p[pick], lo[pick], hi[pick], length)
                who = owner[pick][r]
                order = np.argsort(who, kind="stable")
                values = pa.StructArray.from_arrays([pa.array(c[order].view(np.int64)), pa.array(s[order].view(np.int64)), pa.array((at - cuts[who])[order]), pa.array(n[order].astype(np.int32))], fields=list(kind))
                ends = np.concatenate([[0], np.cumsum(np.bincount(who, minlength=b - a))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.ListArray.from_arrays(pa.array(ends), values)], names=["id0", "t", "pieces"])

    piece = "array<struct<c:bigint,s:bigint,lo:bigint,n:int>>"
    held = written(long.join(chosen, ["id0", "t"]).select("id0", "t", "text", "runs").mapInArrow(cut, f"id0 bigint, t bigint, pieces {piece}"), "pieces")
    flat = held.select("id0", "t", F.inline("pieces"))
    kinds = written(flat.groupBy("c", "s").agg(F.count("*").alias("weight"), F.min(F.struct("id0", "t", "lo", "n")).alias("r")), "kinds")
    per_group = kinds.groupBy("c").agg(F.count("*").alias("different"), F.sum(F.col("r.n") + length).alias("bytes")).where("different > 1")
    sorted_ones = kinds.join(per_group, "c").withColumn("lanes", F.ceil(F.col("bytes") / LANE)).select("c", "s", "lanes", "r")
    sorted_ones = written(sorted_ones.withColumn("lane", F.xxhash64("c", F.pmod(F.xxhash64("s"), F.col("lanes")))), "mixed")
    total = sorted_ones.agg(F.sum(F.col("r.n") + length)).first()[0] or 0
    buckets = max(1, -(-int(total) // BUCKET))

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["c", "s", "lane", "split", "n", "body"]
        for batch in batches:
            for i in range(batch.num_rows):
                data = memoryview(batch.column(0)[i].as_buffer())
                rows = batch.column(1)[i].as_py()
                bodies = [bytes(data[x["lo"] : x["lo"] + x["n"] + length - 1]) for x in rows]
                cols = [pa.array([x[k] for x in rows], t) for k, t in (("c", pa.int64()), ("s", pa.int64()), ("lane", pa.int64()), ("split", pa.bool_()), ("n", pa.int64()))]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(bodies, pa.binary())], names=names)

    per_text = sorted_ones.groupBy(F.col("r.id0").alias("id0"), F.col("r.t").alias("t")).agg(F.collect_list(F.struct("c", "s", "lane", (F.col("lanes") > 1).alias("split"), F.col("r.lo").alias("lo"), F.col("r.n").alias("n"))).alias("rows"))
    bodies = long.join(per_text, ["id0", "t"]).dropDuplicates(["id0", "t"]).select("text", "rows").mapInArrow(take, "c bigint, s bigint, lane bigint, split boolean, n bigint, body binary")
    found = bodies.withColumn("bucket", F.pmod("lane", F.lit(buckets))).groupBy("bucket").applyInArrow(lambda t: sort_bucket(t.drop(["bucket"]), length, buckets), _FOUND_SQL)
    found = written(found, "found")
    across = found.where("slot IS NOT NULL").groupBy("slot").applyInArrow(meet_lanes, "c bigint, s bigint, a int, b int")
    parts = found.where("slot IS NULL").select("c", "s", "a", "b").unionAll(across).groupBy("c", "s").agg(F.collect_list(F.struct("a", "b")).alias("ranges"))
    # a piece that stands several times recurs as a whole; one that stands once in the ranges found for it
    whole = kinds.where("weight > 1").select("c", "s", "weight", F.array(F.struct(F.lit(0).alias("a"), (F.col("r.n") - 1).cast("int").alias("b"))).alias("ranges"))
    once = kinds.where("weight = 1").select("c", "s", "weight").join(parts, ["c", "s"])
    flags = written(whole.unionByName(once), "flags")
    met = keyed_join(flat, flags, ["c", "s"], "weight").select("id0", "t", "lo", F.inline("ranges"))
    hits = met.select("id0", "t", (F.col("lo") + F.col("a")).alias("start"), (F.col("lo") + F.col("b") + 1).alias("end"))
    return hits.groupBy("id0", "t").agg(F.collect_set(F.struct("start", "end")).alias("spans"))


def remove_repeats(docs: DataFrame, length: int = 400, with_text: bool = False) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256[, kept]) for every row of docs; kept: the bytes that stay."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("id0"), F.xxhash64(text).alias("t"), text.alias("text"))
    spans = repeated_windows(rows.select("id0", "t", "text"), length)
    out = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), *([("kept", pa.binary())] if with_text else [])]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            done = []
            for doc_id, value, found in zip(batch.column(0), batch.column(1), batch.column(2), strict=True):
                data = value.as_buffer().to_pybytes() if value.is_valid else b""
                kept, at, removed, n = [], 0, 0, 0
                ranges = sorted((x["start"], x["end"] + length - 1) for x in found.as_py()) if found.is_valid else []
                for a, b in ranges:
                    if b <= at:
                        continue
                    if a > at or not n:
                        n += 1
                        kept.append(data[at:a])
                    removed += b - max(a, at)
                    at = b
                kept.append(data[at:])
                left = b"".join(kept)
                done.append((doc_id.as_py(), len(data), removed, n, hashlib.sha256(left).hexdigest(), *([left] if with_text else [])))
            yield pa.RecordBatch.from_arrays([pa.array(col, t) for col, (_, t) in zip(zip(*done, strict=True) if done else [[]] * len(out), out, strict=True)], names=[k for k, _ in out])

    joined = rows.join(spans, ["id0", "t"], "left").select("doc_id", "text", "spans")
    return joined.mapInArrow(cut, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + (", kept binary" if with_text else ""))
