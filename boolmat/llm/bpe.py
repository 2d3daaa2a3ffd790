"""Byte-level BPE encoding and decoding with overlapping chunks.

A text longer than a chunk is cut into chunks that overlap. Every chunk is split into pre-tokens by itself; where a
boundary of one chunk that is sure to hold meets a boundary of the next one, the two have resynchronised, because the
pattern looks only forward; from there on the next chunk's boundaries are the text's. Each chunk then encodes the
pieces between its two meeting points, and the text's ids are the chunks' ids in order. Where an overlap has no meeting
point, the scan goes on over the text until there is one. Decoding concatenates the bytes of the ids.

The pre-tokens of the pattern FAMILIAR are found on the UTF-8 bytes of many texts at once, those of other patterns by
regex, text by text. A slice of texts looks each different pre-token up once, and the new ones are merged in step.

Defined cases: a null or empty text has no ids, repeated rows each give a row, an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import cached_property, lru_cache
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, text_buffers, written

#: Characters of a chunk, and how many of them the next chunk repeats.
CHUNK, OVERLAP = 65_536, 1_024
#: A boundary is sure if this many characters of its chunk follow it: the pattern looks no further.
MARGIN = 4
#: Pieces whose ids a worker remembers.
REMEMBERED = 100_000
#: Bytes of text whose pre-tokens are found at once.
SLICE = 1 << 20
#: Bytes of the longest piece that is merged in step with others, and how many pieces are; 6 bits hold a place.
WIDEST, STEP = 64, 4_096
#: The pattern that pretokens() follows.
FAMILIAR = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_BLANK, _LETTER, _NUMBER, _OTHER = range(4)


@lru_cache(1)
def kinds() -> np.ndarray:
    """The kind of every code point: blank, letter, number or other."""
    out = np.full(0x110000, _OTHER, np.uint8)
    every = np.arange(len(out), dtype="<u4").tobytes().decode("utf-32-le", "surrogatepass")
    for kind, pattern in ((_BLANK, r"\s+"), (_LETTER, r"\p{L}+"), (_NUMBER, r"\p{N}+")):
        for m in regex.finditer(pattern, every):
            out[m.start() : m.end()] = kind
    return out


def byte_kinds(data: np.ndarray) -> np.ndarray:
    """The kind of the code point that each byte of UTF-8 belongs to."""
    table = kinds()
    out = table[:256][data]
    high = np.flatnonzero(data >= 0x80)
    lead = high[data[high] >= 0xC0]
    first = data[lead]
    length = 2 + (first >= 0xE0) + (first >= 0xF0)
    point = first & np.array([0, 0, 0x1F, 0x0F, 0x07], np.uint32)[length]
    for k in range(1, 4):
        more = length > k
        point[more] = point[more] << np.uint32(6) | data[lead[more] + k] & np.uint32(0x3F)
    found = table[point]
    for k in range(4):
        more = length > k
        out[lead[more] + k] = found[more]
    return out


def pretokens(data: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """The begins of all matches of FAMILIAR in the texts data[cuts[i]:cuts[i + 1]] (UTF-8), and len(data).

    Matches begin where the kind changes. The last blank before something else is a match of its own or, if it is a
    space, the begin of the next. An apostrophe that begins a match takes its letters along.
    """
    n = len(data)
    if not n:
        return np.zeros(1, np.int64)
    kind = byte_kinds(data)
    begins = cuts[:-1][cuts[:-1] < n]
    mark = np.ones(n, bool)
    np.not_equal(kind[1:], kind[:-1], out=mark[1:])
    turn = mark[1:] & (kind[:-1] == _BLANK)  # turn[i]: the text's last blank of a run ends at i
    turn[begins[begins > 0] - 1] = False
    mark[1:] &= ~(turn & (data[:-1] == 0x20))
    mark[begins] = True
    wide = np.flatnonzero(turn & (data[:-1] >= 0x80))
    turn[wide] = False
    mark[:-1] |= turn
    for _ in range(3):  # blanks of several bytes begin before their last
        wide = np.where(data[wide] & 0xC0 == 0x80, wide - 1, wide)
    mark[wide] = True

    at = np.flatnonzero(data == ord("'"))
    at = at[mark[at]]
    room = cuts[np.searchsorted(cuts, at, side="right")] - at
    one, two = (data[np.minimum(at + k, n - 1)] for k in (1, 2))
    short = (room > 1) & np.isin(one, np.frombuffer(b"stmd", np.uint8))
    long = (room > 2) & (np.isin(one, np.frombuffer(b"rv", np.uint8)) & (two == ord("e")) | (one == ord("l")) & (two == ord("l")))
    mark[at[short | long] + 1] = False
    ends = np.concatenate([at[short] + 2, at[long] + 3])
    mark[ends[ends < n]] = True
    return np.append(np.flatnonzero(mark), n)


class Pairs:
    """Which adjacent pairs of ids join, and to which id: a table with open addressing, and a plain one for pairs of bytes."""

    def __init__(self, ranks: dict[bytes, int]):
        self.none = np.int32(np.iinfo(np.int32).max >> 6)
        self.byte = np.array([ranks.get(bytes([b]), -1) for b in range(256)], np.int32)
        splits = ((a, b, r) for x, r in ranks.items() for k in range(1, len(x)) if (a := ranks.get(x[:k])) is not None and (b := ranks.get(x[k:])) is not None)
        a, b, r = np.fromiter(chain.from_iterable(splits), np.int64).reshape(-1, 3).T
        self.shift = np.uint64(64 - max(4, (4 * len(r)).bit_length()))
        self.mask = (1 << (64 - int(self.shift))) - 1
        self.keys, self.to = np.full(self.mask + 1, -1, np.int64), np.full(self.mask + 1, self.none, np.int32)
        key, left = a << 32 | b, np.arange(len(r))
        slot = self._slot(key)
        while len(left):
            free = self.keys[slot[left]] < 0
            self.keys[slot[left[free]]] = key[left[free]]  # of several, the last one stays
            here = self.keys[slot[left]] == key[left]
            self.to[slot[left[here]]] = r[left[here]]
            left = left[~here]
            slot[left] = (slot[left] + 1) & self.mask
        every = np.arange(256)
        self.bytes = self.find(self.byte[every[:, None]].repeat(256, 1).ravel(), np.tile(self.byte, 256))

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The ids that a[i] and b[i] join to, or none; negative ids join with nothing."""
        key = a.astype(np.int64) << 32 | b.astype(np.int64) & 0xFFFFFFFF
        out = np.full(len(key), self.none, np.int32)
        left = np.flatnonzero((a >= 0) & (b >= 0))
        slot = self._slot(key[left])
        while len(left):
            there = self.keys[slot]
            hit = there == key[left]
            out[left[hit]] = self.to[slot[hit]]
            on = ~hit & (there >= 0)
            left, slot = left[on], (slot[on] + 1) & self.mask
        return out

    def merge(self, data: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each piece) of the pieces data[ends[i]:ends[i + 1]], none empty or over WIDEST bytes.

        A column per piece, a row per place and one of nothing at the end. In each step every piece joins its pair of
        least rank, the leftmost of several: the least of rank and place.
        """
        n, size = len(ends) - 1, np.diff(ends)
        width = int(size.max())
        place = np.arange(width)[:, None]
        inside = place < size
        raw = np.zeros((width, n), np.uint8)
        raw.T[inside.T] = data
        ids = np.full((width + 1, n), -1, np.int32)
        ids[:-1] = np.where(inside, self.byte[raw], -1)
        stop = np.int32(self.none << 6)
        keys = np.full((width + 1, n), stop, np.int32)
        pair = self.bytes[raw[:-1].astype(np.int32) << 8 | raw[1:]]
        keys[: width - 1] = np.where(inside[1:] & (pair < self.none), pair << 6 | place[:-1], stop)
        after = np.where(place + 1 < size, place + 1, width).astype(np.int32)
        before = np.where(place > 0, place - 1, width) + np.zeros((1, n), np.int32)
        after, before = (np.concatenate([x, np.full((1, n), width, x.dtype)]).ravel() for x in (after, before))
        alive = np.concatenate([inside, np.zeros((1, n), bool)])
        flat, key, live = ids.ravel(), keys.ravel(), alive.ravel()
        col = np.arange(n)
        while True:
            least = np.minimum.reduce(keys, axis=0)[col] if len(col) > n // 8 else np.minimum.reduce(keys[:, col], axis=0)
            go = least < stop
            col, least = col[go], least[go]
            if not len(col):
                break
            joined = least >> 6
            at = (least & 63) * n + col
            gone = after[at] * n + col
            right, left = after[gone] * n + col, before[at] * n + col
            flat[at], key[gone], live[gone] = joined, stop, False
            after[at], before[right] = after[gone], least & 63
            for other, pair, here in ((right, self.find(joined, flat[right]), at), (left, self.find(flat[left], joined), left)):
                key[here] = np.where(pair < self.none, pair << 6 | (here // n).astype(np.int32), stop)
        return ids.T[alive.T], alive.sum(axis=0)


class Tokenizer:
    """Ranks and pattern; encodes pieces and remembers them."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.split = regex.compile(pattern)
        self.bytes_of = {i: b for b, i in self.ranks.items()}
        self.familiar = pattern == FAMILIAR and all(bytes([b]) in self.ranks for b in range(256))
        self.known: dict[str, tuple[int, ...]] = {}
        self.forget()

    @cached_property
    def pairs(self) -> Pairs:
        return Pairs(self.ranks)

    def forget(self) -> None:
        """No marked piece is remembered. codes: the number of each; numbers, sizes: the ids of all, and how many each has."""
        self.codes: dict[bytes, int] = {}
        self.numbers, self.sizes = np.zeros(0, np.int32), np.zeros(0, np.int32)

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Joins the adjacent pair of least rank, leftmost first, until no pair has a rank."""
        if piece in self.ranks:
            return (self.ranks[piece],)
        parts = [piece[i : i + 1] for i in range(len(piece))]
        if len(parts) > 200:
            return self._merge_long(parts)
        rank, none = self.ranks.get, len(self.ranks)
        pairs = [rank(a + b, none) for a, b in zip(parts, parts[1:])]
        while pairs and (best := min(pairs)) < none:
            at = pairs.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
            del pairs[at]
            if at:
                pairs[at - 1] = rank(parts[at - 1] + parts[at], none)
            if at < len(pairs):
                pairs[at] = rank(parts[at] + parts[at + 1], none)
        return tuple([self.ranks[p] for p in parts])

    def _merge_long(self, parts: list[bytes]) -> tuple[int, ...]:
        """The same with a heap over a linked list, for pieces of any length."""
        import heapq

        ranks, n = self.ranks, len(parts)
        left, right, alive = list(range(-1, n - 1)), [*range(1, n), -1], [True] * n
        heap = [(r, i, parts[i] + parts[i + 1]) for i in range(n - 1) if (r := ranks.get(parts[i] + parts[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, both = heapq.heappop(heap)
            j = right[i] if alive[i] else -1
            if j < 0 or parts[i] + parts[j] != both:
                continue
            parts[i], alive[j], right[i] = both, False, right[j]
            if right[j] >= 0:
                left[right[j]] = i
            for a in (left[i], i):
                b = right[a] if a >= 0 else -1
                if b >= 0 and (r := ranks.get(parts[a] + parts[b])) is not None:
                    heapq.heappush(heap, (r, a, parts[a] + parts[b]))
        return tuple(ranks[p] for p, x in zip(parts, alive, strict=True) if x)

    def piece(self, text: str) -> tuple[int, ...]:
        if len(self.known) >= REMEMBERED:
            self.known.clear()
        found = self.known[text] = self.merge(text.encode())
        return found

    def merge_all(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each piece): merge() of every piece; those of about one length go in step."""
        whole = np.fromiter(map(self.ranks.get, pieces, repeat(-1)), np.int32, len(pieces))
        size = np.fromiter(map(len, pieces), np.int64, len(pieces))
        counts = np.ones(len(pieces), np.int32)
        step = np.flatnonzero((whole < 0) & (size <= WIDEST))
        step = step[np.argsort(size[step], kind="stable")]
        ids = []
        for a in range(0, len(step), STEP):
            of = step[a : a + STEP]
            found, counts[of] = self.pairs.merge(np.frombuffer(b"".join([pieces[i] for i in of]), np.uint8), np.cumsum([0, *size[of]]))
            ids.append(found)
        rest = np.flatnonzero((whole < 0) & (size > WIDEST))
        for i in rest:
            ids.append(np.array(self.merge(pieces[i]), np.int32))
            counts[i] = len(ids[-1])
        single = np.flatnonzero(whole >= 0)
        ids.append(whole[single])
        order = np.concatenate([step, rest, single])  # the pieces as their ids stand in ids
        begin = np.zeros(len(pieces), np.int64)
        begin[order] = np.cumsum(counts[order]) - counts[order]
        ends = np.cumsum(counts)
        return np.concatenate(ids)[np.repeat(begin - ends + counts, counts) + np.arange(counts.sum())], counts

    def encode_pieces(self, pieces: list[str]) -> list[int]:
        known = self.known
        return list(chain.from_iterable([known.get(p) or self.piece(p) for p in pieces]))

    def encode_marked(self, data: np.ndarray, bounds: np.ndarray) -> pa.ListArray:
        """Ids of every piece data[bounds[i]:bounds[i + 1]]; equal pieces are looked up once."""
        pieces = pa.Array.from_buffers(pa.large_binary(), len(bounds) - 1, [None, pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(data)]).dictionary_encode()
        different = pieces.dictionary.to_pylist()
        if len(self.codes) + len(different) > REMEMBERED or len(self.numbers) > 10 * REMEMBERED:
            self.forget()
        code = np.fromiter(map(self.codes.get, different, repeat(-1)), np.int32, len(different))
        new = np.flatnonzero(code < 0)
        if len(new):
            wanted = [different[i] for i in new]
            ids, counts = self.merge_all(wanted)
            code[new] = len(self.sizes) + np.arange(len(new))
            self.codes.update(zip(wanted, code[new].tolist()))
            self.numbers, self.sizes = np.concatenate([self.numbers, ids]), np.concatenate([self.sizes, counts])
        ends = np.concatenate([[0], np.cumsum(self.sizes)]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(self.numbers))
        return lists.take(pa.array(code).take(pieces.indices))

    def encode_texts(self, data: np.ndarray, cuts: np.ndarray) -> pa.ListArray:
        """Ids of every text data[cuts[i]:cuts[i + 1]] (UTF-8)."""
        if not self.familiar:
            texts = (data[a:b].tobytes().decode() for a, b in zip(cuts, cuts[1:]))
            return pa.array([self.encode_pieces(self.split.findall(x)) for x in texts], pa.list_(pa.int32()))
        bounds = pretokens(data, cuts)
        lists = self.encode_marked(data, bounds)
        ends = lists.offsets.to_numpy()[np.searchsorted(bounds, cuts)]
        return pa.ListArray.from_arrays(pa.array(ends), lists.values)

    def ends(self, text: str) -> list[int]:
        """The ends of all pre-tokens of a text, in characters."""
        if not self.familiar:
            return [m.end() for m in self.split.finditer(text)]
        data = np.frombuffer(text.encode(), np.uint8)
        bounds = pretokens(data, np.array([0, len(data)]))[1:]
        return (bounds if len(data) == len(text) else np.cumsum(data & 0xC0 != 0x80)[bounds - 1]).tolist()

    def encode_run(self, text: str, bounds: list[int]) -> list[int]:
        """Ids of the pieces of a text between bounds, which begin with 0 and are in characters."""
        data = np.frombuffer(text.encode(), np.uint8)
        return self.encode_marked(data, np.append(np.flatnonzero(data & 0xC0 != 0x80), len(data))[bounds]).values.to_pylist()

    def encode(self, text: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[int]:
        """Ids of one text, by chunks if it is longer than one."""
        if len(text) <= chunk:
            data = np.frombuffer(text.encode(), np.uint8)
            return self.encode_texts(data, np.array([0, len(data)])).values.to_pylist()
        parts = [(s, text[s : s + chunk]) for s in starts(len(text), chunk, overlap)]
        cuts = [(s, len(p), [s + e for e in self.ends(p)]) for s, p in parts]
        return list(chain.from_iterable(self.encode_run(text[run[0] : run[-1]], [b - run[0] for b in run]) for run in stitched(text, cuts, self.split)))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


@lru_cache(4)
def tokenizer(path: str, pattern: str) -> Tokenizer:
    return Tokenizer(path, pattern)


def starts(length: int, chunk: int, overlap: int) -> list[int]:
    return list(range(0, max(1, length - overlap), chunk - overlap))


def stitched(text: str, cuts: list[tuple[int, int, list[int]]], split: regex.Pattern) -> Iterator[list[int]]:
    """The true boundaries of a text, one run per chunk; a run begins where the one before it ends.

    cuts: (start, length, ends of pre-tokens within the whole text) of each chunk in order.
    """
    at, own = 0, cuts[0][2]
    for k, (start, length, ends) in enumerate(cuts):
        if k and at != start and at not in ends:  # no meeting point: scan on until there is one
            marks, run = set(ends), [at]
            while at < len(text) and at not in marks:
                at = split.match(text, at).end()
                run.append(at)
            yield run
        own = [e for e in ends if e > at]
        last = k == len(cuts) - 1
        if last:
            yield [at, *own]
            return
        sure = start + length - MARGIN
        nexts = set(cuts[k + 1][2]) | {cuts[k + 1][0]}
        held = [e for e in own if e <= sure]
        meet = next((i for i, e in enumerate(held) if e in nexts), None)
        if meet is not None:
            held = held[: meet + 1]
        yield [at, *held]
        at = held[-1] if held else at


def encode(docs: DataFrame, path: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """(doc_id, ids) for every row of (doc_id, text).

    Texts of up to a chunk are encoded where they are read. Longer ones are exploded into chunks that are dealt over the
    cluster; each task finds the pre-tokens of its chunks. The boundaries of a text meet in one task, which only looks up
    where chunks resynchronise. The stretches between the meeting points are dealt out again to be encoded.
    """
    schema = "doc_id bigint, ids array<int>"
    arrow = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))])
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))

    def short(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path, pattern)
        for batch in batches:
            batch.column(1).validate(full=True)  # the kernels take UTF-8 for granted
            raw, offsets = text_buffers(batch.column(1))
            for a, b in slices(offsets, SLICE):
                ids = t.encode_texts(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), ids], schema=arrow)

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path, pattern)
        for batch in batches:
            for row in batch.to_pylist():
                yield pa.RecordBatch.from_pylist([row | {"ends": t.ends(row["part"])}], pa.schema([*batch.schema, ("ends", pa.list_(pa.int32()))]))

    def stitch(key: tuple, table: pa.Table) -> pa.Table:
        t = tokenizer(path, pattern)
        chunks = sorted(table.to_pylist(), key=lambda r: r["start"])
        text = "".join([r["part"][: chunk - overlap] for r in chunks[:-1]] + [chunks[-1]["part"]])
        cuts = [(r["start"], len(r["part"]), [r["start"] + e for e in r["ends"]]) for r in chunks]
        found = [(k, text[run[0] : run[-1]], [b - run[0] for b in run]) for k, run in enumerate(stitched(text, cuts, t.split))]
        n, first = len(found), chunks[0]
        return pa.table([pa.array([first["doc_id"]] * n, pa.int64()), pa.array([first["row"]] * n, pa.int64()), *(pa.array([f[i] for f in found], kind) for i, kind in enumerate((pa.int32(), pa.string(), pa.list_(pa.int32()))))], names=["doc_id", "row", "k", "part", "bounds"])

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path, pattern)
        for batch in batches:
            for i in range(batch.num_rows):
                ids = t.encode_run(batch.column(3)[i].as_py(), batch.column(4)[i].as_py())
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(i, 1) for c in range(3)), pa.array([ids], pa.list_(pa.int32()))], names=["doc_id", "row", "k", "ids"])

    long = rows.where(F.length("text") > chunk).withColumn("row", F.monotonically_increasing_id())
    begins = F.sequence(F.lit(0), F.length("text") - overlap - 1, F.lit(chunk - overlap))
    pieces = long.select("doc_id", "row", "text", F.explode(begins).alias("start")).select("doc_id", "row", "start", F.substring(F.col("text"), F.col("start") + 1, F.lit(chunk)).alias("part"))
    # the row number only tells equal ids apart; the chunks are stored with it, so that it is drawn once
    pieces = written(pieces, "chunks")
    marked = pieces.repartition("row", "start").mapInArrow(marks, "doc_id bigint, row bigint, start int, part string, ends array<int>")
    met = marked.groupBy("doc_id", "row").applyInArrow(stitch, "doc_id bigint, row bigint, k int, part string, bounds array<int>")
    encoded = met.repartition("row", "k").mapInArrow(runs, "doc_id bigint, row bigint, k int, ids array<int>")
    joined = encoded.groupBy("doc_id", "row").agg(F.sort_array(F.collect_list(F.struct("k", "ids"))).alias("runs")).select("doc_id", F.flatten(F.col("runs.ids")).alias("ids"))
    return rows.where(F.length("text") <= chunk).mapInArrow(short, schema).unionAll(joined)


def joined(words: pa.Array, ids: pa.Array, ends: np.ndarray) -> Iterator[memoryview]:
    """The words of the ids of each list, one behind the other. ends: the lists' offsets."""
    taken = words.take(ids)
    if taken.null_count:
        raise KeyError("an id that is not in the vocabulary")
    raw, offsets = text_buffers(taken)
    data, at = memoryview(raw), offsets[ends - ends[0]].tolist()
    return (data[a:b] for a, b in zip(at, at[1:]))


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded): the bytes of the ids, and a digest of the ids."""
    return _decoded(encoded, path, pattern, False)


def digests(encoded: DataFrame, path: str, pattern: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256[, ids]): as decode, with a digest of the bytes in their place."""
    return _decoded(encoded, path, pattern, True, with_ids)


def _decoded(encoded: DataFrame, path: str, pattern: str, digest: bool, with_ids: bool = False) -> DataFrame:
    last = ("decoded_sha256", pa.string()) if digest else ("decoded", pa.binary())
    arrow = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), last, *([("ids", pa.list_(pa.int32()))] if with_ids else [])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path, pattern)
        every = range(max(t.bytes_of) + 1)
        decimal, spelt = (pa.array(x, pa.large_binary()) for x in ([b"%d " % i for i in every], [t.bytes_of.get(i) for i in every]))
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                lists = part.column(1)
                ends = lists.offsets.to_numpy()
                sums = [hashlib.sha256(x[:-1]).hexdigest() for x in joined(decimal, lists.flatten(), ends)]
                outs = [hashlib.sha256(x).hexdigest() if digest else bytes(x) for x in joined(spelt, lists.flatten(), ends)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(ends), pa.int64()), pa.array(sums, pa.string()), pa.array(outs, last[1]), *([lists] if with_ids else [])], schema=arrow)

    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id bigint, n_tokens bigint, ids_sha256 string, {last[0]} {'string' if digest else 'binary'}" + (", ids array<int>" if with_ids else ""))
