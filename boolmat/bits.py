"""Bit-level codes in NumPy: fixed width, folded entropy code (interleaved range asymmetric numerals), canonical prefix codes."""

from __future__ import annotations

import heapq
import struct
from collections.abc import Iterator

import numpy as np


def width_of(most: int) -> int:
    """Bits for values up to `most`: floor(log2 most) + 1, at least 1."""
    return max(1, int(most).bit_length())


#: Values that are spread into bits at once, eight bytes a bit: a multiple of 8, so that stretches end at whole bytes.
STRETCH = 1 << 16


def pack_fixed(values: np.ndarray, width: int) -> bytes:
    v, out = np.asarray(values, np.uint64), []
    for at in range(0, len(v), STRETCH):
        bits = ((v[at : at + STRETCH, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
        out.append(np.packbits(bits.ravel(), bitorder="little").tobytes())
    return b"".join(out)


def unpack_fixed(data: bytes, width: int, count: int) -> np.ndarray:
    raw, out = np.frombuffer(data, np.uint8), np.empty(count, np.int64)
    for at in range(0, count, STRETCH):
        n = min(STRETCH, count - at)
        bits = np.unpackbits(raw[at * width // 8 :], bitorder="little", count=width * n) if n < STRETCH else np.unpackbits(raw[at * width // 8 : (at + n) * width // 8], bitorder="little")
        out[at : at + n] = (bits.reshape(n, width).astype(np.int64) << np.arange(width)).sum(1)
    return out


def bit_lengths(values: np.ndarray) -> np.ndarray:
    """Bit length of each non-negative integer below 2**53."""
    return np.where(values > 0, np.frexp(np.maximum(values, 1).astype(float))[1], 0).astype(np.int64)


def fold(values: np.ndarray, keep: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(class, raw low bits, their number): values of more than `keep` bits give their low bits away, so classes stay few."""
    shift = np.maximum(bit_lengths(values) - keep, 0)
    return (shift << (keep - 1)) + (values >> shift), values & ((1 << shift) - 1), shift


def unfold(classes: np.ndarray, keep: int) -> tuple[np.ndarray, np.ndarray]:
    """(value without its low bits, number of low bits) of each class."""
    shift = np.maximum((classes >> (keep - 1)) - 1, 0)
    return (classes - (shift << (keep - 1))) << shift, shift


def join_bits(values: np.ndarray, lengths: np.ndarray) -> bytes:
    """Bit fields of given lengths, low bit first, one behind the other."""
    ends = np.cumsum(lengths)
    bits = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    for i in range(0, len(lengths), STRETCH):
        some = lengths[i : i + STRETCH]
        first, last = int(ends[i] - lengths[i]), int(ends[min(i + STRETCH, len(ends)) - 1])
        at = np.arange(first, last) - np.repeat(ends[i : i + STRETCH] - some, some)
        bits[first:last] = (np.repeat(values[i : i + STRETCH], some) >> at) & 1
    return np.packbits(bits, bitorder="little").tobytes()


def split_bits(data: bytes, lengths: np.ndarray) -> np.ndarray:
    ends, out = np.cumsum(lengths), np.zeros(len(lengths), np.int64)
    bits = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little", count=int(ends[-1]) if len(ends) else 0)
    for i in range(0, len(lengths), STRETCH):
        some = lengths[i : i + STRETCH]
        first, last = int(ends[i] - lengths[i]), int(ends[min(i + STRETCH, len(ends)) - 1])
        at = np.arange(first, last) - np.repeat(ends[i : i + STRETCH] - some, some)
        if last > first:
            out[i : i + STRETCH] = np.bincount(np.repeat(np.arange(len(some)), some), bits[first:last].astype(np.int64) << at, minlength=len(some))
    return out


_SCALE, _STREAMS = 14, 32
#: Steps of the coders that are laid out at once.
STEPS = 1 << 11


def _frequencies(counts: np.ndarray) -> np.ndarray:
    """Positive integers in proportion to counts that sum to 2**_SCALE."""
    total = 1 << _SCALE
    f = np.maximum(1, np.floor(counts * (total / counts.sum())).astype(np.int64))
    while (gap := total - int(f.sum())) != 0:
        order = np.argsort(-f, kind="stable")
        if gap > 0:
            f[order[0]] += gap
        else:
            take = order[f[order] > 1]
            f[take[: min(len(take), -gap)]] -= 1
    return f


def _coded(tables: list[tuple[np.ndarray, np.ndarray]]) -> list[tuple[np.ndarray, bytes]]:
    """(last states, words) of each (symbol numbers, frequencies), all of one length: one loop drives the coders of all."""
    steps = -(-len(tables[0][0]) // _STREAMS)
    lanes = [slice(i * _STREAMS, (i + 1) * _STREAMS) for i in range(len(tables))]
    starts = [np.concatenate([[0], np.cumsum(f)[:-1]]) for _, f in tables]
    x = np.full(_STREAMS * len(tables), 1 << 16, np.int64)
    out: list[list[np.ndarray]] = [[] for _ in tables]
    for lo in range((steps - 1) // STEPS * STEPS, -1, -STEPS):
        n = min(STEPS, steps - lo)
        fs, cs = np.empty((n, len(x)), np.int64), np.empty((n, len(x)), np.int64)
        for lane, (index, f), c in zip(lanes, tables, starts, strict=True):
            some = index[lo * _STREAMS : (lo + n) * _STREAMS]
            padded = np.concatenate([some, np.zeros(n * _STREAMS - len(some), np.int64)]).reshape(n, _STREAMS)
            fs[:, lane], cs[:, lane] = f[padded], c[padded]
        tops, words, full = fs << (32 - _SCALE), np.empty((n, len(x)), np.uint16), np.empty((n, len(x)), bool)
        for s in range(n - 1, -1, -1):
            np.greater_equal(x, tops[s], out=full[s])
            words[s] = x & 0xFFFF
            x >>= full[s] * np.int64(16)
            whole = x // fs[s]
            x += whole * ((1 << _SCALE) - fs[s])  # whole << _SCALE and the remainder
            x += cs[s]
        for lane, found in zip(lanes, out, strict=True):
            found.append(words[:, lane][full[:, lane]])
    return [(x[lane], np.concatenate(found[::-1]).tobytes()) for lane, found in zip(lanes, out, strict=True)]


def _folded(values: np.ndarray, keeps: tuple[int, ...]) -> Iterator[bytes]:
    """Order-0 entropy codes of non-negative integers: folded classes by 32 interleaved coders, low bits raw."""
    values = np.asarray(values, np.int64)
    n = len(values)
    if not n:
        yield from (struct.pack("<II", 0, keep) for keep in keeps)
        return
    kinds, tables = [], []
    for keep in keeps:
        while True:
            symbols, index, counts = _numbered(fold(values, keep)[0])
            if len(symbols) <= 1 << (_SCALE - 1):
                break
            keep -= 1
        kinds.append((keep, symbols))
        tables.append((index, _frequencies(counts)))
    for (keep, symbols), (_, f), (x, words) in zip(kinds, tables, _coded(tables), strict=True):
        _, low, shift = fold(values, keep)
        gaps = np.diff(symbols, prepend=-1) - 1
        width_gap, width_f = width_of(int(gaps.max())), width_of(int(f.max()))
        head = struct.pack("<IIIBBI", n, keep, len(symbols), width_gap, width_f, len(words))
        yield head + pack_fixed(gaps, width_gap) + pack_fixed(f, width_f) + x.astype(np.uint32).tobytes() + words + join_bits(low, shift)


def _numbered(classes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct classes, number of each one's class, counts); classes are few and small."""
    if int(classes.max()) > 1 << 22:
        symbols, index, counts = np.unique(classes, return_inverse=True, return_counts=True)
        return symbols, index.astype(np.int32), counts
    counts = np.bincount(classes)
    symbols = np.flatnonzero(counts)
    number = np.zeros(len(counts), np.int32)
    number[symbols] = np.arange(len(symbols))
    return symbols, number[classes], counts[symbols]


def fold_encode(values: np.ndarray, keep: int = 8) -> bytes:
    """One folding's entropy code."""
    return next(_folded(values, (keep,)))


def fold_encode_best(values: np.ndarray, keeps: tuple[int, ...] = (2, 3, 4, 6, 8, 10)) -> bytes:
    """The shortest of several foldings: short streams cannot pay for large class tables."""
    return min(_folded(values, keeps), key=len)


def fold_decode(data: bytes) -> np.ndarray:
    n, keep = struct.unpack_from("<II", data)
    if not n:
        return np.zeros(0, np.int64)
    n, keep, k, width_gap, width_f, n_words = struct.unpack_from("<IIIBBI", data)
    at = struct.calcsize("<IIIBBI")
    parts = []
    for size in (-(-k * width_gap // 8), -(-k * width_f // 8), 4 * _STREAMS, n_words):
        parts.append(data[at : at + size])
        at += size
    symbols = np.cumsum(unpack_fixed(parts[0], width_gap, k) + 1) - 1
    f = unpack_fixed(parts[1], width_f, k)
    c = np.concatenate([[0], np.cumsum(f)[:-1]])
    which = np.repeat(np.arange(k), f)
    x = np.frombuffer(parts[2], np.uint32).astype(np.int64)
    words, pos = np.frombuffer(parts[3], np.uint16).astype(np.int64), 0
    steps = -(-n // _STREAMS)
    out = np.empty((steps, _STREAMS), np.int64)
    for s in range(steps):
        slot = x & ((1 << _SCALE) - 1)
        i = which[slot]
        out[s] = i
        x = f[i] * (x >> _SCALE) + slot - c[i]
        low = np.flatnonzero(x < 1 << 16)
        x[low] = (x[low] << 16) | words[pos : pos + len(low)]
        pos += len(low)
    values, shift = unfold(symbols[out.ravel()[:n]], keep)
    return values + split_bits(data[at:], shift)


def code_lengths(counts: np.ndarray) -> np.ndarray:
    """Lengths of an optimal prefix code by merging the two lightest trees."""
    if len(counts) == 1:
        return np.ones(1, np.int64)
    heap = [(int(c), i, (i,)) for i, c in enumerate(counts)]
    heapq.heapify(heap)
    lengths, serial = np.zeros(len(counts), np.int64), len(counts)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        lengths[list(a[2] + b[2])] += 1
        heapq.heappush(heap, (a[0] + b[0], serial, a[2] + b[2]))
        serial += 1
    return lengths


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Code words of a canonical prefix code, written high bit first but returned bit-reversed for low-first storage."""
    out, code, at = np.zeros(len(lengths), np.int64), 0, 0
    for i in np.lexsort((np.arange(len(lengths)), lengths)):
        code <<= int(lengths[i]) - at
        at = int(lengths[i])
        out[i] = int(format(code, f"0{at}b")[::-1], 2)
        code += 1
    return out


def prefix_encode(values: np.ndarray, keep: int = 4) -> tuple[bytes, np.ndarray]:
    """(data, bit offset of each value): folded classes by a prefix code, raw low bits behind each code word."""
    values = np.asarray(values, np.int64)
    classes, low, shift = fold(values, keep)
    symbols, index, counts = np.unique(classes, return_inverse=True, return_counts=True) if len(values) else (np.zeros(0, np.int64),) * 3
    lengths = code_lengths(counts) if len(symbols) else np.zeros(0, np.int64)
    words = canonical(lengths)
    own = lengths[index] if len(values) else np.zeros(0, np.int64)
    total = own + shift
    head = struct.pack("<III", len(values), keep, len(symbols)) + symbols.astype(np.uint32).tobytes() + lengths.astype(np.uint8).tobytes()
    body = join_bits((words[index] if len(values) else own) | (low << own), total)
    return head + body, np.cumsum(total) - total


class PrefixReader:
    """Values of a prefix-coded stream from any bit offset of a value on."""

    def __init__(self, data: bytes):
        n, self.keep, k = struct.unpack_from("<III", data)
        self.count = n
        symbols = np.frombuffer(data, np.uint32, k, 12).astype(np.int64)
        lengths = np.frombuffer(data, np.uint8, k, 12 + 4 * k).astype(np.int64)
        values, shifts = unfold(symbols, self.keep)
        self.table = {(int(ln), int(w)): (int(v), int(s)) for ln, w, v, s in zip(lengths, canonical(lengths), values, shifts, strict=True)}
        self.raw = np.unpackbits(np.frombuffer(data[12 + 5 * k :], np.uint8), bitorder="little").tobytes()  # a byte a bit

    def all(self) -> np.ndarray:
        """All values, read a stretch at a time."""
        out, at = np.empty(self.count, np.int64), 0
        for i in range(0, self.count, STRETCH):
            some, at = self.read(at, min(STRETCH, self.count - i))
            out[i : i + len(some)] = some
        return out

    def read(self, at: int, count: int) -> tuple[list[int], int]:
        out, raw, table = [], self.raw, self.table
        for _ in range(count):
            word = length = 0
            while True:
                word |= raw[at] << length
                length += 1
                at += 1
                if (hit := table.get((length, word))) is not None:
                    break
            value, shift = hit
            for b in range(shift):
                value |= raw[at + b] << b
            at += shift
            out.append(value)
        return out, at
