"""Adjacency rows by reference to an earlier row of the tile plus differences.

For every row the candidates are no reference and the `window` rows before it whose chains are shorter than `max_depth`;
the cheapest by estimated bits wins, the nearest on ties. A row is kept as reference offset, alternating copied and
skipped runs over the reference, stretches of consecutive columns (`min_run` and longer), and gaps of the rest.

refcopy_prefix: prefix codes and a bit offset per row, so a row can be read alone. refcopy_stream: entropy coded, for
storage. Products start a row from its reference's result and add and subtract the differences, depth by depth.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from ..bits import PrefixReader, bit_lengths, fold_decode, fold_encode_best, pack_fixed, prefix_encode, unpack_fixed, width_of
from .base import Format, Parts, Tile, add_at, from_header, header, row_lengths


#: Ones whose rows are described at once.
CELLS = 1 << 17


def gamma_bits(v: np.ndarray) -> np.ndarray:
    """Estimated bits of small non-negative integers."""
    return 2 * bit_lengths(v + 1) - 1


def _zigzag(v: np.ndarray) -> np.ndarray:
    return np.where(v >= 0, 2 * v, -2 * v - 1)


def _runs(fresh: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first place, length) of each run, runs beginning where fresh is true."""
    first = np.flatnonzero(fresh)
    return first, np.diff(np.append(first, len(fresh)))


def _firsts(owner: np.ndarray) -> np.ndarray:
    """Whether an entry is the first of its owner; owners ascend."""
    out = np.ones(len(owner), bool)
    out[1:] = owner[1:] != owner[:-1]
    return out


def shared_with(rows: np.ndarray, cols: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Whether the row k before each cell, and the row k behind it, holds its column, for k from 0 (never) to `window`."""
    order = np.lexsort((rows, cols))
    r, c = rows[order], cols[order]
    before, behind = np.zeros((window + 1, len(r)), bool), np.zeros((window + 1, len(r)), bool)
    for k in range(1, min(window, len(r) - 1) + 1):  # rows of a column are distinct: k entries on is k rows on or more
        away = r[k:] - r[:-k]
        near = np.flatnonzero((c[k:] == c[:-k]) & (away <= window))
        before[away[near], order[near + k]] = True
        behind[away[near], order[near]] = True
    return before, behind


def describe(cols: np.ndarray, first: np.ndarray, before: np.ndarray, behind: np.ndarray, rows: np.ndarray, offsets: np.ndarray, min_run: int) -> tuple[np.ndarray, np.ndarray]:
    """(numbers, how many of them per row) of ascending rows: degree, offset[, runs], stretches, gaps.

    Row i has the columns from first[i] to first[i + 1] and copies the row offsets[i] before it, or none with 0.
    """
    n, degree = len(rows), np.diff(first)
    # runs over the references, the first one copied; a skipped end needs no length
    has = np.flatnonzero(offsets)
    ref = rows[has] - offsets[has]
    at, owner = _spread(first[ref], degree[ref]), np.repeat(has, degree[ref])
    kept = behind[offsets[owner], at]
    start = _firsts(owner)
    fresh = start.copy()
    fresh[1:] |= kept[1:] != kept[:-1]
    run, run_length = _runs(fresh)
    run_owner, run_first = owner[run], start[run]
    last = np.append(run_first[1:], True) if len(run) else run_first
    said = kept[run] | ~last
    zero = np.bincount(run_owner[run_first & ~kept[run]], minlength=n)  # nothing is copied at first
    run_owner, run_length = run_owner[said], run_length[said]
    runs = np.bincount(run_owner, minlength=n)
    # stretches of what is left, and gaps
    at, owner = _spread(first[rows], degree[rows]), np.repeat(np.arange(n), degree[rows])
    left = ~before[offsets[owner], at]
    c, owner = cols[at[left]], owner[left]
    fresh = _firsts(owner)
    fresh[1:] |= c[1:] != c[:-1] + 1
    a, length = _runs(fresh)
    wide = length >= min_run
    long_owner, begin, long_length = owner[a[wide]], c[a[wide]], length[wide]
    stretches = np.bincount(long_owner, minlength=n)
    end = np.concatenate([[0], (begin + long_length)[:-1]]) if len(begin) else begin
    jump = np.where(_firsts(long_owner), _zigzag(begin - rows[long_owner]), begin - end - 1)
    rest = np.repeat(~wide, length)
    c, owner = c[rest], owner[rest]
    gap = np.where(_firsts(owner), _zigzag(c - rows[owner]), c - np.concatenate([[0], c[:-1]]) - 1) if len(c) else c
    gaps = np.bincount(owner, minlength=n)
    # all of a row in one place
    copies = (offsets > 0).astype(np.int64)
    counts = 3 + copies * (1 + zero + runs) + 2 * stretches + gaps
    place = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()), np.int64)
    out[place], out[place + 1] = degree[rows], offsets
    out[place[has] + 2] = (zero + runs)[has]
    place = place + 2 + copies * (1 + zero)
    out[_spread(place, runs)] = run_length
    place = place + runs
    out[place] = stretches
    pairs = _spread(place + 1, 2 * stretches)
    out[pairs[::2]], out[pairs[1::2]] = jump, long_length - min_run
    out[_spread(place + 1 + 2 * stretches, gaps)] = gap
    return out, counts


class _Reader:
    """Takes numbers one after the other and turns them back into rows."""

    def __init__(self, take, min_run: int):
        self.take, self.min_run = take, min_run

    def row(self, own: int, rows) -> tuple[int, list[int], list[int]]:
        """(offset, columns, dropped columns of the reference) of row `own`; rows(i) gives an earlier row."""
        take = self.take
        degree, offset = take(), take()
        copied, dropped = [], []
        if offset:
            ref = rows(own - offset)
            at, keep = 0, True
            for _ in range(take()):
                n = take()
                (copied if keep else dropped).extend(ref[at : at + n])
                at, keep = at + n, not keep
            dropped.extend(ref[at:])
        more, last = [], own
        for k in range(take()):
            g, n = take(), take() + self.min_run
            a = last + ((g >> 1) ^ -(g & 1)) if k == 0 else last + g + 1
            more.extend(range(a, a + n))
            last = a + n
        last = own
        for k in range(degree - len(copied) - len(more)):
            g = take()
            last = last + ((g >> 1) ^ -(g & 1)) if k == 0 else last + g + 1
            more.append(last)
        return offset, sorted(copied + more), dropped


def _spread(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[i], starts[i] + 1, ... counts[i] numbers for each i."""
    return np.repeat(starts - np.cumsum(counts) + counts, counts) + np.arange(int(counts.sum()))


def _chained(first: np.ndarray, steps: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Running sums within lists of counts[i] numbers; list i starts at first[i]; the first step of each is not used."""
    begin = np.cumsum(counts) - counts
    full = counts > 0
    steps = steps.copy()
    steps[begin[full]] = 0
    total = np.cumsum(steps)
    return total - np.repeat(total[begin[full]] - first[full], counts[full])


class Differences:
    """All rows of a tile as what they copy, drop and add. Lists are flat with counts per row."""

    def __init__(self, numbers: np.ndarray, n_rows: int, min_run: int):
        v, at = numbers.tolist(), 0
        fields = np.zeros((n_rows, 6), np.int64)  # degree, offset, first run, runs, first stretch, first gap
        more = np.zeros((n_rows, 2), np.int64)  # stretches, gaps
        for i in range(n_rows):  # a few steps per row; the lists themselves are taken as arrays below
            degree, offset = v[at], v[at + 1]
            at, runs, copied, first_run = at + 2, 0, 0, 0
            if offset:
                runs, first_run = v[at], at + 1
                at = first_run + runs
                copied = sum(v[first_run:at:2])
            stretches, first_stretch = v[at], at + 1
            at = first_stretch + 2 * stretches
            gaps = degree - copied - sum(v[first_stretch + 1 : at : 2]) - stretches * min_run
            fields[i], more[i] = (degree, offset, first_run, runs, first_stretch, at), (stretches, gaps)
            at += gaps
        own = np.arange(n_rows)
        self.degree, offset = fields[:, 0], fields[:, 1]
        self.ref = own - offset
        self.depth = np.zeros(n_rows, np.int64)
        back = np.flatnonzero(offset)
        while len(back):  # a row is one deeper than its reference; chains are short
            deeper = self.depth[self.ref[back]] + 1
            changed = deeper != self.depth[back]
            self.depth[back] = deeper
            if not changed.any():
                break
        unzig = lambda g: (g >> 1) ^ -(g & 1)
        n = more[:, 0]
        spots = _spread(fields[:, 4], 2 * n)[::2] if n.any() else np.zeros(0, np.int64)
        g, length = numbers[spots], numbers[spots + 1] + min_run
        before = np.concatenate([[0], length[:-1]]) if len(length) else length
        begin = np.cumsum(n) - n
        start = _chained(np.where(n > 0, own + unzig(g[np.minimum(begin, max(0, len(g) - 1))]) if len(g) else own, 0), g + before + 1, n) if len(g) else g
        columns = [_spread(start, length)]
        rows = [np.repeat(np.repeat(own, n), length)]
        m = more[:, 1]
        g = numbers[_spread(fields[:, 5], m)]
        begin = np.cumsum(m) - m
        if len(g):
            columns.append(_chained(np.where(m > 0, own + unzig(g[np.minimum(begin, len(g) - 1)]), 0), g + 1, m))
            rows.append(np.repeat(own, m))
        rows, columns = np.concatenate(rows), np.concatenate(columns)
        order = np.lexsort((columns, rows))
        self.added = rows[order], columns[order]
        self._copy(numbers, fields)

    def _copy(self, numbers: np.ndarray, fields: np.ndarray) -> None:
        """Fills the whole lists depth by depth, and what each row drops of its reference."""
        n_rows = len(self.degree)
        self.first = np.concatenate([[0], np.cumsum(self.degree)])
        self.columns = np.zeros(int(self.first[-1]), np.int64)
        per_row = np.bincount(self.added[0], minlength=n_rows)
        of_row = np.cumsum(per_row) - per_row
        dropped: list[tuple[np.ndarray, np.ndarray]] = []
        for d in range(int(self.depth.max(initial=0)) + 1):
            at = np.flatnonzero(self.depth == d)
            more = _spread(of_row[at], per_row[at])
            rows, cols = self.added[0][more], self.added[1][more]
            if d:
                n = fields[at, 3]
                spots = _spread(fields[at, 2], n)
                lengths = numbers[spots]
                kept = (np.arange(len(spots)) - np.repeat(np.cumsum(n) - n, n)) % 2 == 0
                have = self.degree[self.ref[at]]
                used = np.bincount(np.repeat(np.arange(len(at)), n), lengths, minlength=len(at)).astype(np.int64)
                # the flags of a row's runs, then the skipped end of its reference
                flags = np.zeros(int(have.sum()), bool)
                flags[_spread(np.cumsum(have) - have, used)] = np.repeat(kept, lengths)
                theirs = self.columns[_spread(self.first[self.ref[at]], have)]
                mine = np.repeat(at, have)
                dropped.append((mine[~flags], theirs[~flags]))
                rows, cols = np.concatenate([rows, mine[flags]]), np.concatenate([cols, theirs[flags]])
                order = np.lexsort((cols, rows))
                rows, cols = rows[order], cols[order]
            self.columns[_spread(self.first[at], self.degree[at])] = cols
        self.dropped = tuple(np.concatenate([x[k] for x in dropped]) if dropped else np.zeros(0, np.int64) for k in (0, 1))


class RefCopy(Format):
    """opts: window (0: no copying), max_depth, min_run."""

    most = 1 << 18

    def __init__(self, coding: str):
        self.coding, self.name = coding, f"refcopy_{coding}"

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        window, max_depth, min_run = (int(tile.opts.get(k, d)) for k, d in (("window", 7), ("max_depth", 3), ("min_run", 4)))
        n, window = tile.n_rows, max(0, window)
        first = np.concatenate([[0], np.cumsum(row_lengths(tile.rows, n))]).astype(np.int64)
        depth, offset, found, counts, diffs = [0] * n, np.zeros(n, np.int64), [], [], 0
        for lo, hi in self._stretches(first):
            low = max(0, lo - window)  # with the rows before it that may be copied
            cut = slice(first[low], first[hi])
            near = first[low : hi + 1] - first[low]
            cols = tile.cols[cut]
            before, behind = shared_with(tile.rows[cut], cols, window)
            # columns and rows are counted from `low`, so that gaps to a row's own number stay the same
            said = lambda rows, offsets: describe(cols - low, near, before, behind, rows - low, offsets, min_run)  # noqa: B023, E731
            bits = self._bits(*said(np.arange(lo, hi), np.zeros(hi - lo, np.int64)))
            costs = [bits.tolist()]
            for k in range(1, window + 1):
                shared = np.add.reduceat(np.append(before[k], False), near[:-1], dtype=np.int64) * (np.diff(near) > 0)
                rows = np.flatnonzero(shared[lo - low :]) + lo
                cost = bits.copy()  # no gain where nothing is shared
                cost[rows - lo] = self._bits(*said(rows, np.full(len(rows), k)))
                costs.append(cost.tolist())
            for i, options in enumerate(zip(*costs, strict=True), lo):
                best = options[0]
                for k in range(1, min(window, i) + 1):
                    if options[k] < best and depth[i - k] < max_depth:
                        best, offset[i], depth[i] = options[k], k, depth[i - k] + 1
            rows, own = np.arange(lo, hi), offset[lo:hi]
            numbers, count = said(rows, own)
            found.append(numbers)
            counts.append(count)
            mine = np.repeat(offset[low:hi], np.diff(near))
            mine[: near[lo - low]] = 0
            common = int(before[mine, np.arange(len(mine))].sum())
            ref = rows[own > 0] - own[own > 0]
            diffs += int(first[hi] - first[lo] + (first[ref + 1] - first[ref]).sum() - 2 * common)
        depth = np.array(depth, np.int64)
        values, counts = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (found, counts))
        parts = {"head": header(len(values), min_run)}
        if self.coding == "prefix":
            parts["data"], places = prefix_encode(values)
            first = places[np.cumsum(counts) - counts] if len(counts) else places
            width = width_of(int(first.max()) if len(first) else 0)
            parts["offsets"] = bytes([width]) + pack_fixed(first, width)
        else:
            parts["data"] = fold_encode_best(values)
        return parts, {"numbers": len(values), "diffs": diffs, "copied_rows": int((depth > 0).sum()), "touched": diffs}

    @staticmethod
    def _stretches(first: np.ndarray) -> Iterator[tuple[int, int]]:
        """Row ranges of about CELLS ones and an eighth as many rows, one row at least."""
        lo, n = 0, len(first) - 1
        while lo < n:
            hi = min(n, lo + max(1, CELLS // 8), max(lo + 1, int(np.searchsorted(first, first[lo] + CELLS, side="right")) - 1))
            yield lo, hi
            lo = hi

    @staticmethod
    def _bits(numbers: np.ndarray, counts: np.ndarray) -> np.ndarray:
        return np.add.reduceat(gamma_bits(numbers), np.cumsum(counts) - counts) if len(counts) else counts

    def differences(self, parts: Parts, n_rows: int) -> Differences:
        if self.coding == "stream":
            numbers = fold_decode(parts["data"])
        else:
            numbers = PrefixReader(parts["data"]).all()
        return Differences(np.asarray(numbers, np.int64), n_rows, from_header(parts["head"])[1])

    def row_of(self, parts: Parts, n_rows: int, i: int) -> list[int]:
        """One row: with prefix codes only its own chain of references is read."""
        if self.coding == "stream":
            d = self.differences(parts, n_rows)
            return d.columns[d.first[i] : d.first[i + 1]].tolist()
        reader, min_run = PrefixReader(parts["data"]), from_header(parts["head"])[1]
        places = unpack_fixed(parts["offsets"][1:], parts["offsets"][0], n_rows)

        def row(k: int) -> list[int]:
            at = int(places[k])

            def take() -> int:
                nonlocal at
                (v,), at = reader.read(at, 1)
                return v

            return _Reader(take, min_run).row(k, row)[1]

        return row(i)

    def decode(self, parts, n_rows, n_cols):
        d = self.differences(parts, n_rows)
        return np.repeat(np.arange(n_rows), d.degree), d.columns, None

    def right(self, parts, n_rows, n_cols, x):
        d = self.differences(parts, n_rows)
        y = add_at(d.added[0], x[d.added[1]], n_rows) - add_at(d.dropped[0], x[d.dropped[1]], n_rows)
        for k in range(1, int(d.depth.max(initial=0)) + 1):
            at = np.flatnonzero(d.depth == k)
            y[at] += y[d.ref[at]]
        return y

    def left(self, parts, n_rows, n_cols, z):
        d = self.differences(parts, n_rows)
        w = np.array(z, float)
        for k in range(int(d.depth.max(initial=0)), 0, -1):
            at = np.flatnonzero(d.depth == k)
            w += np.bincount(d.ref[at], w[at], minlength=n_rows)
        return np.bincount(d.added[1], w[d.added[0]], minlength=n_cols) - np.bincount(d.dropped[1], w[d.dropped[0]], minlength=n_cols)
