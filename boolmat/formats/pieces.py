"""Formats that take a matrix apart: complete bipartite pieces, and groups of columns."""

from __future__ import annotations

import numpy as np

from ..bits import pack_fixed, unpack_fixed, width_of
from .base import Format, Parts, Tile, add_at, from_header, from_ints, header, ints, row_lengths
from .quadbits import QuadBits

_REST = QuadBits()


class Biclique(Format):
    """Complete bipartite pieces (rows S, columns T) whose product is one sum over T added to every row of S; the rest
    is a quadrant tree. Pieces come from equal rows, then from the common columns of neighbours in min-hash order."""

    name = "biclique"
    most = 1 << 18

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        saving = int(tile.opts.get("min_saving", 2))
        lists = {i: set(x.tolist()) for i, x in enumerate(np.split(tile.cols, np.cumsum(row_lengths(tile.rows, tile.n_rows))[:-1])) if len(x)} if tile.n_rows else {}
        found: list[tuple[list[int], list[int]]] = []

        def take(s: list[int], t: set[int]) -> None:
            found.append((s, sorted(t)))
            for i in s:
                lists[i] -= t

        equal: dict[frozenset, list[int]] = {}
        for i, t in lists.items():
            equal.setdefault(frozenset(t), []).append(i)
        for t, s in equal.items():
            if len(s) > 1 and len(s) * len(t) - len(s) - len(t) >= saving:
                take(s, set(t))
        for seed in (1, 2):  # rows that share their smallest hashes are likely to share columns
            place = ((np.arange(tile.n_cols, dtype=np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15 * (2 * seed + 1) % (1 << 64))).tolist()
            order = sorted((min(place[c] for c in t), i) for i, t in lists.items() if t)
            group: list[int] = []
            common: set[int] = set()
            for _, i in [*order, (None, None)]:
                both = common & lists[i] if i is not None and group else set()
                grown = (len(group) + 1) * len(both) - len(group) - 1 - len(both)
                if group and grown > len(group) * len(common) - len(group) - len(common):
                    group, common = [*group, i], both
                    continue
                if len(group) > 1 and len(group) * len(common) - len(group) - len(common) >= saving:
                    take(group, common)
                group, common = ([i], set(lists[i])) if i is not None else ([], set())
        rest = sorted((i, c) for i, t in lists.items() for c in t)
        r, c = (np.array(x, np.int64) for x in zip(*rest, strict=True)) if rest else (np.zeros(0, np.int64),) * 2
        sub, work = _REST.encode(Tile(tile.n_rows, tile.n_cols, r, c))
        parts = {"sizes": ints(np.array([(len(s), len(t)) for s, t in found]).ravel()), "s": ints(np.array([i for s, _ in found for i in s])), "t": ints(np.array([j for _, t in found for j in t]))}
        members = sum(len(s) + len(t) for s, t in found)
        return parts | {f"rest_{k}": v for k, v in sub.items()}, {"pieces": len(found), "members": members, "rest": len(r), "touched": members + work["bits"]}

    def _open(self, parts: Parts):
        sizes = from_ints(parts["sizes"]).reshape(-1, 2)
        n = np.arange(len(sizes))
        return np.repeat(n, sizes[:, 0]), from_ints(parts["s"]), np.repeat(n, sizes[:, 1]), from_ints(parts["t"]), len(sizes), {k[5:]: v for k, v in parts.items() if k.startswith("rest_")}

    def decode(self, parts, n_rows, n_cols):
        ps, s, pt, t, n, rest = self._open(parts)
        r, c, _ = _REST.decode(rest, n_rows, n_cols)
        rows, cols = [r], [c]
        for k in range(n):
            a, b = s[ps == k], t[pt == k]
            rows.append(np.repeat(a, len(b)))
            cols.append(np.tile(b, len(a)))
        r, c = np.concatenate(rows), np.concatenate(cols)
        order = np.lexsort((c, r))
        return r[order], c[order], None

    def right(self, parts, n_rows, n_cols, x):
        ps, s, pt, t, n, rest = self._open(parts)
        sums = add_at(pt, x[t], n)
        return _REST.right(rest, n_rows, n_cols, x) + add_at(s, sums[ps], n_rows)

    def left(self, parts, n_rows, n_cols, z):
        ps, s, pt, t, n, rest = self._open(parts)
        sums = np.bincount(ps, z[s], minlength=n)
        return _REST.left(rest, n_rows, n_cols, z) + np.bincount(t, sums[pt], minlength=n_cols)


def _shortest(n_rows: int, n_kinds: int, k: np.ndarray, r: np.ndarray, runs: np.ndarray) -> tuple[int, bytes]:
    """(form, body) of a group with tuple numbers k at rows r, in the order of the tuples: only the shortest form is made."""
    width = width_of(max(n_rows, n_kinds + 1))
    lengths = {0: (n_kinds + len(r)) * width, 1: runs.size * width, 2: n_rows * width_of(n_kinds)}
    kind = min(lengths, key=lambda o: -(-lengths[o] // 8))
    if kind == 2:
        dense = np.zeros(n_rows, np.int64)
        dense[r] = k + 1
        return kind, pack_fixed(dense, width_of(n_kinds))
    return kind, pack_fixed(np.concatenate([np.bincount(k, minlength=n_kinds), r]) if kind == 0 else runs.ravel(), width)


def _single_columns(n_rows: int, columns: list[int], order: np.ndarray, cut: np.ndarray, rows: np.ndarray, vals: np.ndarray):
    """(head, tuples, body) of each group of one column: sorted all at once, with offset lists of the usual width packed at once."""
    if not columns:
        return
    cols = np.array(columns)
    n = cut[cols + 1] - cut[cols]
    ends = np.cumsum(n)
    cells = order[np.repeat(cut[cols] - ends + n, n) + np.arange(int(ends[-1]))]
    g, r, v = np.repeat(np.arange(len(cols)), n), rows[cells], vals[cells]
    by = np.lexsort((r, v, g))  # a group's cells stay in its place
    r, v = r[by], v[by]
    kind_at = np.concatenate([[True], (g[1:] != g[:-1]) | (v[1:] != v[:-1])])
    k = np.cumsum(kind_at) - 1
    counts, kinds = np.bincount(k), v[kind_at]
    kind_cut = np.concatenate([[0], np.cumsum(np.bincount(g[kind_at], minlength=len(cols)))])
    run_at = np.flatnonzero(kind_at | np.concatenate([[True], r[1:] != r[:-1] + 1]))
    run_cut = np.searchsorted(run_at, np.concatenate([[0], ends]))
    runs = np.column_stack([k[run_at], r[run_at], np.diff(np.append(run_at, len(r)))])
    n_kinds, n_runs, width = np.diff(kind_cut), np.diff(run_cut), width_of(n_rows)
    sizes = [-(-x // 8) for x in ((n_kinds + n) * width, 3 * n_runs * width, n_rows * np.maximum(1, np.frexp(n_kinds.astype(float))[1]))]
    listed = (sizes[0] <= sizes[1]) & (sizes[0] <= sizes[2]) & (n_kinds < n_rows)
    # lists of one width: the counts of a group's tuples, then its rows, filled up to whole bytes
    some = np.flatnonzero(listed)
    used = (n_kinds + n)[some]
    room = 8 * -(-used * width // 8)
    bits = np.zeros(int(room.sum()), np.uint8)
    first, own = np.cumsum(room) - room, np.cumsum(used) - used
    numbers = np.empty(int(used.sum()), np.int64)
    spread = lambda start, count: np.repeat(start - np.cumsum(count) + count, count) + np.arange(int(count.sum()))
    numbers[spread(own, n_kinds[some])] = counts[spread(kind_cut[some], n_kinds[some])]
    numbers[spread(own + n_kinds[some], n[some])] = r[spread(ends[some] - n[some], n[some])]
    place = np.repeat(first - own * width, used) + np.arange(len(numbers)) * width
    for b in range(width):
        bits[place + b] = numbers >> b & 1
    packed, first = np.packbits(bits, bitorder="little").tobytes(), (first // 8).tolist()
    at = dict(zip(some.tolist(), zip(first, sizes[0][some].tolist(), strict=True), strict=True))
    kind_cut, run_cut, ends, n = kind_cut.tolist(), run_cut.tolist(), ends.tolist(), n.tolist()
    for i in range(len(cols)):
        a, b = kind_cut[i], kind_cut[i + 1]
        mine = run_cut[i], run_cut[i + 1]
        if i in at:
            kind, body = 0, packed[at[i][0] : at[i][0] + at[i][1]]
        else:
            span = slice(ends[i] - n[i], ends[i])
            kind, body = _shortest(n_rows, b - a, k[span] - a, r[span], runs[mine[0] : mine[1]] - [a, 0, 0])
        yield (kind, b - a, n[i], mine[1] - mine[0], len(body)), kinds[a:b], body


class ColGroup(Format):
    """Columns that are non-zero on similar rows are coded together: a dictionary of value tuples, and for every row the
    tuple it has, as offset lists, as runs, or as one code per row, whichever is shortest."""

    name, valued, most = "colgroup", True, 1 << 18

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        vals = np.ones(tile.nnz) if tile.vals is None else tile.vals
        order = np.lexsort((tile.rows, tile.cols))
        per_col = np.bincount(tile.cols, minlength=tile.n_cols)
        cut = np.concatenate([[0], np.cumsum(per_col)])
        rows_of = lambda c: tile.rows[order[cut[c] : cut[c + 1]]]
        used = np.flatnonzero(per_col)
        # a sample of rows decides what goes together; the encoding is exact
        step = max(1, int(1 / float(tile.opts.get("sample", 0.05))) if tile.n_rows > 2_000 else 1)
        lead = used[np.lexsort((used, -per_col[used], tile.rows[order[cut[used]]]))].tolist() if len(used) else []
        seen = np.flatnonzero(tile.rows[order] % step == 0)
        seen_rows, seen_cut = tile.rows[order[seen]].tolist(), np.searchsorted(seen, cut).tolist()
        groups: list[list[int]] = []
        for c in lead:
            if groups and len(groups[-1]) < int(tile.opts.get("widest", 4)):
                a, b = (seen_rows[seen_cut[x] : seen_cut[x + 1]] for x in (groups[-1][0], c))
                shared = len(set(a).intersection(b)) if a and b else 0
                if shared and 2 * shared >= len(a) + len(b) - shared:
                    groups[-1].append(c)
                    continue
            groups.append([c])
        parts, tuples, touched = {"groups": ints(np.array([len(g) for g in groups])), "cols": ints(np.array([c for g in groups for c in g]))}, 0, 0
        heads, values, bodies = [], [], []
        alone = _single_columns(tile.n_rows, [g[0] for g in groups if len(g) == 1], order, cut, tile.rows, vals)
        for g in groups:
            if len(g) == 1:
                head, kinds, body = next(alone)
                heads.append(head)
                values.append(kinds)
                bodies.append(body)
                tuples += len(kinds)
                touched += head[2] + len(kinds)
                continue
            where = [order[cut[c] : cut[c + 1]] for c in g]
            rows, at = np.unique(np.concatenate([tile.rows[w] for w in where]), return_inverse=True)
            grid = np.zeros((len(rows), len(g)))
            grid[at, np.repeat(np.arange(len(g)), [len(w) for w in where])] = vals[np.concatenate(where)]
            kinds, code = np.unique(grid, axis=0, return_inverse=True)
            code = code.ravel()
            by = np.lexsort((rows, code))
            r, k = rows[by], code[by]
            fresh = np.ones(len(r), bool)
            fresh[1:] = (k[1:] != k[:-1]) | (r[1:] != r[:-1] + 1)
            first = np.flatnonzero(fresh)
            runs = np.column_stack([k[first], r[first], np.diff(np.append(first, len(r)))])
            kind, body = _shortest(tile.n_rows, len(kinds), k, r, runs)
            heads.append((kind, len(kinds), len(r), len(runs), len(body)))
            values.append(kinds.ravel())
            bodies.append(body)
            tuples += len(kinds)
            touched += len(r) + kinds.size
        parts |= {"heads": ints(np.array(heads).ravel()), "values": np.concatenate([np.zeros(0), *values]).astype(np.float64).tobytes(), "body": b"".join(bodies), "plain": header(int(tile.vals is None))}
        return parts, {"groups": len(groups), "tuples": tuples, "touched": touched}

    def _groups(self, parts: Parts, n_rows: int):
        """(columns, tuples, tuple number, row) of every group."""
        sizes, cols, heads = from_ints(parts["groups"]), from_ints(parts["cols"]), from_ints(parts["heads"]).reshape(-1, 5)
        values, at, v, b = np.frombuffer(parts["values"], np.float64), 0, 0, 0
        for size, (kind, n_kinds, n, n_runs, length) in zip(sizes, heads, strict=True):
            body = parts["body"][b : b + length]
            width = width_of(max(n_rows, n_kinds + 1))
            if kind == 0:
                raw = unpack_fixed(body, width, n_kinds + n)
                code, rows = np.repeat(np.arange(n_kinds), raw[:n_kinds]), raw[n_kinds:]
            elif kind == 1:
                runs = unpack_fixed(body, width, 3 * n_runs).reshape(-1, 3)
                code = np.repeat(runs[:, 0], runs[:, 2])
                rows = np.repeat(runs[:, 1] - np.cumsum(runs[:, 2]) + runs[:, 2], runs[:, 2]) + np.arange(len(code))
            else:
                dense = unpack_fixed(body, width_of(n_kinds), n_rows)
                rows = np.flatnonzero(dense)
                code = dense[rows] - 1
            yield cols[at : at + size], values[v : v + n_kinds * size].reshape(n_kinds, size), code, rows
            at, v, b = at + size, v + n_kinds * size, b + length

    def decode(self, parts, n_rows, n_cols):
        r, c, v = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        for cols, kinds, code, rows in self._groups(parts, n_rows):
            grid = kinds[code]
            i, j = np.nonzero(grid)
            r.append(rows[i])
            c.append(cols[j])
            v.append(grid[i, j])
        r, c, v = np.concatenate(r), np.concatenate(c), np.concatenate(v)
        order = np.lexsort((c, r))
        return r[order], c[order], None if from_header(parts["plain"])[0] else v[order]

    def right(self, parts, n_rows, n_cols, x):
        y = np.zeros((n_rows, *x.shape[1:]))
        for cols, kinds, code, rows in self._groups(parts, n_rows):
            y[rows] += (kinds @ x[cols])[code]  # a row occurs once per group
        return y

    def left(self, parts, n_rows, n_cols, z):
        y = np.zeros(n_cols)
        for cols, kinds, code, rows in self._groups(parts, n_rows):
            y[cols] += np.bincount(code, z[rows], minlength=len(kinds)) @ kinds
        return y
