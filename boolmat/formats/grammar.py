"""Recursive pairing over the row-by-row symbol sequence of a matrix.

A symbol is value index * n_cols + column. The pair of adjacent symbols that occurs most often, never across a row end,
becomes a rule; its occurrences become the rule's symbol; and so on until no pair occurs `min_count` times. Rules are
renumbered by height, so that both products run over heights, not over rules. Three codings: 32-bit numbers, fixed-width
numbers, and fixed-width rules with an entropy-coded sequence.
"""

from __future__ import annotations

import heapq
from array import array

import numpy as np

from ..bits import fold_decode, fold_encode_best, pack_fixed, unpack_fixed, width_of
from .base import Format, Parts, Tile, add_at, from_header, from_ints, header, ints, row_lengths


def pair_exact(symbols: np.ndarray, lengths: np.ndarray, first_rule: int, min_count: int = 2, max_rules: int | None = None) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """(rules, sequence, row lengths): one pair at a time, the most frequent first, ties to the smallest pair.

    The sequence is a linked list with a gap behind every row; each pair keeps the places where it started. A pair's
    places are all made in one step and only lost later, so pairs below `min_count` are never kept; lost places stay in
    the lists, are left out of the counts, and are seen by their symbols.
    """
    ends = np.cumsum(lengths)
    start = np.insert(symbols.astype(np.int64), ends, -1) if len(lengths) else np.zeros(0, np.int64)
    n, span = len(start), first_rule + len(symbols) + 1
    key = np.where((start[:-1] >= 0) & (start[1:] >= 0), start[:-1] * span + start[1:], -1)
    by = np.argsort(key, kind="stable")
    key = key[by]
    cuts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]])) if len(key) else np.zeros(1, np.int64)
    counts: dict[int, int] = {}
    places: dict[int, np.ndarray | list[int]] = {}
    often = np.diff(cuts) >= min_count
    for a, b in zip(cuts[:-1][often].tolist(), cuts[1:][often].tolist(), strict=True):
        if key[a] >= 0:
            counts[int(key[a])], places[int(key[a])] = b - a, by[a:b]
    s, nxt, prv = array("q", start.tobytes()), array("q", np.arange(1, n + 1).tobytes()), array("q", np.arange(-1, n - 1).tobytes())
    heaps: dict[int, list[int]] = {}  # pairs by count, each pair once, under a count that it has or had
    for k, c in counts.items():
        heaps.setdefault(c, []).append(k)  # in order
    rules: list[tuple[int, int]] = []
    top = max(heaps, default=0)
    while top >= min_count and (max_rules is None or len(rules) < max_rules):
        heap = heaps.get(top)
        if not heap:
            heaps.pop(top, None)
            top -= 1
            continue
        pair = heapq.heappop(heap)
        here = counts.get(pair, 0)
        if here < min_count:
            places.pop(pair, None)
            counts.pop(pair, None)
            continue
        if here != top:
            heapq.heappush(heaps.setdefault(here, []), pair)
            continue
        new, (left, right) = first_rule + len(rules), divmod(pair, span)
        rules.append((left, right))
        del counts[pair]
        where = places.pop(pair)
        fresh: dict[int, list[int]] = {}
        for i in sorted(where) if isinstance(where, list) else where.tolist():
            j = nxt[i]
            if s[i] != left or j >= n or s[j] != right:
                continue
            before, after = prv[i], nxt[j]
            if before >= 0 and s[before] >= 0:
                old = s[before] * span + left
                if old in counts:
                    counts[old] -= 1
                k = s[before] * span + new
                fresh.setdefault(k, []).append(before)
                counts[k] = counts.get(k, 0) + 1
            if after < n and s[after] >= 0:
                old = right * span + s[after]
                if old in counts:
                    counts[old] -= 1
                k = new * span + s[after]
                fresh.setdefault(k, []).append(i)
                counts[k] = counts.get(k, 0) + 1
            s[i], s[j] = new, -2
            nxt[i] = after
            if after < n:
                prv[after] = i
        for k, at in fresh.items():
            if counts[k] >= min_count:
                places[k] = at
                heapq.heappush(heaps.setdefault(counts[k], []), k)
                top = max(top, counts[k])
            else:
                del counts[k]
    out = np.frombuffer(s, np.int64)
    out = out[out != -2]
    stop = np.flatnonzero(out == -1)
    return rules, out[out >= 0], np.diff(np.concatenate([[-1], stop])) - 1


def pair_batched(symbols: np.ndarray, lengths: np.ndarray, first_rule: int, min_count: int = 2, max_rules: int | None = None) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """The same in rounds: all pairs with at least half of the largest count at once, left to right within a row."""
    rows = np.repeat(np.arange(len(lengths)), lengths)
    s, rules, span = symbols.astype(np.int64), [], first_rule + len(symbols) + 1
    while len(s) > 1 and (max_rules is None or len(rules) < max_rules):
        key = np.where(rows[1:] == rows[:-1], s[:-1] * span + s[1:], -1)
        kinds, which, counts = np.unique(key, return_inverse=True, return_counts=True)
        counts[kinds < 0] = 0
        most = int(counts.max())
        if most < min_count:
            break
        goal = max(min_count, -(-most // 2))
        while True:
            good = (counts >= goal)[which]
            spots = np.flatnonzero(good)
            fresh = np.ones(len(spots), bool)
            fresh[1:] = spots[1:] != spots[:-1] + 1
            run = np.maximum.accumulate(np.where(fresh, np.arange(len(spots)), 0))
            taken = spots[(np.arange(len(spots)) - run) % 2 == 0]  # every second one of overlapping pairs
            used = np.bincount(which[taken], minlength=len(kinds))
            poor = used < min_count
            taken = taken[~poor[which[taken]]]
            if len(taken):
                break
            best = int(np.argmax(counts))  # overlaps spoilt all: the most frequent pair alone
            counts = np.where(np.arange(len(counts)) == best, counts, 0)
            goal = min_count
        chosen = np.unique(which[taken])
        number = np.full(len(kinds), -1)
        number[chosen] = first_rule + len(rules) + np.arange(len(chosen))
        rules += [(int(k) // span, int(k) % span) for k in kinds[chosen]]
        s[taken] = number[which[taken]]
        stay = np.ones(len(s), bool)
        stay[taken + 1] = False
        s, rows = s[stay], rows[stay]
    return rules, s, np.bincount(rows, minlength=len(lengths))


def by_height(rules: list[tuple[int, int]], seq: np.ndarray, first_rule: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rules, number of rules per height, sequence) renumbered by height, then by pair."""
    table = np.array(rules, np.int64).reshape(-1, 2)
    height = np.zeros(len(table), np.int64)
    for i, (a, b) in enumerate(rules):
        height[i] = 1 + max(height[a - first_rule] if a >= first_rule else 0, height[b - first_rule] if b >= first_rule else 0)
    order = np.lexsort((table[:, 1], table[:, 0], height))
    new = np.empty(len(table), np.int64)
    new[order] = np.arange(len(table))
    rename = lambda v: np.where(v >= first_rule, first_rule + new[np.maximum(v - first_rule, 0)], v) if len(table) else v
    return rename(table[order]), np.bincount(height, minlength=1)[1:], rename(seq)


class PairGrammar(Format):
    """opts: min_count, max_rules, mode ('exact' or 'batched'), coding given by the format."""

    valued = True
    most = 1 << 18

    def __init__(self, coding: str):
        self.coding, self.name = coding, {"w32": "pg_w32", "packed": "pg_packed", "folded": "pg_folded"}[coding]

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        if tile.vals is None:
            values, which = np.ones(1), np.zeros(tile.nnz, np.int64)
        else:
            values, which = np.unique(tile.vals, return_inverse=True)
            values = values if len(values) else np.ones(1)
        terminals = len(values) * max(1, tile.n_cols)
        if "grammar" not in tile.made:  # the three codings write the same rules
            pairing = pair_batched if tile.opts.get("mode", "exact") == "batched" else pair_exact
            limit = tile.opts.get("max_rules")
            rules, seq, lengths = pairing(which * max(1, tile.n_cols) + tile.cols, row_lengths(tile.rows, tile.n_rows), terminals, int(tile.opts.get("min_count", 2)), int(limit) if limit else None)
            tile.made["grammar"] = *by_height(rules, seq, terminals), lengths
        table, heights, seq, lengths = tile.made["grammar"]
        top = terminals + len(table)
        width, width_len = width_of(top), width_of(int(lengths.max()) if len(lengths) else 0)
        parts = {"head": header(len(table), len(seq), width, width_len, terminals), "heights": ints(heights), "values": values.astype(np.float64).tobytes()}
        if self.coding == "w32":
            parts |= {"rules": ints(table.ravel()), "final": ints(seq), "lengths": ints(lengths)}
        else:
            parts |= {"rules": pack_fixed(table.ravel(), width), "lengths": pack_fixed(lengths, width_len)}
            parts["final"] = pack_fixed(seq, width) if self.coding == "packed" else fold_encode_best(seq)
        return parts, {"rules": len(table), "symbols": len(seq), "touched": 2 * len(table) + len(seq)}

    def _open(self, parts: Parts, n_rows: int):
        n_rules, n_seq, width, width_len, terminals = from_header(parts["head"])
        heights, values = from_ints(parts["heights"]), np.frombuffer(parts["values"], np.float64)
        if self.coding == "w32":
            table, seq, lengths = from_ints(parts["rules"]).reshape(-1, 2), from_ints(parts["final"]), from_ints(parts["lengths"])
        else:
            table = unpack_fixed(parts["rules"], width, 2 * n_rules).reshape(-1, 2)
            lengths = unpack_fixed(parts["lengths"], width_len, n_rows)
            seq = unpack_fixed(parts["final"], width, n_seq) if self.coding == "packed" else fold_decode(parts["final"])
        return terminals, table, np.concatenate([[0], np.cumsum(heights)]), values, seq, np.repeat(np.arange(n_rows), lengths)

    def _met(self, parts: Parts, n_rows: int, n_cols: int):
        """What products need: the values and columns of the terminals, rules, heights, sequence and rows.

        With several values only terminals that occur are numbered: values times columns may be far more than the ones.
        """
        terminals, table, cuts, values, seq, rows = self._open(parts, n_rows)
        if len(values) == 1:
            return np.repeat(values, n_cols), np.arange(n_cols), table, cuts, seq, rows
        used = np.unique(np.concatenate([table.ravel(), seq]))
        used = used[: np.searchsorted(used, terminals)]
        short = lambda v: np.where(v < terminals, np.searchsorted(used, v), v - terminals + len(used))
        return values[used // max(1, n_cols)], used % max(1, n_cols), short(table), cuts, short(seq), rows

    def decode(self, parts, n_rows, n_cols):
        terminals, table, _, values, seq, rows = self._open(parts, n_rows)
        while len(big := np.flatnonzero(seq >= terminals)):
            times = np.ones(len(seq), np.int64)
            times[big] = 2
            pair = table[seq[big] - terminals]
            first = np.cumsum(times) - times
            out = np.repeat(seq, times)
            out[first[big]], out[first[big] + 1] = pair[:, 0], pair[:, 1]
            seq, rows = out, np.repeat(rows, times)
        cols = seq % max(1, n_cols)
        order = np.lexsort((cols, rows))
        vals = values[seq // max(1, n_cols)]
        return rows[order], cols[order], None if (values == 1).all() and len(values) == 1 else vals[order]

    def right(self, parts, n_rows, n_cols, x):
        values, cols, table, cuts, seq, rows = self._met(parts, n_rows, n_cols)
        terminals = len(cols)
        w = np.concatenate([values.reshape(-1, *[1] * (x.ndim - 1)) * x[cols], np.zeros((len(table), *x.shape[1:]))])
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            w[terminals + a : terminals + b] = w[table[a:b, 0]] + w[table[a:b, 1]]
        return add_at(rows, w[seq], n_rows)

    def left(self, parts, n_rows, n_cols, z):
        values, cols, table, cuts, seq, rows = self._met(parts, n_rows, n_cols)
        terminals = len(cols)
        w = np.bincount(seq, z[rows], minlength=terminals + len(table))
        for a, b in reversed(list(zip(cuts[:-1], cuts[1:], strict=True))):
            down = np.repeat(w[terminals + a : terminals + b], 2)
            w = w + np.bincount(table[a:b].ravel(), down, minlength=len(w))
        return np.bincount(cols, values * w[:terminals], minlength=n_cols)
