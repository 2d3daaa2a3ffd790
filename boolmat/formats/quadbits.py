"""Quadrant trees as pointer-free bit strings, and the same with copied subtrees.

The side is padded to a product of arities. A node splits into arity x arity quadrants; its bits say which hold ones.
Bits stand level by level. A visit holds the origins of one level's nodes and turns the next bits into the next level's
origins, so products need no rank structure. `rank_directory` adds one all the same, to weigh what leaving it out saves.
"""

from __future__ import annotations

import numpy as np

from ..bits import pack_fixed, unpack_fixed, width_of
from .base import Format, Parts, Tile, add_at, from_header, header


#: Bits per entry of the rank directory.
DIRECTORY = 512
_POPCOUNT = np.array([x.bit_count() for x in range(256)], np.int64)


def arities(side: int, k: int = 2, leaf_side: int = 1, top_k: int | None = None, top_levels: int = 0) -> list[int]:
    """Arity of each level from the root; top_k for the first levels gives a hybrid tree, leaf_side a wider last level."""
    out, covered = [], max(1, leaf_side)
    while covered < side:
        out.append(k)
        covered *= k
    if leaf_side > 1:
        out.append(leaf_side)
    out = out or [k]
    if top_k:
        have = int(np.prod(out))
        out = [top_k] * top_levels + out
        while len(out) > top_levels + 1 and np.prod(out[:-1]) >= side and np.prod(out) > have:
            out.pop(top_levels)
    return out


def codes(rows: np.ndarray, cols: np.ndarray, levels: list[int]) -> np.ndarray:
    """Interleaved digits of row and column, most significant level first."""
    z = np.zeros(len(rows), np.int64)
    step = int(np.prod(levels))
    for k in levels:
        step //= k
        z *= k
        z += rows // step % k
        z *= k
        z += cols // step % k
    return z


class QuadBits(Format):
    name = "quadbits"
    most = 1 << 19

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        levels = arities(max(tile.n_rows, tile.n_cols, 1), int(tile.opts.get("k", 2)), int(tile.opts.get("leaf_side", 1)), tile.opts.get("top_k"), int(tile.opts.get("top_levels", 0)))
        child, out, nodes = np.sort(codes(tile.rows, tile.cols, levels)), [], 0
        for k in levels[::-1]:  # from the cells up, each level's nodes in order
            above, digit = np.divmod(child, k * k)
            fresh = np.ones(len(above), bool)
            fresh[1:] = above[1:] != above[:-1]
            child = above[fresh]
            bits = np.zeros(len(child) * k * k, np.uint8)
            bits[(np.cumsum(fresh) - 1) * (k * k) + digit] = 1
            out.append(bits)
            nodes += len(child)
        bits = np.concatenate(out[::-1]) if out else np.zeros(0, np.uint8)
        parts = {"head": header(*levels), "size": header(len(bits)), "bits": np.packbits(bits).tobytes()}
        if tile.opts.get("rank_directory"):
            parts["rank"] = np.cumsum(np.add.reduceat(bits, np.arange(0, len(bits), DIRECTORY), dtype=np.uint32), dtype=np.uint32).tobytes() if len(bits) else b""
        return parts, {"nodes": nodes, "bits": len(bits), "touched": len(bits)}

    def leaves(self, parts: Parts) -> tuple[np.ndarray, np.ndarray]:
        """Rows and columns of the ones in tree order: one pass over the bits, a level at a time."""
        levels, (size,) = from_header(parts["head"]), from_header(parts["size"])
        bits = np.unpackbits(np.frombuffer(parts["bits"], np.uint8), count=size)
        r = c = np.zeros(1 if size else 0, np.int32 if np.prod(levels) < 1 << 31 else np.int64)
        step, at = int(np.prod(levels)), 0
        for k in levels:
            step //= k
            hit = np.flatnonzero(bits[at : at + len(r) * k * k])
            at += len(r) * k * k
            parent, digit = hit // (k * k), (hit % (k * k)).astype(r.dtype)
            r, c = r[parent] + digit // k * step, c[parent] + digit % k * step
        return r, c

    def decode(self, parts, n_rows, n_cols):
        r, c = self.leaves(parts)
        order = np.lexsort((c, r))
        return r[order].astype(np.int64), c[order].astype(np.int64), None

    def right(self, parts, n_rows, n_cols, x):
        r, c = self.leaves(parts)  # sums need no order
        return add_at(r, x[c], n_rows)

    def left(self, parts, n_rows, n_cols, z):
        r, c = self.leaves(parts)
        return add_at(c, z[r], n_cols)

    def cell(self, parts: Parts, i: int, j: int) -> bool:
        """Root-to-leaf test: the bits before a place are counted by words from the start, or from the last directory entry."""
        levels, (size,) = from_header(parts["head"]), from_header(parts["size"])
        packed = np.frombuffer(parts["bits"], np.uint8)
        ranks = np.frombuffer(parts["rank"], np.uint32) if "rank" in parts else None

        def ones(end: int) -> int:
            """Ones among the first `end` bits; with a directory at most DIRECTORY bits are looked at."""
            since = end // DIRECTORY if ranks is not None else 0
            near = packed[since * DIRECTORY // 8 : end // 8]
            tail = int(packed[end // 8]) >> (8 - end % 8) if end % 8 else 0
            return (int(ranks[since - 1]) if since else 0) + int(_POPCOUNT[near].sum()) + tail.bit_count()

        step, node = int(np.prod(levels)), 0
        if not size or i >= step or j >= step:
            return False
        start, before, width = 0, 0, 1  # of the level: first bit, ones ahead of it, nodes
        for k in levels:
            step //= k
            pos = start + node * k * k + (i // step) * k + j // step
            if not packed[pos // 8] >> (7 - pos % 8) & 1:
                return False
            node = ones(pos) - before
            end = start + width * k * k
            after = ones(end)
            start, before, width = end, after, after - before
            i, j = i % step, j % step
        return True


def _split(place: np.ndarray, height: int) -> tuple[np.ndarray, np.ndarray]:
    """Row and column of interleaved places within a quadrant of 2**height cells a side."""
    r = c = np.zeros(len(place), np.int64)
    for k in range(height):
        r, c = r | (place >> (2 * k + 1) & 1) << k, c | (place >> (2 * k) & 1) << k
    return r, c


class BlockTree(Format):
    """A quadrant tree in which a subtree that occurred before on its level is a pointer to its first occurrence, and a
    quadrant with a single one is the place of it.

    A table per level lists the different nodes with two ones or more (and the root). An entry is 0 (no one), the number
    of a node of the level below, or -1 - place. Products evaluate every (node, column range) once however many copies
    of it stand below one another, and likewise (node, row range) from the left.
    """

    name = "blocktree2d"
    #: Height of the quadrants whose products are kept as dense stretches of 2**MEMO values.
    MEMO = 4

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        levels = arities(max(tile.n_rows, tile.n_cols, 1), 2)
        z = np.unique(codes(tile.rows, tile.cols, levels))
        tables, prefix, some = [], z, z  # some: a cell of each node
        names, ones = np.ones(len(z), np.int64), np.ones(len(z), np.int64)
        for depth in range(len(levels)):  # bottom up: equal tuples of children get one number
            own, first_child, inverse = np.unique(prefix >> 2, return_index=True, return_inverse=True)
            children = np.zeros((len(own), 4), np.int64)
            children[inverse, prefix & 3] = names
            count = np.bincount(inverse, ones, minlength=len(own)).astype(np.int64)
            some = some[first_child]
            named = (count > 1) | (depth == len(levels) - 1)
            kinds, first, which = np.unique(children[named], axis=0, return_index=True, return_inverse=True)
            order = np.argsort(np.argsort(first))  # numbers by first occurrence
            names = -1 - (some & ((1 << 2 * (depth + 1)) - 1))
            names[named] = order[which.ravel()] + 1
            table = np.zeros_like(kinds)
            table[order] = kinds
            tables.append(table)
            prefix, ones = own, count
        parts, bits, singles = {"head": header(len(levels), len(z))}, 0, 0
        for depth, table in enumerate(tables):
            mask, refs = table != 0, table[table != 0]
            width = width_of(int(refs.max(initial=0)))
            parts[f"mask{depth}"] = header(len(table), width) + np.packbits(mask.ravel()).tobytes()
            bits += mask.size
            if depth:
                up = np.maximum(refs, 0)
                fresh = refs == np.maximum.accumulate(np.concatenate([[0], up[:-1]])) + 1 if len(refs) else np.zeros(0, bool)
                rest = refs[~fresh]
                alone = rest < 0
                parts[f"new{depth}"], parts[f"single{depth}"] = np.packbits(fresh).tobytes(), np.packbits(alone).tobytes()
                parts[f"copy{depth}"], parts[f"place{depth}"] = pack_fixed(rest[~alone], width), pack_fixed(-1 - rest[alone], 2 * depth)
                singles += int(alone.sum())
                bits += len(refs) + len(rest) + int((~alone).sum()) * width + int(alone.sum()) * 2 * depth
        return parts, {"nodes": sum(map(len, tables)), "singles": singles, "bits": bits, "touched": bits}

    def _tables(self, parts: Parts) -> list[np.ndarray]:
        depth, _ = from_header(parts["head"])
        out = []
        for d in range(depth):
            count, width = from_header(parts[f"mask{d}"][:16])
            table = np.unpackbits(np.frombuffer(parts[f"mask{d}"][16:], np.uint8), count=4 * count).astype(np.int64)
            hits = np.flatnonzero(table)
            if d and len(hits):
                fresh = np.unpackbits(np.frombuffer(parts[f"new{d}"], np.uint8), count=len(hits)).astype(bool)
                left = int((~fresh).sum())
                alone = np.unpackbits(np.frombuffer(parts[f"single{d}"], np.uint8), count=left).astype(bool)
                rest = np.empty(left, np.int64)
                rest[~alone] = unpack_fixed(parts[f"copy{d}"], width, int((~alone).sum()))
                rest[alone] = -1 - unpack_fixed(parts[f"place{d}"], 2 * d, int(alone.sum())).astype(np.int64)
                refs = np.cumsum(fresh)
                refs[~fresh] = rest
                table[hits] = refs
            out.append(table.reshape(-1, 4))
        return out

    def _down(self, tables: list[np.ndarray], stop: int, full: bool) -> tuple[tuple[np.ndarray, ...], tuple[np.ndarray, np.ndarray]]:
        """Nodes of height `stop` as (number, row, column), and the cells that were met as single ones above."""
        r = c = np.zeros(1 if full else 0, np.int64)
        name, met = np.ones(len(r), np.int64), [(r[:0], c[:0])]
        for height in range(len(tables), stop, -1):
            half = 1 << (height - 1)
            children = tables[height - 1][name - 1]
            node, digit = np.nonzero(children)
            r, c, name = r[node] + (digit >> 1) * half, c[node] + (digit & 1) * half, children[node, digit]
            alone = name < 0
            if alone.any():
                dr, dc = _split(-1 - name[alone], height - 1)
                met.append((r[alone] + dr, c[alone] + dc))
                r, c, name = r[~alone], c[~alone], name[~alone]
        return (name, r, c), (np.concatenate([m[0] for m in met]), np.concatenate([m[1] for m in met]))

    def decode(self, parts, n_rows, n_cols):
        (_, r, c), (sr, sc) = self._down(self._tables(parts), 0, from_header(parts["head"])[1] > 0)
        r, c = np.concatenate([r, sr]), np.concatenate([c, sc])
        order = np.lexsort((c, r))
        return r[order], c[order], None

    def _stretches(self, tables: list[np.ndarray], height: int, name: np.ndarray, at: np.ndarray, x: np.ndarray, turned: bool) -> np.ndarray:
        """Products of nodes of one height with the stretch of x from `at`: one row of 2**height values each.

        Equal (node, stretch) are evaluated once; `turned` takes the nodes from the left.
        """
        if height == 0:
            return x[at][:, None]
        keys, which = np.unique(name * len(x) + at, return_inverse=True)
        name, at = np.divmod(keys, len(x))
        half, out = 1 << (height - 1), np.zeros((len(keys), 1 << height))
        children = tables[height - 1][name - 1]
        node, digit = np.nonzero(children)
        child = children[node, digit]
        across, along = (digit & 1, digit >> 1) if not turned else (digit >> 1, digit & 1)
        base = at[node] + across * half
        alone = child < 0
        if alone.any():
            dr, dc = _split(-1 - child[alone], height - 1)
            inner, outer = (dc, dr) if not turned else (dr, dc)
            out += np.bincount((node[alone] << height) + along[alone] * half + outer, x[base[alone] + inner], minlength=out.size).reshape(out.shape)
        some = np.flatnonzero(~alone)
        if len(some):
            got = self._stretches(tables, height - 1, child[some], base[some], x, turned)
            for k in range(4):  # a node has at most one child of each digit
                own = np.flatnonzero(digit[some] == k)
                to = int(along[some[own[0]]]) * half if len(own) else 0
                out[node[some[own]], to : to + half] += got[own]
        return out[which.ravel()]

    def _product(self, parts: Parts, size: int, x: np.ndarray, turned: bool) -> np.ndarray:
        tables = self._tables(parts)
        stop = min(self.MEMO, len(tables))
        (name, r, c), (sr, sc) = self._down(tables, stop, from_header(parts["head"])[1] > 0)
        side = 1 << len(tables)
        wide = np.zeros(side)
        wide[: len(x)] = x
        to, at, single_to, single_at = (r, c, sr, sc) if not turned else (c, r, sc, sr)
        y = np.bincount(single_to, wide[single_at], minlength=side)
        if len(name):
            got = self._stretches(tables, stop, name, at, wide, turned)
            y = y + np.bincount((to[:, None] + np.arange(1 << stop)).ravel(), got.ravel(), minlength=side)
        return y[:size]

    def right(self, parts, n_rows, n_cols, x):
        return self._product(parts, n_rows, x, False) if x.ndim == 1 else np.column_stack([self._product(parts, n_rows, v, False) for v in x.T])

    def left(self, parts, n_rows, n_cols, z):
        return self._product(parts, n_cols, z, True)
