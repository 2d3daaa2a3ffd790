"""Tile formats: worked examples, losslessness and both products on edge cases and random matrices."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from boolmat.bits import PrefixReader, fold_decode, fold_encode, pack_fixed, prefix_encode, unpack_fixed, width_of
from boolmat.formats.base import Tile
from boolmat.formats.grammar import by_height, pair_batched, pair_exact
from boolmat.formats.quadbits import QuadBits
from boolmat.formats.registry import FORMATS

R, C = np.array([0, 0, 0, 1, 1, 2, 2, 2, 3]), np.array([0, 1, 3, 0, 1, 0, 1, 3, 2])


@pytest.mark.parametrize("name", FORMATS)
def test_worked_example(name):
    f = FORMATS[name]
    parts, _ = f.encode(Tile(5, 4, R, C))
    assert f.right(parts, 5, 4, np.array([2.0, 0, 2, 4])).tolist() == [6, 2, 6, 2, 0]
    assert f.left(parts, 5, 4, np.array([1.0, 0, 1, 2, 1])).tolist() == [2, 2, 2, 2]


def test_quadrant_bits_of_the_worked_example():
    parts, work = QuadBits().encode(Tile(5, 4, R, C))
    assert work["bits"] == 24
    assert "".join(map(str, np.unpackbits(np.frombuffer(parts["bits"], np.uint8)))) == "100011111111010011000110"


def test_grammar_of_the_worked_example():
    rules, seq, lengths = pair_exact(C, np.array([3, 2, 3, 1, 0]), 4)
    assert rules == [(0, 1), (4, 3)]
    assert seq.tolist() == [5, 4, 5, 2] and lengths.tolist() == [1, 1, 1, 1, 0]


@pytest.mark.parametrize("pairing", [pair_exact, pair_batched])
def test_no_pair_is_left_and_expansion_is_lossless(pairing):
    rng = np.random.default_rng(1)
    lengths = rng.integers(0, 12, 60)
    seq = np.concatenate([np.sort(rng.choice(20, n, replace=False)) for n in lengths]).astype(np.int64)
    rules, out, left = pairing(seq, lengths, 20)
    seen = set()
    for row in np.split(out, np.cumsum(left)[:-1]):
        for pair in zip(row.tolist(), row.tolist()[1:]):
            assert pair not in seen
            seen.add(pair)
    expand = lambda s: [s] if s < 20 else expand(rules[s - 20][0]) + expand(rules[s - 20][1])
    assert [x for s in out.tolist() for x in expand(s)] == seq.tolist()
    table, heights, _ = by_height(rules, out, 20)
    assert len(table) == heights.sum()


cells = st.integers(1, 12).flatmap(lambda r: st.integers(1, 12).flatmap(lambda c: st.tuples(st.just(r), st.just(c), st.sets(st.integers(0, r * c - 1)))))


@settings(max_examples=25, deadline=None)
@given(cells)
def test_every_format_is_lossless(case):
    n_rows, n_cols, ones = case
    flat = np.array(sorted(ones), np.int64)
    r, c = flat // n_cols, flat % n_cols
    m = np.zeros((n_rows, n_cols))
    m[r, c] = 1
    x, z = np.arange(n_cols) + 1.0, np.arange(n_rows) + 2.0
    for f in FORMATS.values():
        parts, _ = f.encode(Tile(n_rows, n_cols, r, c))
        a, b, _ = f.decode(parts, n_rows, n_cols)
        assert a.tolist() == r.tolist() and b.tolist() == c.tolist(), f.name
        assert np.allclose(f.right(parts, n_rows, n_cols, x), m @ x) and np.allclose(f.left(parts, n_rows, n_cols, z), z @ m), f.name


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 1 << 30), max_size=300))
def test_codes_round_trip(values):
    v = np.array(values, np.int64)
    assert fold_decode(fold_encode(v)).tolist() == values
    w = width_of(max(values, default=0))
    assert unpack_fixed(pack_fixed(v, w), w, len(v)).tolist() == values
    if values:
        data, places = prefix_encode(v)
        assert PrefixReader(data).read(0, len(values))[0] == values
        assert PrefixReader(data).read(int(places[-1]), 1)[0] == values[-1:]


def test_reference_depth_and_row_access():
    rng = np.random.default_rng(2)
    rows = [np.sort(rng.choice(60, 20, replace=False))]
    for _ in range(40):
        rows.append(np.unique(np.concatenate([rows[-1][1:], rng.integers(0, 60, 1)])))
    r, c = np.repeat(np.arange(len(rows)), [len(x) for x in rows]), np.concatenate(rows)
    f = FORMATS["refcopy_prefix"]
    parts, work = f.encode(Tile(len(rows), 60, r, c))
    depth = f.differences(parts, len(rows)).depth
    assert work["copied_rows"] > 20 and depth.max() <= 3
    assert all(f.row_of(parts, len(rows), i) == rows[i].tolist() for i in (0, 17, 40))


def web_like(n=700, seed=3):
    """Rows that copy most of a row shortly before, with blocks that recur across the matrix."""
    rng = np.random.default_rng(seed)
    rows = [np.unique(rng.integers(0, n, 12))]
    for i in range(1, n):
        old = rows[max(0, i - int(rng.integers(1, 6)))]
        rows.append(np.unique(np.concatenate([old[rng.random(len(old)) < 0.9], rng.integers(0, n, 2), np.arange(i // 2, i // 2 + rng.integers(0, 6)) % n])))
    block = rng.random((64, 64)) < 0.1
    r, c = np.nonzero(block)
    cells = {(i, int(j)) for i, row in enumerate(rows) for j in row} | {(int(a) + o, int(b) + p) for a, b in zip(r, c) for o in (0, 128, 512) for p in (0, 256)}
    both = np.array(sorted(cells))
    return n, both[:, 0], both[:, 1]


@pytest.mark.parametrize("name", ["quadbits", "blocktree2d", "refcopy_prefix", "refcopy_stream", "pg_folded"])
def test_products_of_a_larger_matrix(name):
    n, r, c = web_like()
    f = FORMATS[name]
    parts, _ = f.encode(Tile(n, n, r, c))
    x = np.random.default_rng(0).random(n)
    dense = np.zeros((n, n))
    dense[r, c] = 1
    assert np.allclose(f.right(parts, n, n, x), dense @ x) and np.allclose(f.left(parts, n, n, x), x @ dense)
    wide = np.column_stack([x, x * 2])
    assert np.allclose(f.right(parts, n, n, wide), dense @ wide)
    back = f.decode(parts, n, n)
    assert np.array_equal(back[0], r) and np.array_equal(back[1], c)


@pytest.mark.parametrize("opts", [{}, {"rank_directory": True}, {"k": 4, "rank_directory": True}])
def test_cells_with_and_without_a_directory(opts):
    n, r, c = web_like()
    f = FORMATS["quadbits"]
    parts, work = f.encode(Tile(n, n, r, c, None, opts))
    ones, rng = set(zip(r.tolist(), c.tolist())), np.random.default_rng(1)
    for i, j in [*list(ones)[:200], *rng.integers(0, n, (200, 2)).tolist()]:
        assert f.cell(parts, i, j) == ((i, j) in ones)
    assert len(parts.get("rank", b"")) == (4 * -(-work["bits"] // 512) if opts else 0)


def test_a_quadrant_with_a_single_one_is_its_place():
    f = FORMATS["blocktree2d"]
    r, c = np.array([0, 100, 200, 255]), np.array([3, 90, 17, 255])
    parts, work = f.encode(Tile(256, 256, r, c))
    assert work["singles"] == 4 and work["nodes"] <= 3 and np.array_equal(f.decode(parts, 256, 256)[1], c)
    # copies of one block in one column range are evaluated once
    calls = []
    keep = f._stretches
    f._stretches = lambda t, h, name, at, x, turned: calls.append((h, len(name), len(set(zip(name.tolist(), at.tolist()))))) or keep(t, h, name, at, x, turned)
    try:
        n, r, c = web_like()
        parts, _ = f.encode(Tile(n, n, r, c))
        f.right(parts, n, n, np.ones(n))
    finally:
        del f._stretches
    assert any(distinct < asked for _, asked, distinct in calls)


def _one_row(row, ref, offset, own, min_run):
    """The numbers of a row, one column after the other."""
    out, left = [len(row), offset], row
    if offset:
        flags = [c in row for c in ref]
        runs = [] if flags[0] else [0]
        for i, f in enumerate(flags):
            if i and f == flags[i - 1]:
                runs[-1] += 1
            else:
                runs.append(1)
        runs = runs if flags[-1] else runs[:-1]
        out += [len(runs), *runs]
        left = [c for c in row if c not in ref]
    zig = lambda v: 2 * v if v >= 0 else -2 * v - 1
    pieces = []
    for c in left:
        if pieces and c == pieces[-1][-1] + 1:
            pieces[-1].append(c)
        else:
            pieces.append([c])
    wide, rest = [p for p in pieces if len(p) >= min_run], [c for p in pieces if len(p) < min_run for c in p]
    out.append(len(wide))
    for k, p in enumerate(wide):
        out += [p[0] - wide[k - 1][-1] - 2 if k else zig(p[0] - own), len(p) - min_run]
    return out + [c - rest[k - 1] - 1 if k else zig(c - own) for k, c in enumerate(rest)]


@pytest.mark.parametrize("window", [0, 3, 7, 70])
def test_refcopy_chooses_as_row_by_row(window, monkeypatch):
    from boolmat.bits import fold_decode
    from boolmat.formats import refcopy

    monkeypatch.setattr(refcopy, "CELLS", 150, raising=False)  # several stretches
    rng = np.random.default_rng(window)
    grid = rng.random((90, 40)) < rng.choice([0.0, 0.1, 0.5, 0.9], (90, 1))
    for i in range(1, 90):
        if rng.random() < 0.7:
            grid[i] = grid[max(0, i - int(rng.integers(1, 9)))] ^ (rng.random(40) < 0.05)
    rows = [np.flatnonzero(g).tolist() for g in grid]
    want, depth = [], []
    for i, row in enumerate(rows):
        best, d = _one_row(row, None, 0, i, 4), 0
        cost = lambda v: sum(2 * (x + 1).bit_length() - 1 for x in v)
        for off in range(1, min(window, i) + 1):
            if depth[i - off] < 3 and set(row) & set(rows[i - off]):
                found = _one_row(row, rows[i - off], off, i, 4)
                if cost(found) < cost(best):
                    best, d = found, depth[i - off] + 1
        want += best
        depth.append(d)
    r, c = np.nonzero(grid)
    parts, work = refcopy.RefCopy("stream").encode(Tile(90, 40, r, c, None, {"window": window}))
    assert fold_decode(parts["data"]).tolist() == want and work["copied_rows"] == sum(d > 0 for d in depth)


def test_refcopy_takes_many_rows_a_step():
    import sys

    rng = np.random.default_rng(2)
    cells = np.unique(rng.integers(0, 4000, 80_000) * 500 + rng.integers(0, 500, 80_000))
    steps = 0

    def count(frame, event, arg):
        nonlocal steps
        steps += event in ("call", "c_call")

    sys.setprofile(count)
    try:
        FORMATS["refcopy_stream"].encode(Tile(4000, 500, cells // 500, cells % 500))
    finally:
        sys.setprofile(None)
    assert steps < 30_000  # 2,356,531 row by row
