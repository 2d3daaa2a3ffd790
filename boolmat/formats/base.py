"""What every tile format offers.

A tile is a sparse matrix of n_rows x n_cols with cells (rows, cols, vals) sorted by row, then column, without repeats.
Formats keep it as named byte strings ("parts"), and multiply those parts by a vector from either side.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass, field

import numpy as np

from ..bits import pack_fixed, unpack_fixed, width_of

Parts = dict[str, bytes]


@dataclass
class Tile:
    n_rows: int
    n_cols: int
    rows: np.ndarray
    cols: np.ndarray
    vals: np.ndarray | None = None
    opts: dict = field(default_factory=dict)
    #: What one encoder has made of the tile and another may use.
    made: dict = field(default_factory=dict)

    @property
    def nnz(self) -> int:
        return len(self.rows)


class Format:
    """encode() gives parts and work counters; decode() the cells; right() M x; left() z M. By default products decode."""

    name = ""
    valued = False
    #: Ones that a tile may hold so that its encoder stays in a few hundred MB; fewer where it keeps Python objects.
    most = 1 << 20

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        raise NotImplementedError

    def decode(self, parts: Parts, n_rows: int, n_cols: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
        raise NotImplementedError

    def right(self, parts: Parts, n_rows: int, n_cols: int, x: np.ndarray) -> np.ndarray:
        r, c, v = self.decode(parts, n_rows, n_cols)
        return add_at(r, x[c] if v is None else (v.reshape(-1, *[1] * (x.ndim - 1)) * x[c]), n_rows)

    def left(self, parts: Parts, n_rows: int, n_cols: int, z: np.ndarray) -> np.ndarray:
        r, c, v = self.decode(parts, n_rows, n_cols)
        return add_at(c, z[r] if v is None else v * z[r], n_cols)


def add_at(index: np.ndarray, values: np.ndarray, size: int) -> np.ndarray:
    """Sums of values by index; values may have a second axis (several vectors at once)."""
    if values.ndim == 1:
        return np.bincount(index, values, minlength=size)
    return np.column_stack([np.bincount(index, v, minlength=size) for v in values.T]) if values.shape[1] else np.zeros((size, 0))


def ints(values: np.ndarray) -> bytes:
    return np.asarray(values, np.int32).tobytes()


def from_ints(data: bytes) -> np.ndarray:
    return np.frombuffer(data, np.int32).astype(np.int64)


def header(*numbers: int) -> bytes:
    return struct.pack(f"<{len(numbers)}q", *numbers)


def from_header(data: bytes) -> tuple[int, ...]:
    return struct.unpack(f"<{len(data) // 8}q", data)


def pack_columns(own: np.ndarray) -> bytes:
    """A tile's ascending column numbers: the first, their count, and the gaps at one width (0 for neighbours only)."""
    if not len(own):
        return header(0, 0)
    gaps = np.diff(own) - 1
    most = int(gaps.max(initial=0))
    width = width_of(most) if most else 0
    return header(int(own[0]), len(own)) + bytes([width]) + (pack_fixed(gaps, width) if width else b"")


def columns_of(data: bytes) -> np.ndarray:
    first, n = struct.unpack("<2q", data[:16])
    if not n:
        return np.zeros(0, np.int64)
    gaps = unpack_fixed(data[17:], data[16], n - 1) if data[16] else np.zeros(n - 1, np.int64)
    return np.concatenate([[first], first + np.cumsum(gaps + 1)]).astype(np.int64)


def row_lengths(rows: np.ndarray, n_rows: int) -> np.ndarray:
    return np.bincount(rows, minlength=n_rows)
