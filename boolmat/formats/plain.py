"""Uncompressed forms and general-purpose byte compressors: coordinate lists, row lists, bitmaps, deflate, lzma."""

from __future__ import annotations

import lzma
import zlib

import numpy as np

from .base import Format, Parts, Tile, from_ints, ints, row_lengths

#: A dense tile has at most this many cells.
DENSE_CELLS = 1 << 28


class EdgeList(Format):
    """32-bit row and column pairs (and values, if there are any)."""

    name, valued = "edgelist", True

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        parts = {"pairs": np.column_stack([tile.rows, tile.cols]).astype(np.uint32).tobytes()}
        if tile.vals is not None:
            parts["vals"] = tile.vals.astype(np.float64).tobytes()
        return parts, {"touched": tile.nnz}

    def decode(self, parts, n_rows, n_cols):
        pairs = np.frombuffer(parts["pairs"], np.uint32).reshape(-1, 2).astype(np.int64)
        return pairs[:, 0], pairs[:, 1], np.frombuffer(parts["vals"], np.float64) if "vals" in parts else None


class Csr(Format):
    """Row lengths and columns as 32-bit numbers."""

    name, valued = "csr", True

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        parts = {"lengths": ints(row_lengths(tile.rows, tile.n_rows)), "cols": ints(tile.cols)}
        if tile.vals is not None:
            parts["vals"] = tile.vals.astype(np.float64).tobytes()
        return parts, {"touched": tile.nnz}

    def decode(self, parts, n_rows, n_cols):
        return np.repeat(np.arange(n_rows), from_ints(parts["lengths"])), from_ints(parts["cols"]), np.frombuffer(parts["vals"], np.float64) if "vals" in parts else None


class Dense(Format):
    """One bit per cell; refused above DENSE_CELLS cells."""

    name = "dense"

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        if tile.n_rows * tile.n_cols > DENSE_CELLS:
            raise ValueError(f"a dense tile of {tile.n_rows} x {tile.n_cols} cells is too large")
        grid = np.zeros((tile.n_rows, tile.n_cols), bool)
        grid[tile.rows, tile.cols] = True
        return {"bits": np.packbits(grid.ravel()).tobytes()}, {"touched": tile.n_rows * tile.n_cols}

    def _grid(self, parts, n_rows, n_cols):
        return np.unpackbits(np.frombuffer(parts["bits"], np.uint8), count=n_rows * n_cols).reshape(n_rows, n_cols)

    def decode(self, parts, n_rows, n_cols):
        return *np.nonzero(self._grid(parts, n_rows, n_cols)), None

    def right(self, parts, n_rows, n_cols, x):
        return self._grid(parts, n_rows, n_cols).astype(float) @ x

    def left(self, parts, n_rows, n_cols, z):
        return z @ self._grid(parts, n_rows, n_cols).astype(float)


class Squeezed(Format):
    """The coordinate list through a byte compressor; products decompress on the fly."""

    def __init__(self, name, squeeze, expand):
        self.name, self.squeeze, self.expand = name, squeeze, expand

    def encode(self, tile: Tile) -> tuple[Parts, dict[str, int]]:
        raw = np.column_stack([tile.rows, tile.cols]).astype(np.uint32).tobytes()
        return {"pairs": self.squeeze(raw)}, {"touched": tile.nnz}

    def decode(self, parts, n_rows, n_cols):
        pairs = np.frombuffer(self.expand(parts["pairs"]), np.uint32).reshape(-1, 2).astype(np.int64)
        return pairs[:, 0], pairs[:, 1], None


DEFLATE = Squeezed("deflate", lambda b: zlib.compress(b, 6), zlib.decompress)
LZMA = Squeezed("lzma", lzma.compress, lzma.decompress)
