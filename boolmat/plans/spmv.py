"""Matrix-vector products and the choice of how the vector travels.

A vector is a DataFrame (id, value); ids without a row are 0. Three strategies:
broadcast: the vector is packed into one value and meets every tile (vectors of a checked size, a few MB);
dictionary: every tile gets exactly the entries its column dictionary names, by one shuffle of those entries;
edges: no tiles at all, a join of the edge list with the vector and a partial and final sum.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..formats.base import columns_of
from ..formats.registry import FORMATS
from ..model import BoolMatrix, CompressedMatrix

#: Vectors of up to this many bytes are broadcast: each tile's row carries a copy on its way to the kernel.
BROADCAST_BYTES = 8 << 20


def choose_spmv(n: int, iterations: int = 100, compressed: bool = True, limit: int = BROADCAST_BYTES, break_even: int = 3, tiles: int = 1) -> str:
    """'edges' for few iterations of a matrix that is not encoded yet, else by the size of the vector and of its copies."""
    if not compressed and iterations < break_even:
        return "edges"
    return "broadcast" if 8 * n <= limit and 8 * n * tiles <= 16 * limit else "dictionary"


def packed(vector: DataFrame, n: int) -> DataFrame:
    """One row (x BINARY): the dense vector as 64-bit floats."""
    entries = vector.agg(F.collect_list(F.struct(F.col("id").cast("bigint").alias("id"), F.col("value").cast("double").alias("value"))).alias("entries"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.column(0):
                x = np.zeros(n)
                flat = row.values
                if flat is not None and len(flat):
                    x[np.asarray(flat.field(0))] = np.asarray(flat.field(1))
                yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary())], names=["x"])

    return entries.mapInArrow(run, "x binary")


def spmv_edges(matrix: BoolMatrix, x: DataFrame, hint: str | None = None) -> DataFrame:
    """(id, value) of M x over the edge list, rows with ones only. hint: a join strategy for the vector's side."""
    side = x.select(F.col("id").alias("col"), F.col("value").alias("x"))
    joined = matrix.df.join(side.hint(hint) if hint else side, "col")
    value = F.col("x") * F.col("val") if matrix.valued else F.col("x")
    return joined.groupBy(F.col("row").alias("id")).agg(F.sum(value).alias("value"))


def spmv_left_edges(matrix: BoolMatrix, z: DataFrame) -> DataFrame:
    return spmv_edges(matrix.transpose(), z)


def spmv(cm: CompressedMatrix, x: DataFrame, strategy: str = "auto", emit: str = "all") -> DataFrame:
    """(id, value) of M x from tiles. emit='nonzero' leaves out rows without ones."""
    codec, keep = FORMATS[cm.fmt], emit == "all"
    strategy = choose_spmv(cm.n_cols, tiles=cm.blocks) if strategy == "auto" else strategy

    def one(t: dict, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = t["row_hi"] - t["row_lo"]
        y = codec.right(dict(t["parts"]), n, t["n_cols"], own)
        at = np.arange(n)
        if not keep:
            at = np.unique(codec.decode(dict(t["parts"]), n, t["n_cols"])[0])
        return at + t["row_lo"], np.asarray(y, float)[at]

    if strategy == "broadcast":
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    t = batch.slice(i, 1).to_pylist()[0]
                    ids, y = one(t, np.frombuffer(t["x"], np.float64)[columns_of(t["col_dict"])])
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(y)], names=["id", "value"])

        return whole_rows(cm, cm.df.crossJoin(F.broadcast(packed(x, cm.n_cols))).mapInArrow(run, "id bigint, value double"))

    entries = cm.used_columns().join(x.select(F.col("id").alias("col"), F.col("value").cast("double").alias("value")), "col").select("blk", "at", "value")

    def meet(tiles: pa.Table, own: pa.Table) -> pa.Table:
        if not tiles.num_rows:
            return pa.table({"id": pa.array([], pa.int64()), "value": pa.array([], pa.float64())})
        t = tiles.to_pylist()[0]
        local = np.zeros(t["n_cols"])
        if own.num_rows:
            local[np.asarray(own.column("at"))] = np.asarray(own.column("value"))
        ids, y = one(t, local)
        return pa.table({"id": ids, "value": y})

    return whole_rows(cm, cm.df.groupBy("blk").cogroup(entries.groupBy("blk")).applyInArrow(meet, "id bigint, value double"))


def whole_rows(cm: CompressedMatrix, y: DataFrame) -> DataFrame:
    """y, with the parts of rows that several tiles share summed; only matrices with such rows pay a shuffle."""
    return y.groupBy("id").agg(F.sum("value").alias("value")) if cm.segmented else y


def spmv_left(cm: CompressedMatrix, z: DataFrame, strategy: str = "auto") -> DataFrame:
    """(id, value) of z M from tiles: partial sums per tile over its own columns, then one sum by column."""
    codec = FORMATS[cm.fmt]
    strategy = choose_spmv(cm.n_rows, tiles=cm.blocks) if strategy == "auto" else strategy

    def one(t: dict, local: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        y = codec.left(dict(t["parts"]), t["row_hi"] - t["row_lo"], t["n_cols"], local)
        return columns_of(t["col_dict"]), np.asarray(y, float)

    if strategy == "broadcast":
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    t = batch.slice(i, 1).to_pylist()[0]
                    cols, y = one(t, np.frombuffer(t["x"], np.float64)[t["row_lo"] : t["row_hi"]])
                    yield pa.RecordBatch.from_arrays([pa.array(cols), pa.array(y)], names=["id", "value"])

        partial = cm.df.crossJoin(F.broadcast(packed(z, cm.n_rows))).mapInArrow(run, "id bigint, value double")
    else:
        def meet(tiles: pa.Table, own: pa.Table) -> pa.Table:
            if not tiles.num_rows:
                return pa.table({"id": pa.array([], pa.int64()), "value": pa.array([], pa.float64())})
            t = tiles.to_pylist()[0]
            local = np.zeros(t["row_hi"] - t["row_lo"])
            if own.num_rows:
                local[np.asarray(own.column("id")) - t["row_lo"]] = np.asarray(own.column("value"), dtype=float)
            cols, y = one(t, local)
            return pa.table({"id": cols, "value": y})

        partial = cm.df.groupBy("blk").cogroup(cm.tiles_of(z.select("id", "value"), "id").select("blk", "id", "value").groupBy("blk")).applyInArrow(meet, "id bigint, value double")
    return partial.groupBy("id").agg(F.sum("value").alias("value"))


def spmm(cm: CompressedMatrix, table: DataFrame, width: int) -> DataFrame:
    """(id, vec) of M X for a table (id, vec) of `width` components: the kernels take all components at once."""
    codec = FORMATS[cm.fmt]
    entries = cm.used_columns().join(table.select(F.col("id").alias("col"), F.col("vec").cast("array<double>").alias("vec")), "col").select("blk", "at", "vec")

    def meet(tiles: pa.Table, own: pa.Table) -> pa.Table:
        empty = pa.table({"id": pa.array([], pa.int64()), "vec": pa.array([], pa.list_(pa.float64()))})
        if not tiles.num_rows:
            return empty
        t = tiles.to_pylist()[0]
        local = np.zeros((t["n_cols"], width))
        if own.num_rows:
            local[np.asarray(own.column("at"))] = np.asarray(own.column("vec").combine_chunks().flatten()).reshape(-1, width)
        n = t["row_hi"] - t["row_lo"]
        y = codec.right(dict(t["parts"]), n, t["n_cols"], local)
        return pa.table({"id": np.arange(n) + t["row_lo"], "vec": pa.ListArray.from_arrays(np.arange(0, n * width + 1, width, dtype=np.int32), np.ascontiguousarray(y).ravel())})

    y = cm.df.groupBy("blk").cogroup(entries.groupBy("blk")).applyInArrow(meet, "id bigint, vec array<double>")
    if not cm.segmented:
        return y
    sums = y.select("id", F.posexplode("vec").alias("k", "c")).groupBy("id", "k").agg(F.sum("c").alias("c"))
    return sums.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("k", "c"))).alias("all")).select("id", F.col("all.c").alias("vec"))


def spmv_ternary(plus: CompressedMatrix, minus: CompressedMatrix, x: DataFrame) -> DataFrame:
    """(id, value) of (P - N) x: two Boolean products."""
    both = spmv(plus, x).unionAll(spmv(minus, x).select("id", (-F.col("value")).alias("value")))
    return both.groupBy("id").agg(F.sum("value").alias("value"))
