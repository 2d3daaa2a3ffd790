"""Column functions, and the UDF, UDAF and UDTF surface."""

from __future__ import annotations

import lzma
import zlib
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..formats.registry import FORMATS


def morton(row: Column, col: Column, bits: int) -> Column:
    """Bits of row and column in turn, the row's first: built-in shifts only."""
    bit = lambda c, i, s: F.shiftleft(F.shiftright(c, i).bitwiseAND(1).cast("bigint"), 2 * i + s)
    return reduce(lambda a, b: a + b, [bit(row, i, 1) + bit(col, i, 0) for i in range(bits)])


def width_bits(most: Column) -> Column:
    return F.greatest(F.floor(F.log2(most)) + 1, F.lit(1)).cast("int")


def gaps(a: Column) -> Column:
    """First element, then differences."""
    return F.transform(a, lambda x, i: F.when(i == 0, x).otherwise(x - F.get(a, i - 1)))


def list_diff(a: Column, b: Column) -> Column:
    return F.struct(F.array_except(a, b).alias("added"), F.array_except(b, a).alias("dropped"))


def runs(a: Column) -> Column:
    """(start, length) of the stretches of consecutive numbers in a sorted list."""
    first = F.filter(a, lambda x, i: (i == 0) | (x != F.get(a, i - 1) + 1))
    last = F.filter(a, lambda x, i: (i == F.size(a) - 1) | (x + 1 != F.get(a, i + 1)))
    return F.zip_with(first, last, lambda s, e: F.struct(s.alias("start"), (e - s + 1).alias("length")))


def merge_metrics(a: Column, b: Column) -> Column:
    return F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def register_functions(spark: SparkSession) -> None:
    """SQL names: gap_bits, varint_len (scalar), deflate_bits, lzma_bits (aggregates over an edge's packed 8 bytes),
    grammar_expand, quad_leaves, decode_rows (table functions over a tile)."""
    from pyspark.sql.functions import pandas_udf, udtf

    @pandas_udf("bigint")
    def gap_bits(gap: pd.Series) -> pd.Series:
        return 2 * np.floor(np.log2(gap.fillna(0) + 1)).astype("int64") + 1

    @pandas_udf("bigint")
    def varint_len(v: pd.Series) -> pd.Series:
        return pd.Series(np.maximum(1, -(-np.frexp(np.maximum(v.fillna(0), 1).astype(float))[1] // 7)).astype("int64"))

    def squeezed(how):
        @pandas_udf("bigint")
        def bits(pairs: pd.Series) -> int:
            return 8 * len(how(np.sort(pairs.to_numpy(np.int64)).astype("<u8").tobytes()))

        return bits

    spark.udf.register("gap_bits", gap_bits)
    spark.udf.register("varint_len", varint_len)
    spark.udf.register("deflate_bits", squeezed(lambda b: zlib.compress(b, 6)))
    spark.udf.register("lzma_bits", squeezed(lzma.compress))

    def cells(fmt_default):
        class Cells:
            def eval(self, parts: dict, n_rows: int, n_cols: int, fmt: str = fmt_default):
                r, c, _ = FORMATS[fmt].decode({k: bytes(v) for k, v in parts.items()}, n_rows, n_cols)
                yield from zip(r.tolist(), c.tolist(), strict=True)

        return udtf(Cells, returnType="row bigint, col bigint")

    spark.udtf.register("decode_rows", cells("csr"))
    spark.udtf.register("quad_leaves", cells("quadbits"))
    spark.udtf.register("grammar_expand", cells("pg_w32"))


def byte_bits(kind: str):
    """Grouped-aggregate function over (row, col): bits of a byte compressor on the group's 32-bit pairs."""
    how = {"deflate": lambda b: zlib.compress(b, 6), "lzma": lzma.compress}[kind]

    def bits(table: pa.Table) -> pa.Table:
        r, c = (np.asarray(table.column(k)) for k in ("row", "col"))
        order = np.lexsort((c, r))
        return pa.table({"bits": [8 * len(how(np.column_stack([r[order], c[order]]).astype("<u4").tobytes()))]})

    return bits
