"""Matrices, compressed matrices and vectors as DataFrames."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .formats.base import Tile, columns_of, pack_columns
from .formats.registry import FORMATS
from .sources.tables import stored

#: Ones that a tile holds by default; an upper bound keeps payloads far below what a BINARY value may hold.
TILE_ONES = 1 << 20
TILE_SQL = "blk int, row_lo bigint, row_hi bigint, n_cols bigint, nnz bigint, col_dict binary, parts map<string,binary>, work map<string,bigint>"
TILE_ARROW = pa.schema([("blk", pa.int32()), ("row_lo", pa.int64()), ("row_hi", pa.int64()), ("n_cols", pa.int64()), ("nnz", pa.int64()), ("col_dict", pa.binary()), ("parts", pa.map_(pa.string(), pa.binary())), ("work", pa.map_(pa.string(), pa.int64()))])


@dataclass
class BoolMatrix:
    """Distinct cells (row, col) or, with values, (row, col, val), of an n_rows x n_cols matrix."""

    df: DataFrame
    n_rows: int
    n_cols: int
    #: Number of ones where it is known.
    nnz: int | None = None

    @property
    def valued(self) -> bool:
        return "val" in self.df.columns

    def transpose(self) -> BoolMatrix:
        return BoolMatrix(self.df.select(F.col("col").alias("row"), F.col("row").alias("col"), *(["val"] if self.valued else [])), self.n_cols, self.n_rows, self.nnz)


@dataclass
class CompressedMatrix:
    """One row per tile (columns in TILE_SQL). A tile numbers its own columns; col_dict lists them as packed gaps."""

    df: DataFrame
    fmt: str
    n_rows: int
    n_cols: int
    valued: bool = False
    opts: dict = field(default_factory=dict)
    #: Number of row blocks, and whether rows with more ones than a tile are spread over several tiles.
    blocks: int = 0
    segmented: bool = False
    #: (blk, row_lo, row_hi) of all tiles, without the work of encoding them.
    bounds: DataFrame | None = None

    def held(self, df: DataFrame) -> CompressedMatrix:
        """The same matrix over stored tiles."""
        return replace(self, df=df, bounds=None)

    def tiles_of(self, ids: DataFrame, at: str) -> DataFrame:
        """ids, once per tile whose rows hold its column `at`, with blk, row_lo and row_hi.

        Rows meet tiles through equal stretches of rows: a join by equality, then a test of the bounds.
        """
        n, stretches = max(1, self.n_rows), max(1, self.blocks or 1024)
        place = lambda c: F.floor(c * stretches / F.lit(n))
        bounds = (self.bounds if self.bounds is not None else self.df).select("blk", "row_lo", "row_hi").where("row_hi > row_lo")
        spread = bounds.withColumn("__s", F.explode(F.sequence(place(F.col("row_lo")), place(F.col("row_hi") - 1))))
        met = ids.withColumn("__s", place(F.col(at))).join(spread, "__s")
        return met.where((F.col(at) >= F.col("row_lo")) & (F.col(at) < F.col("row_hi"))).drop("__s")

    def used_columns(self) -> DataFrame:
        """(blk, at, col): which global column stands at which place of a tile."""
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for blk, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    cols = columns_of(raw)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cols), blk), pa.int32()), pa.array(np.arange(len(cols)), pa.int32()), pa.array(cols)], names=["blk", "at", "col"])

        return self.df.select("blk", "col_dict").mapInArrow(run, "blk int, at int, col bigint")


def blocks_for(nnz: int, most: int = TILE_ONES) -> int:
    return max(1, -(-nnz // most))


def row_blocks(matrix: BoolMatrix, blocks: int) -> tuple[DataFrame, DataFrame]:
    """(cells with blk, tiles (blk, row_lo, row_hi)) for equal row ranges, by arithmetic alone."""
    n = max(1, matrix.n_rows)
    lo = lambda b: F.ceil(b * F.lit(n) / F.lit(blocks)).cast("bigint")
    tiles = matrix.df.sparkSession.range(blocks).select(F.col("id").cast("int").alias("blk"), lo(F.col("id")).alias("row_lo"), F.least(lo(F.col("id") + 1), F.lit(matrix.n_rows)).alias("row_hi"))
    return matrix.df.withColumn("blk", F.floor(F.col("row") * blocks / F.lit(n)).cast("int")), tiles


def balanced_blocks(matrix: BoolMatrix, blocks: int, most: int = TILE_ONES) -> tuple[DataFrame, DataFrame, bool]:
    """(cells with blk, tiles, whether rows are split): row ranges with about equal numbers of ones.

    Ones are counted per row stretch, stretches get running sums (in two steps, so that no task holds all of them), and
    a stretch goes to the block of its first one. A row with more than `most` ones gets tiles of its own, one per
    column range of about `most` ones; at most total / most rows are like that.
    """
    spark, n = matrix.df.sparkSession, max(1, matrix.n_rows)
    stretches = min(n, max(4096, 16 * blocks))
    groups = min(stretches, 1024)
    place = F.floor(F.col("row") * stretches / F.lit(n))
    hubs = stored(matrix.df.groupBy("row").agg(F.count("*").alias("ones")).where(F.col("ones") > most), "hubs")
    split = hubs.limit(1).count() > 0
    rest = matrix.df.join(F.broadcast(hubs.select("row")) if split else hubs.select("row"), "row", "left_anti") if split else matrix.df
    counts = rest.groupBy(place.alias("s")).agg(F.count("*").alias("ones"))
    filled = spark.range(stretches).select(F.col("id").alias("s")).join(counts, "s", "left").select("s", F.coalesce("ones", F.lit(0)).alias("ones"), F.floor(F.col("s") * groups / F.lit(stretches)).alias("g"))
    filled = stored(filled, "stretches")
    per_group = filled.groupBy("g").agg(F.sum("ones").alias("ones"))
    earlier = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_group.select("g", F.coalesce(F.sum("ones").over(earlier(Window.orderBy("g"))), F.lit(0)).alias("offset"))  # at most 1024 rows
    total = filled.agg(F.greatest(F.sum("ones"), F.lit(1)).alias("total"))
    before = F.col("offset") + F.coalesce(F.sum("ones").over(earlier(Window.partitionBy("g").orderBy("s"))), F.lit(0))
    dealt = filled.join(F.broadcast(offsets), "g").join(F.broadcast(total)).select("s", F.least(F.floor(before * blocks / F.col("total")), F.lit(blocks - 1)).cast("int").alias("blk"))
    dealt = stored(dealt, "stretches")
    low = lambda c: F.ceil(c * F.lit(n) / F.lit(stretches)).cast("bigint")
    tiles = dealt.groupBy("blk").agg(low(F.min("s")).alias("row_lo"), F.least(low(F.max("s") + 1), F.lit(matrix.n_rows)).alias("row_hi"))
    side = F.broadcast(dealt) if stretches <= 1 << 20 else dealt
    cells = rest.withColumn("s", place).join(side, "s").drop("s")
    if split:
        wide = hubs.withColumn("parts", F.ceil(F.col("ones") / most))
        wide = stored(wide.withColumn("base", blocks + F.sum("parts").over(Window.orderBy("row")) - F.col("parts")), "hubs")
        own = matrix.df.join(F.broadcast(wide), "row").withColumn("blk", (F.col("base") + F.floor(F.col("col") * F.col("parts") / F.lit(max(1, matrix.n_cols)))).cast("int"))
        cells = cells.unionByName(own.select(*cells.columns))
        tiles = tiles.unionAll(wide.select(F.explode(F.sequence(F.col("base").cast("int"), (F.col("base") + F.col("parts") - 1).cast("int"))).alias("blk"), F.col("row").alias("row_lo"), (F.col("row") + 1).alias("row_hi")))
    return cells, stored(tiles, "layout"), split


def tile_of(table: pa.Table, lo: int, hi: int, valued: bool, opts: dict) -> tuple[Tile, np.ndarray]:
    """(tile, its columns) of the cells (row, col[, val]) of rows lo to hi."""
    rows, cols = (np.asarray(table.column(c).combine_chunks(), dtype=np.int64) if table.num_rows else np.zeros(0, np.int64) for c in ("row", "col"))
    order = np.lexsort((cols, rows))
    vals = np.asarray(table.column("val").combine_chunks())[order] if valued and table.num_rows else (np.zeros(0) if valued else None)
    rows, cols = rows[order], cols[order]
    del order
    rows -= lo
    own = np.unique(cols)
    return Tile(hi - lo, len(own), rows, np.searchsorted(own, cols), vals, opts), own


def _bounded(matrix: BoolMatrix, blocks: int, most: int) -> tuple[str, int]:
    """How to cut a matrix so that no tile holds far more than `most` ones: equal row ranges if they do, else balanced ones."""
    if matrix.nnz is not None and matrix.nnz <= most:
        return "rows", blocks
    ones = row_blocks(matrix, blocks)[0].groupBy("blk").agg(F.count("*").alias("ones")).agg(F.sum("ones"), F.max("ones")).first()
    return ("rows", blocks) if (ones[1] or 0) <= most else ("nnz", max(blocks, blocks_for(ones[0], most)))


def encode(matrix: BoolMatrix, fmt: str, blocks: int | None = None, by: str | None = None, **opts) -> CompressedMatrix:
    """One shuffle by row block; each block is encoded by one task. Encoding is deterministic, so retries agree.

    by='rows': exactly `blocks` equal row ranges, as in the experiments on blocks. by='nnz': ranges with about equal
    numbers of ones and no tile far above what the format takes (`most`), the default without `blocks`. With `blocks`
    alone, equal row ranges if none holds more than that, else as many balanced ones as it takes. Blocks without a one
    still get a tile, so that products cover all rows.
    """
    codec = FORMATS[fmt]
    if matrix.valued and not codec.valued:
        raise ValueError(f"{fmt} keeps Boolean matrices only")
    valued, n_rows = matrix.valued, matrix.n_rows
    most = min(TILE_ONES, codec.most)
    if by is None and blocks:
        by, blocks = _bounded(matrix, min(blocks, max(1, n_rows)), most)
    by = by or "nnz"
    blocks = min(blocks or blocks_for(matrix.df.count() if matrix.nnz is None else matrix.nnz, most), max(1, n_rows))
    cells, lows, segmented = (*row_blocks(matrix, blocks), False) if by == "rows" else balanced_blocks(matrix, blocks, *([most] if most < TILE_ONES else []))

    def pack(key: tuple, head: pa.Table, table: pa.Table) -> pa.Table:
        lo, hi = head.column("row_lo")[0].as_py(), head.column("row_hi")[0].as_py()
        tile, own = tile_of(table, lo, hi, valued, opts)
        parts, work = codec.encode(tile)
        row = {"blk": key[0].as_py(), "row_lo": lo, "row_hi": hi, "n_cols": len(own), "nnz": tile.nnz, "col_dict": pack_columns(own), "parts": list(parts.items()), "work": [(k, int(v)) for k, v in work.items()]}
        return pa.Table.from_pylist([row], TILE_ARROW)

    packed = lows.groupBy("blk").cogroup(cells.select("blk", "row", "col", *(["val"] if valued else [])).groupBy("blk")).applyInArrow(pack, TILE_SQL)
    return CompressedMatrix(packed, fmt, n_rows, matrix.n_cols, valued, opts, blocks, segmented, lows)


def decode(cm: CompressedMatrix) -> DataFrame:
    """(row, col[, val]): the cells again."""
    codec, valued = FORMATS[cm.fmt], cm.valued

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):  # one tile at a time: a batch may hold many
                t = batch.slice(i, 1).to_pylist()[0]
                own = columns_of(t["col_dict"])
                r, c, v = codec.decode(dict(t["parts"]), t["row_hi"] - t["row_lo"], t["n_cols"])
                out = [pa.array(r + t["row_lo"]), pa.array(own[c] if len(own) else c)]
                yield pa.RecordBatch.from_arrays(out + ([pa.array(np.ones(len(r)) if v is None else v)] if valued else []), names=["row", "col", *(["val"] if valued else [])])

    return cm.df.mapInArrow(run, "row bigint, col bigint" + (", val double" if valued else ""))


def write_matrix(cm: CompressedMatrix, path: str) -> None:
    """Tiles as Parquet, with the header repeated as one JSON column (it compresses to nothing)."""
    head = json.dumps({"fmt": cm.fmt, "n_rows": cm.n_rows, "n_cols": cm.n_cols, "valued": cm.valued, "opts": cm.opts, "blocks": cm.blocks, "segmented": cm.segmented})
    cm.df.withColumn("head", F.lit(head)).write.mode("overwrite").parquet(path)


def read_matrix(spark: SparkSession, path: str) -> CompressedMatrix:
    df = spark.read.parquet(path)
    head = json.loads(df.select("head").first()[0])
    return CompressedMatrix(df.drop("head"), **head)


def row_of(cm: CompressedMatrix, row: int) -> DataFrame:
    """(row, col) of one row: only its tile is opened, and in row-addressable formats only what the row needs."""
    codec = FORMATS[cm.fmt]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in batch.to_pylist():
                own, n = columns_of(t["col_dict"]), t["row_hi"] - t["row_lo"]
                if hasattr(codec, "row_of"):
                    cols = np.array(codec.row_of(dict(t["parts"]), n, row - t["row_lo"]), np.int64)
                else:
                    r, c, _ = codec.decode(dict(t["parts"]), n, t["n_cols"])
                    cols = c[r == row - t["row_lo"]]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cols), row), pa.int64()), pa.array(own[cols] if len(cols) else cols)], names=["row", "col"])

    return cm.df.where((F.col("row_lo") <= row) & (F.col("row_hi") > row)).mapInArrow(run, "row bigint, col bigint")


def submatrix(cm: CompressedMatrix, rows: tuple[int, int], cols: tuple[int, int]) -> DataFrame:
    """Cells in half-open row and column ranges; tiles outside the rows are pruned by their headers before decoding."""
    near = cm.held(cm.df.where((F.col("row_lo") < rows[1]) & (F.col("row_hi") > rows[0])))
    return decode(near).where((F.col("row") >= rows[0]) & (F.col("row") < rows[1]) & (F.col("col") >= cols[0]) & (F.col("col") < cols[1]))


def cells_lookup(cm: CompressedMatrix, wanted: DataFrame) -> DataFrame:
    """wanted (row, col) with `found`: whether the cell is one. Quadrant trees test from the root, others decode."""
    codec = FORMATS[cm.fmt]
    asked = cm.tiles_of(wanted, "row").select("blk", *wanted.columns)

    def run(tiles: pa.Table, asks: pa.Table) -> pa.Table:
        r, c = np.asarray(asks.column("row")), np.asarray(asks.column("col"))
        hit = np.zeros(len(r), bool)
        if tiles.num_rows and len(r):
            t = tiles.to_pylist()[0]
            own, parts = columns_of(t["col_dict"]), dict(t["parts"])
            at = np.searchsorted(own, c)
            known = np.append(own, -1)[np.minimum(at, len(own))] == c
            if hasattr(codec, "cell"):
                hit = np.array([bool(k) and codec.cell(parts, int(i), int(j)) for k, i, j in zip(known, r - t["row_lo"], at, strict=True)], bool)
            else:
                a, b, _ = codec.decode(parts, t["row_hi"] - t["row_lo"], t["n_cols"])
                hit = known & np.isin((r - t["row_lo"]) * max(1, len(own)) + at, a * max(1, len(own)) + b)
        return pa.table({"row": r, "col": c, "found": hit})

    told = cm.df.groupBy("blk").cogroup(asked.groupBy("blk")).applyInArrow(run, "row bigint, col bigint, found boolean")
    told = told.groupBy("row", "col").agg(F.bool_or("found").alias("found")) if cm.segmented else told
    outside = wanted.where((F.col("row") < 0) | (F.col("row") >= cm.n_rows)).select("row", "col", F.lit(False).alias("found"))
    return told.unionByName(outside)
