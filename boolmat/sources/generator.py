"""Synthetic graphs of any size, made by the executors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def copy_model_graph(spark: SparkSession, n: int, degree: int = 20, p_copy: float = 0.97, spread: float = 30.0, blocks: int = 8, seed: int = 10, window: int = 7, fresh: float = 0.05, vertices: DataFrame | None = None) -> DataFrame:
    """edges(u, v) like a web crawl: most rows keep each target of one of the `window` rows before with probability
    p_copy and draw the rest near the diagonal, a tenth of them anywhere. Blocks are independent; seeds are block ids.

    vertices: (id, seed) of a table below n: only these have rows, and each draws by its own seed.
    """
    def links(rng: np.random.Generator, i: int, rows: list[np.ndarray]) -> np.ndarray:
        kept = np.zeros(0, np.int64)
        if rows and rng.random() > fresh:
            base = rows[-int(rng.integers(1, min(window, len(rows)) + 1))]
            kept = base[rng.random(len(base)) < p_copy]
        need = max(0, degree - len(kept))
        near = np.rint(rng.normal(i, spread, need)).astype(np.int64) % n
        far = rng.integers(0, n, need)
        return np.unique(np.concatenate([kept, np.where(rng.random(need) < 0.1, far, near)]))

    def edges(ids: np.ndarray, rows: list[np.ndarray]) -> list[np.ndarray]:
        return [np.repeat(ids, [len(r) for r in rows]).astype(np.int64), np.concatenate(rows) if rows else np.zeros(0, np.int64)]

    def of_table(table: pa.Table) -> pa.Table:
        ids, seeds = (np.asarray(table.column(c).combine_chunks()) for c in ("id", "seed"))
        order, rows = np.lexsort((seeds, ids)), []
        for i, own in zip(ids[order].tolist(), seeds[order].tolist(), strict=True):
            rows.append(links(np.random.default_rng([seed, own & (1 << 63) - 1]), i, rows))
        return pa.table(edges(ids[order], rows), names=["u", "v"])

    if vertices is not None:
        place = F.floor(F.col("id") * blocks / F.lit(max(1, n))).alias("b")
        return vertices.select("id", "seed", place).groupBy("b").applyInArrow(of_table, "u bigint, v bigint").distinct()

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in batch.column(0).to_pylist():
                rng = np.random.default_rng([seed, b])
                lo, hi = b * n // blocks, (b + 1) * n // blocks
                rows: list[np.ndarray] = []
                for i in range(lo, hi):
                    rows.append(links(rng, i, rows))
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in edges(np.arange(lo, hi), rows)], names=["u", "v"])

    return spark.range(0, blocks, 1, blocks).mapInArrow(make, "u bigint, v bigint")


def uniform_graph(spark: SparkSession, n: int, m: int, seed: int = 3) -> DataFrame:
    h = lambda k: F.pmod(F.xxhash64("id", F.lit(seed + k)), F.lit(n))
    return spark.range(m).select(h(0).alias("u"), h(1).alias("v")).where("u <> v").distinct()


def power_law_graph(spark: SparkSession, n: int, m: int, exponent: float = 2.0, seed: int = 4) -> DataFrame:
    """Targets drawn with a power-law in-degree: hubs among the small numbers."""
    unit = F.shiftrightunsigned(F.xxhash64("id", F.lit(seed)), 11) * F.lit(2.0**-53)
    v = F.least(F.floor(F.pow(1 - unit, F.lit(-1.0 / (exponent - 1)))) - 1, F.lit(n - 1)).cast("bigint")
    return spark.range(m).select(F.pmod(F.xxhash64("id", F.lit(seed + 1)), F.lit(n)).alias("u"), v.alias("v")).where("u <> v").distinct()
