"""spark.read.format("boolmat").load(path): cells of a stored matrix, one partition per tile file.

Filters on `row` with a constant prune tiles by their headers, if spark.sql.python.filterPushdown.enabled is on.
Tiles are read with pyarrow, so `path` must be one that pyarrow can open on driver and executors.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from ..formats.base import columns_of
from ..formats.registry import FORMATS


class TileFile(InputPartition):
    def __init__(self, file: str, low: int, high: int):
        self.file, self.low, self.high = file, low, high


class TileReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.low, self.high = path.removeprefix("file:"), 0, 1 << 62

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if getattr(f, "attribute", None) == ("row",) and isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual)):
                if isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual)):
                    self.low = max(self.low, f.value + isinstance(f, GreaterThan))
                if isinstance(f, (EqualTo, LessThan, LessThanOrEqual)):
                    self.high = min(self.high, f.value + (not isinstance(f, LessThan)))
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        return [TileFile(f, self.low, self.high) for f in ds.dataset(self.path, format="parquet", exclude_invalid_files=True).files] or [TileFile("", 0, 0)]

    def read(self, part: TileFile) -> Iterator[pa.RecordBatch]:
        if not part.file:
            return
        near = (ds.field("row_lo") < part.high) & (ds.field("row_hi") > part.low)
        for t in ds.dataset(part.file).to_table(filter=near).to_pylist():
            own = columns_of(t["col_dict"])
            r, c, _ = FORMATS[json.loads(t["head"])["fmt"]].decode(dict(t["parts"]), t["row_hi"] - t["row_lo"], t["n_cols"])
            r, c = r + t["row_lo"], own[c] if len(own) else c
            keep = (r >= part.low) & (r < part.high)
            yield pa.RecordBatch.from_arrays([pa.array(r[keep]), pa.array(c[keep])], names=["row", "col"])


class MatrixSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "boolmat"

    def schema(self) -> str:
        return "row bigint, col bigint"

    def reader(self, schema) -> TileReader:
        return TileReader(self.options["path"])
