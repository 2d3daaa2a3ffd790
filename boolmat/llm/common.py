"""Shared helpers: the cluster's shared folder, written intermediate tables, Arrow text buffers, hashing in NumPy."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space that separates words (space, tab to carriage return).
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"
BLANKS = " \t\n\x0b\x0c\r"
#: Rows and list items that a file of an intermediate table holds before another one is begun.
ROWS_A_FILE, ITEMS_A_FILE = 5_000, 2_000_000


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Unset, a local session gets one of our own; a cluster has to name it."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[[^,]*\])?$", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = tempfile.gettempdir() + "/checkpoints"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def files_for(spark: SparkSession, rows: int, items: int = 0) -> int:
    """How many files a table of so many rows, or of so many list items in them, is worth; one per core at least."""
    return max(spark.sparkContext.defaultParallelism, -(-rows // ROWS_A_FILE), -(-items // ITEMS_A_FILE))


def written(df: DataFrame, tag: str, files: int = 0) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage and survives lost executors.

    files: the most files it is written as, where the shuffles before it have more partitions than the rows are worth.
    Hadoop's local file system starts a process of the JVM for each file that it creates.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/boolmat-{tag}-{uuid.uuid4().hex}"
    (df.coalesce(files) if files else df).write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove_table(df: DataFrame) -> None:
    """Deletes a table of written() that nothing reads any more."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/boolmat-" in path:
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def keyed_join(rows: DataFrame, side: DataFrame, keys: list[str], count: str, how: str = "inner", share: int = 1_000) -> DataFrame:
    """Inner or left join of rows with side, which has one row per key; its column `count` says how many rows have the key.

    Keys that hold at least one of `share` parts of all counted rows are at most `share` many, whatever the data: they are
    broadcast, so no task meets all rows of one key. The other keys meet by a shuffle.
    """
    total = side.agg(F.sum(count)).first()[0] or 0
    heavy = F.col(count) * share >= total
    often = F.broadcast(side.where(heavy).select(*keys, F.lit(True).alias("__often")))
    marked = rows.join(often, keys, "left")
    few = marked.where("__often IS NULL").drop("__often").join(side.where(~heavy), keys, how)
    return few.unionByName(marked.where("__often IS NOT NULL").drop("__often").join(F.broadcast(side.where(heavy)), keys))


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def uniform(*parts: Column) -> Column:
    """A number in [0, 1) that depends on the parts only."""
    return F.shiftrightunsigned(F.xxhash64(*parts), 11) * F.lit(2.0**-53)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column without a copy; null texts get length 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    n = len(column)
    _, where, data = column.buffers()
    if n == 0 or where is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offsets = np.frombuffer(where, kind, n + 1 + column.offset)[column.offset :].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw, offsets


def slices(offsets: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts hold about `most` bytes (one row at least), so that kernels need bounded memory."""
    n, at = len(offsets) - 1, 0
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1
        to = min(n, max(to, at + 1))
        yield at, to
        at = to


_MIX1, _MIX2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor shifts and odd multiplications), a bijection."""
    x = x ^ (x >> np.uint64(33))
    x = x * _MIX1
    x ^= x >> np.uint64(33)
    x *= _MIX2
    x ^= x >> np.uint64(33)
    return x


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown on demand; for prefix sums of polynomial hashes."""

    def __init__(self, base: int):
        self.base, self.inverse, self.up, self.down = base, pow(base, -1, 1 << 64), np.ones(1, np.uint64), np.ones(1, np.uint64)

    def grow(self, n: int) -> None:
        if len(self.up) < n:
            for name, b in (("up", self.base), ("down", self.inverse)):
                factors = np.full(max(n, 2 * len(self.up)), b, np.uint64)
                factors[0] = 1
                setattr(self, name, np.multiply.accumulate(factors))

    def prefix(self, data: np.ndarray) -> np.ndarray:
        """p with p[i] = sum of (data[j] + 1) * base**j over j < i."""
        self.grow(len(data) + 1)
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * self.up[: len(data)], out=out[1:])
        return out

    def span(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of each piece [start, end), equal for equal bytes wherever they stand."""
        return mixed((prefix[end] - prefix[start]) * self.down[start])


POWERS = Powers(0x9E3779B97F4A7C15)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def word_spans(data: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, text number) of every word in data, texts being data[cuts[i]:cuts[i + 1]]."""
    ink = ~_BLANK[data]
    begins, ends = ink.copy(), ink.copy()
    begins[1:] &= ~ink[:-1]
    ends[:-1] &= ~ink[1:]
    inner = cuts[1:-1]
    inner = inner[(inner > 0) & (inner < len(data))]
    begins[inner] = ink[inner]
    ends[inner - 1] = ink[inner - 1]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return start, end, np.searchsorted(cuts, start, side="right") - 1


def shingle_hashes(data: np.ndarray, cuts: np.ndarray, size: int, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(shingle hash, text number, words per text): all runs of `size` words; a shorter text with words gives one run of all."""
    if lower:
        data = _LOWER[data]
    start, end, owner = word_spans(data, cuts)
    words = POWERS.span(POWERS.prefix(data), start, end)
    n_texts = len(cuts) - 1
    per_text = np.bincount(owner, minlength=n_texts)
    first = np.concatenate([[0], np.cumsum(per_text)])
    acc = words.copy()
    for k in range(1, min(size, len(words))):  # acc[i] covers the words i .. i + k
        acc[: len(words) - k] = mixed(acc[: len(words) - k]) * np.uint64(0x2545F4914F6CDD1D) + words[k:]
    keep = np.arange(len(words)) + size <= first[owner + 1] if len(words) else np.zeros(0, bool)
    hashes, owners = mixed(acc[keep]), owner[keep]
    short = np.flatnonzero((per_text > 0) & (per_text < size))
    if len(short):
        extra = []
        for t in short:
            h = np.uint64(0x51ED270B)
            with np.errstate(over="ignore"):
                for w in words[first[t] : first[t + 1]]:
                    h = mixed(np.array([h], np.uint64))[0] * np.uint64(0x2545F4914F6CDD1D) + w + np.uint64(per_text[t])
            extra.append(mixed(np.array([h ^ np.uint64(0xABCDEF)], np.uint64))[0])
        hashes, owners = np.concatenate([hashes, np.array(extra, np.uint64)]), np.concatenate([owners, short])
        order = np.argsort(owners, kind="stable")
        hashes, owners = hashes[order], owners[order]
    return hashes, owners, per_text
