"""Tables of a directory, edge files, written intermediate tables."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None, predicate: Column | None = None) -> DataFrame:
    """A table; the scan reads only `columns` and gets `predicate` pushed down."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if predicate is not None:
        df = df.where(predicate)
    return df.select(*columns) if columns else df


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Unset, a local session gets one of our own; a cluster has to name it."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[[^,]*\])?$", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = tempfile.gettempdir() + "/checkpoints"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def stored(df: DataFrame, tag: str = "table") -> DataFrame:
    """df written as Parquet to the shared folder and read back: cuts the lineage, outlives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/boolmat-{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove_table(df: DataFrame) -> None:
    """Deletes the tables of stored() that df reads, once nothing else reads them."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/boolmat-" in path:
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t") -> DataFrame:
    """edges(u, v), distinct, from delimited text or from little-endian pairs of 32-bit numbers."""
    if fmt == "csv":
        return spark.read.csv(path, sep=sep, schema="u bigint, v bigint", comment="#").distinct()

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                e = np.frombuffer(content.as_buffer(), "<u4").reshape(-1, 2).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(e[:, 0]), pa.array(e[:, 1])], names=["u", "v"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(pairs, "u bigint, v bigint").distinct()


def assign_ids(df: DataFrame, key: str, order: str = "natural", seed: int = 1) -> DataFrame:
    """(id, key) for the distinct values of `key`, numbered from 0 in an order.

    order: 'natural' (the values' own), 'revurl' (reversed host labels, then path), 'hash' (shuffled), 'degree' (most
    frequent first). A range sort and per-partition offsets; no window over the whole table. The sorted table is stored
    first, because range bounds are sampled anew each time a plan runs.
    """
    keys = df.groupBy(F.col(key).alias("key")).agg(F.count("*").alias("n"))
    rank = {"natural": F.col("key"), "revurl": F.struct(reverse_host(F.col("key")).alias("h"), F.col("key").alias("p")), "hash": F.struct(F.xxhash64("key", F.lit(seed)).alias("h"), F.col("key").alias("p")), "degree": F.struct((-F.col("n")).alias("h"), F.col("key").alias("p"))}[order]
    ranged = stored(keys.select("key", rank.alias("rank")).repartitionByRange("rank").withColumn("pid", F.spark_partition_id()), "ids")
    from pyspark.sql import Window

    counts = ranged.groupBy("pid").count()
    offsets = counts.withColumn("offset", F.sum("count").over(Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)))  # one row per partition
    within = F.row_number().over(Window.partitionBy("pid").orderBy("rank")) - 1
    return ranged.withColumn("within", within).join(F.broadcast(offsets.select("pid", F.coalesce("offset", F.lit(0)).alias("offset"))), "pid").select((F.col("within") + F.col("offset")).cast("bigint").alias("id"), "key")


def reverse_host(url: Column) -> Column:
    """example.com of http://m.example.com/x becomes com.example.m: neighbours in this order look alike."""
    host = F.regexp_extract(url, "^(?:[a-z]+://)?([^/?#]*)", 1)
    return F.concat_ws(".", F.reverse(F.split(host, r"\.")))


def url_path(url: Column) -> Column:
    return F.regexp_extract(url, "^(?:[a-z]+://)?[^/?#]*([^?#]*)", 1)
