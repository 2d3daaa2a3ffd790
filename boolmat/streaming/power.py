"""Telemetry and edge deltas as streams."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import BoolMatrix, encode
from ..plans.spmv import spmv, spmv_edges
from ..sources.tables import shared_dir, stored


def stream_events(spark: SparkSession, path: str) -> DataFrame:
    """The events table as a file stream; its zoneless timestamps become instants, as watermarks need."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    source = spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder)
    return source.withColumn("ts", F.col("ts").cast("timestamp"))


def run_available(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what there is and gives its result as a table in the shared folder.

    Append and update streams go to Parquet files; a complete one keeps its last batch.
    """
    spark, base = df.sparkSession, f"{shared_dir(df.sparkSession)}/boolmat-stream-{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", base + "/state").trigger(availableNow=True)
    if mode == "complete":
        query = writer.foreachBatch(lambda batch, i: batch.write.mode("overwrite").parquet(base + "/out")).start()
    else:
        query = writer.format("parquet").option("path", base + "/out").start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(base + "/out")


def stream_power(events: DataFrame, kind: str, size: str = "1 day", slide: str | None = None, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Sums and counts per window: kind 'tumbling', 'sliding' (with slide) or 'session' (per user, with gap)."""
    timed = events.withWatermark("ts", delay)
    if kind == "session":
        groups = timed.groupBy("user_id", F.session_window("ts", gap).alias("w"))
        return groups.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total")
    w = F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
    return timed.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "n", "total")


def stream_dedup(events: DataFrame, key: str = "event_id", delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def stream_enrich(events: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return events.join(static, on)


def stream_pair(starts: DataFrame, stops: DataFrame, key: str, within: str = "1 hour") -> DataFrame:
    """Start and stop events of a key that lie within an interval; both sides bound their state by watermarks."""
    a = starts.withWatermark("ts", within).select(F.col(key).alias("k"), F.col("ts").alias("start_ts"))
    b = stops.withWatermark("ts", within).select(F.col(key).alias("k2"), F.col("ts").alias("stop_ts"))
    return a.join(b, F.expr(f"k = k2 AND stop_ts >= start_ts AND stop_ts < start_ts + INTERVAL {within}")).drop("k2")


def stream_energy(events: DataFrame, volts: float) -> DataFrame:
    """(device, joules) so far, an update stream. One record of state per device: last time, last current, energy. Events
    of a batch are taken in time order; one older than the state is left out."""
    def fold(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        t, i, joules = state.get if state.exists else (None, None, 0.0)
        for x in pd.concat(parts).sort_values(["t", "i"]).itertuples():
            if t is not None and x.t < t:
                continue
            if t is not None:
                joules += (x.t - t) / 1e6 * (x.i + i) / 2 * volts
            t, i = x.t, x.i
        state.update((int(t), float(i), float(joules)))
        yield pd.DataFrame({"device": [key[0]], "joules": [joules]})

    rows = events.select(F.col("user_id").alias("device"), F.unix_micros("ts").alias("t"), F.col("value").alias("i"))
    return rows.groupBy("device").applyInPandasWithState(fold, "device bigint, joules double", "t bigint, i double, joules double", "update", "NoTimeout")


def run_updates(df: DataFrame, key: str) -> DataFrame:
    """Runs an update stream over what there is; the last row of each key."""
    base = f"{shared_dir(df.sparkSession)}/boolmat-stream-{uuid.uuid4().hex}"
    keep = lambda batch, i: batch.withColumn("batch", F.lit(i)).write.mode("append").parquet(base + "/out")
    df.writeStream.outputMode("update").option("checkpointLocation", base + "/state").trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    told = df.sparkSession.read.parquet(base + "/out")
    return told.groupBy(key).agg(F.max_by(F.struct(*[c for c in df.columns if c != key]), "batch").alias("last")).select(key, "last.*")


def late_report(query) -> list[dict]:
    """Rows dropped behind the watermark, per progress report of a stateful query."""
    return [{"batch": p["batchId"], "late": sum(o.get("numRowsDroppedByWatermark", 0) for o in p.get("stateOperators", []))} for p in query.recentProgress]


class DeltaMatrix:
    """A stored matrix with edge deltas beside it: y = base x + added x - removed x, until compaction.

    Adding an edge that is there, or removing one that is not, changes nothing.
    """

    def __init__(self, base: BoolMatrix, fmt: str = "pg_w32", blocks: int = 4, **opts):
        self.base, self.fmt, self.blocks, self.opts = base, fmt, blocks, opts
        cm = encode(base, fmt, blocks, **opts)
        self.cm = cm.held(stored(cm.df, "tiles"))
        self.added = base.df.limit(0)
        self.removed = base.df.limit(0)

    def apply(self, added: DataFrame | None = None, removed: DataFrame | None = None) -> None:
        """Takes (row, col) batches, e.g. from foreachBatch."""
        if added is not None:
            fresh = added.select("row", "col").distinct()
            self.removed = stored(self.removed.join(fresh, ["row", "col"], "left_anti"), "delta")
            self.added = stored(self.added.unionAll(fresh.join(self.base.df, ["row", "col"], "left_anti")).distinct(), "delta")
        if removed is not None:
            gone = removed.select("row", "col").distinct()
            self.added = stored(self.added.join(gone, ["row", "col"], "left_anti"), "delta")
            self.removed = stored(self.removed.unionAll(gone.join(self.base.df, ["row", "col"], "left_semi")).distinct(), "delta")

    def product(self, x: DataFrame) -> DataFrame:
        part = lambda df, sign: spmv_edges(BoolMatrix(df, self.base.n_rows, self.base.n_cols), x).select("id", (sign * F.col("value")).alias("value"))
        return spmv(self.cm, x).unionAll(part(self.added, 1.0)).unionAll(part(self.removed, -1.0)).groupBy("id").agg(F.sum("value").alias("value"))

    def compact(self) -> DeltaMatrix:
        """A new base with the deltas in it."""
        df = self.base.df.join(self.removed, ["row", "col"], "left_anti").unionAll(self.added)
        return DeltaMatrix(BoolMatrix(stored(df, "base"), self.base.n_rows, self.base.n_cols), self.fmt, self.blocks, **self.opts)
