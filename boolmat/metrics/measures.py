"""Space, work, time, memory, energy and accuracy of stored matrices and of runs.

Where the host has no meter or counter the value is None with a reason; nothing is estimated in its place.
"""

from __future__ import annotations

import os
import resource
import shutil
import signal
import subprocess
import time
from collections.abc import Callable
from functools import reduce
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..formats.base import Tile, pack_columns
from ..formats.registry import COMPARED, FORMATS
from ..model import TILE_ONES, BoolMatrix, CompressedMatrix, tile_of
from ..operators.algebra import depth_of
from ..sources.tables import stored


#: Numbers of a tile's header: block, first and last row, columns, ones.
HEADER_BYTES = 40


def graph_profile(matrix: BoolMatrix) -> DataFrame:
    """(n, m, mean_degree, dangling): Vertices of a square reading, ones, ones per row, rows without ones."""
    counts = matrix.df.agg(F.count("*").alias("m"), F.count_distinct("row").alias("full"))
    n = matrix.n_rows
    return counts.select(F.lit(n).cast("bigint").alias("n"), "m", (F.col("m") / F.lit(max(n, 1))).alias("mean_degree"), (F.lit(n) - F.col("full")).cast("bigint").alias("dangling"))


def space_report(cm: CompressedMatrix) -> DataFrame:
    """(part, bits): payload by part, dictionary and header; and bits per edge with and without the dictionary."""
    parts = cm.df.select(F.explode("parts").alias("part", "data"), "nnz").groupBy("part").agg((8 * F.sum(F.octet_length("data"))).alias("bits"))
    extra = cm.df.agg((8 * F.sum(F.octet_length("col_dict"))).alias("col_dict"), (F.count("*") * 8 * HEADER_BYTES).alias("header")).unpivot([], ["col_dict", "header"], "part", "bits")
    return parts.unionAll(extra)


def bits_per_edge(cm: CompressedMatrix) -> DataFrame:
    """(nnz, bits, total_bits, bits_per_edge, total_per_edge): payload, and payload with column dictionaries and headers.

    The payload is the measure of a single block whose columns are all in use; what blocks add stands in the total.
    """
    payload = F.expr("aggregate(map_values(parts), 0L, (a, x) -> a + octet_length(x))")
    out = cm.df.agg(F.sum("nnz").alias("nnz"), (8 * F.sum(payload)).alias("bits"), (8 * F.sum(payload + F.octet_length("col_dict") + HEADER_BYTES)).alias("total_bits"))
    return out.withColumns({"bits_per_edge": F.try_divide("bits", "nnz"), "total_per_edge": F.try_divide("total_bits", "nnz")})


def work_report(cm: CompressedMatrix) -> DataFrame:
    """(counter, n): what the encoders counted, and `touched`, the entries that one product reads."""
    return cm.df.select(F.explode("work").alias("counter", "n")).groupBy("counter").agg(F.sum("n").alias("n"))


def measured_space(matrices: dict[str, BoolMatrix], formats: tuple[str, ...], counts: tuple[int, ...], **opts) -> DataFrame:
    """(dataset, format, blocks, bits_per_edge, total_per_edge) of all matrices, formats and numbers of equal row ranges.

    One shuffle for all: a tile meets all formats in one task, and the pair grammars share its rules.
    """
    spark = next(iter(matrices.values())).df.sparkSession
    names, cells, tiles = list(matrices), [], []
    for i, m in enumerate(matrices.values()):
        n = max(1, m.n_rows)
        cut = F.explode(F.array(*[F.struct(F.lit(b).alias("blocks"), F.floor(F.col("row") * min(b, n) / F.lit(n)).cast("int").alias("blk")) for b in counts]))
        cells.append(m.df.select(F.lit(i).alias("i"), cut.alias("c"), "row", "col", (F.col("val") if m.valued else F.lit(None)).cast("double").alias("val")).select("i", "c.blocks", "c.blk", "row", "col", "val"))
        tiles += [(i, b, k, -(-k * m.n_rows // min(b, n)), -(-(k + 1) * m.n_rows // min(b, n))) for b in counts for k in range(min(b, n))]
    valued = [m.valued for m in matrices.values()]
    spread = max(64, min(len(tiles), 1024))  # a number of its own, as tasks are few rows and much work
    key = ["i", "blocks", "blk"]
    heads = spark.createDataFrame(tiles, "i int, blocks int, blk int, row_lo bigint, row_hi bigint").repartition(spread, *key)
    both = reduce(DataFrame.unionAll, cells).repartition(spread, *key)

    def measure(key: tuple, head: pa.Table, table: pa.Table) -> pa.Table:
        i, blocks, _ = (k.as_py() for k in key)
        tile, own = tile_of(table, head.column("row_lo")[0].as_py(), head.column("row_hi")[0].as_py(), valued[i], opts)
        extra, out = len(pack_columns(own)) + HEADER_BYTES, []
        for fmt in formats:
            if not valued[i] or FORMATS[fmt].valued:
                payload = sum(map(len, FORMATS[fmt].encode(tile)[0].values()))
                out.append({"dataset": names[i], "format": fmt, "blocks": blocks, "nnz": tile.nnz, "payload": payload, "total": payload + extra})
        return pa.Table.from_pylist(out, pa.schema([("dataset", pa.string()), ("format", pa.string()), ("blocks", pa.int32()), ("nnz", pa.int64()), ("payload", pa.int64()), ("total", pa.int64())]))

    found = heads.groupBy(*key).cogroup(both.groupBy(*key)).applyInArrow(measure, "dataset string, format string, blocks int, nnz bigint, payload bigint, total bigint")
    sums = found.groupBy("dataset", "format", "blocks").agg(F.sum("nnz").alias("nnz"), (8 * F.sum("payload")).alias("bits"), (8 * F.sum("total")).alias("total_bits"))
    return sums.select("dataset", "format", "blocks", F.try_divide("bits", "nnz").alias("bits_per_edge"), F.try_divide("total_bits", "nnz").alias("total_per_edge"))


def tree_space(matrix: BoolMatrix, most: int = TILE_ONES) -> DataFrame:
    """(nnz, tree_bits, bits, bits_per_edge) of one quadrant tree (k = 2) over all rows and columns, none renumbered.

    The tree is encoded quadrant by quadrant, in the largest quadrants that hold at most `most` ones, and above them as
    a tree over quadrants: together these are the bits of the whole, whatever its size.
    """
    height = depth_of(max(matrix.n_rows, matrix.n_cols))
    low = min(height, max(1, (most.bit_length() - 1) // 2))  # a quadrant of this height cannot hold more
    counts = stored(matrix.df.groupBy(F.shiftright("row", low).alias("r"), F.shiftright("col", low).alias("c")).agg(F.count("*").alias("ones")), "quadrants")
    lifted = counts.select("ones", "r", "c", F.explode(F.sequence(F.lit(0), F.lit(height - low))).alias("up")).groupBy("up", F.expr("shiftright(r, up)").alias("r"), F.expr("shiftright(c, up)").alias("c")).agg(F.sum("ones").alias("ones"))
    up = lifted.groupBy("up").agg(F.max("ones").alias("ones")).where(F.col("ones") <= most).agg(F.max("up")).first()[0] or 0
    cut = low + up
    codec, side = FORMATS["quadbits"], 1 << cut

    def encoded(rows: np.ndarray, cols: np.ndarray, side: int) -> pa.Table:
        _, work = codec.encode(Tile(side, side, rows, cols))
        return pa.table({"ones": pa.array([len(rows)], pa.int64()), "bits": pa.array([work["bits"]], pa.int64())})

    def below(table: pa.Table) -> pa.Table:
        return encoded(np.asarray(table.column("row")) % side, np.asarray(table.column("col")) % side, side)

    def above(table: pa.Table) -> pa.Table:
        return encoded(np.asarray(table.column("r")), np.asarray(table.column("c")), 1 << (height - cut))

    quadrants = matrix.df.select("row", "col", F.shiftright("row", cut).alias("r"), F.shiftright("col", cut).alias("c"))
    found = quadrants.groupBy("r", "c").applyInArrow(below, "ones bigint, bits bigint")
    if cut < height:
        tops = counts.select(F.shiftright("r", up).alias("r"), F.shiftright("c", up).alias("c")).distinct()
        found = found.unionAll(tops.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(above, "ones bigint, bits bigint").select(F.lit(0).cast("bigint").alias("ones"), "bits"))
    # the parts of a tile: an eight-byte number per level and one for the length, and the bits in whole bytes
    out = found.agg(F.sum("ones").alias("nnz"), F.sum("bits").alias("tree_bits")).withColumn("bits", (8 * F.ceil(F.col("tree_bits") / 8) + 64 * (height + 1)).cast("bigint"))
    return out.withColumn("bits_per_edge", F.try_divide("bits", "nnz"))


def space_table(matrices: dict[str, BoolMatrix], formats: tuple[str, ...] = (*COMPARED, "deflate", "lzma"), blocks: int = 1, **opts) -> DataFrame:
    """(dataset, per format payload bits per edge as <format> and all bits per edge as <format>_total)."""
    long = measured_space(matrices, formats, (blocks,), **opts)
    wide = long.groupBy("dataset").pivot("format", list(formats)).agg(F.first("bits_per_edge").alias("payload"), F.first("total_per_edge").alias("total"))
    return wide.select("dataset", *[F.col(f"{f}_payload").alias(f) for f in formats], *[f"{f}_total" for f in formats])


def web_vs_social(web: dict[str, BoolMatrix], social: dict[str, BoolMatrix], formats: tuple[str, ...] = (*COMPARED, "deflate"), mode: str = "batched") -> DataFrame:
    """(format, web, social, gain): mean payload bits per edge of two families, and how many times smaller the first is."""
    both = space_table(web | social, formats, mode=mode).withColumn("family", F.when(F.col("dataset").isin(*web), "web").otherwise("social"))
    long = both.unpivot(["family"], list(formats), "format", "bits").groupBy("format").pivot("family", ["web", "social"]).agg(F.avg("bits"))
    return long.withColumn("gain", F.col("social") / F.col("web"))


def space_vs_blocks(matrices: dict[str, BoolMatrix], formats: tuple[str, ...], counts: tuple[int, ...] = (1, 2, 4, 8, 16, 24, 32, 40, 48), **opts) -> DataFrame:
    """(format, blocks, bits_per_edge, total_per_edge, the inflation of each against one block, dataset)."""
    base = lambda c: F.first_value(c).over(Window.partitionBy("dataset", "format").orderBy("blocks"))
    inflated = {"inflation": F.col("bits_per_edge") / base("bits_per_edge"), "total_inflation": F.col("total_per_edge") / base("total_per_edge")}
    return measured_space(matrices, formats, counts, **opts).withColumns(inflated).select("format", "blocks", "bits_per_edge", "total_per_edge", *inflated, "dataset")


def product_error(y: DataFrame, ref: DataFrame) -> DataFrame:
    """(max_abs, max_rel, only_one): two vectors compared over all ids; a missing id is 0."""
    both = y.select("id", F.col("value").alias("a")).join(ref.select("id", F.col("value").alias("b")), "id", "full")
    a, b = F.coalesce("a", F.lit(0.0)), F.coalesce("b", F.lit(0.0))
    return both.agg(F.max(F.abs(a - b)).alias("max_abs"), F.max(F.abs(a - b) / F.greatest(F.abs(b), F.lit(1e-300))).alias("max_rel"), F.sum((F.col("a").isNull() | F.col("b").isNull()).cast("bigint")).alias("only_one"))


def rank_agreement(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """(shared): how many of the k largest entries two vectors share."""
    best = lambda v: v.orderBy(F.desc("value"), "id").limit(k).select("id")
    return best(a).join(best(b), "id").agg(F.count("*").alias("shared"))


def timed(action: Callable[[], DataFrame]) -> float:
    """Seconds until all rows of the plan are made and thrown away."""
    start = time.perf_counter()
    action().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


class PackageEnergyMeter:
    """Joules from the operating system's power-capping counters; wraps are added. None with a reason without them."""

    def __init__(self, root: str = "/sys/class/powercap"):
        self.zones = [p for p in sorted(Path(root).glob("*:*")) if (p / "energy_uj").exists() and ":" not in p.name.partition(":")[2]] if Path(root).is_dir() else []
        self.before: dict[Path, int] = {}

    def start(self) -> None:
        self.before = {z: int((z / "energy_uj").read_text()) for z in self.zones}

    def stop(self) -> dict:
        if not self.zones:
            return {"joules": None, "domain": None, "method": "package counters", "reason": "no power-capping files"}
        total = 0
        for z, b in self.before.items():
            now = int((z / "energy_uj").read_text())
            total += now - b if now >= b else now - b + int((z / "max_energy_range_uj").read_text())
        return {"joules": total / 1e6, "domain": "package", "method": "package counters", "reason": None}


def integrate_power(samples: DataFrame, volts: float, device: str = "device", ts: str = "ts", amps: str = "amps") -> DataFrame:
    """(device, joules): trapezoids between neighbouring samples of a current trace at a stated voltage."""
    w = Window.partitionBy(device).orderBy(ts, amps)
    t = F.unix_micros(F.col(ts).cast("timestamp"))
    rows = samples.select(device, t.alias("t"), F.col(amps).alias("i"), F.lead(t).over(w).alias("t2"), F.lead(amps).over(w).alias("i2"))
    return rows.where("t2 IS NOT NULL").groupBy(device).agg(F.sum((F.col("t2") - F.col("t")) / 1e6 * (F.col("i") + F.col("i2")) / 2 * volts).alias("joules"))


def peak_memory(spark: SparkSession) -> dict:
    """Peak MB of the driver's heap, of this Python process and its Python workers, and of every executor that reports."""
    pools = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    heap = sum(p.getPeakUsage().getUsed() for p in pools if str(p.getType()) == "Heap memory")
    told = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    executors = {}
    for i in range(told.size()):
        e = told.apply(i)
        if e.peakMemoryMetrics().isDefined():
            m = e.peakMemoryMetrics().get()
            executors[e.id()] = {"heap_mb": m.getMetricValue("JVMHeapMemory") / 2**20, "python_mb": m.getMetricValue("ProcessTreePythonRSSMemory") / 2**20}
    return {"driver_jvm_mb": heap / 2**20, "driver_python_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024, "worker_python_mb": worker_peak_mb(), "executors": executors}


def worker_peak_mb() -> float:
    """Sum of the peak resident sizes of this host's living Python workers; 0 where the system does not tell."""
    total = 0
    for p in Path("/proc").glob("[0-9]*"):
        try:
            if b"pyspark" in (p / "cmdline").read_bytes() and b"daemon" in (p / "cmdline").read_bytes():
                total += next((int(x.split()[1]) for x in (p / "status").read_text().splitlines() if x.startswith("VmHWM")), 0)
        except OSError:
            continue
    return total / 1024


# The counters by the names that perf gives them.
PERF_EVENTS = {"cycles": "cycles", "instructions": "instructions", "L1-dcache-loads": "l1d_loads", "L1-dcache-load-misses": "l1d_load_misses", "L1-dcache-stores": "l1d_stores", "LLC-loads": "l3_accesses"}


class HardwareCounters:
    """Cycles, instructions and cache counters of a process (this one's JVM by default) between start() and stop().

    They come from `perf stat` attached to the process; None with a reason where perf is missing or refuses.
    """

    def __init__(self, pid: int | None = None):
        self.pid, self.tool, self.run = pid or os.getpid(), shutil.which("perf"), None

    def start(self) -> None:
        if self.tool:
            self.run = subprocess.Popen([self.tool, "stat", "-x", ",", "-e", ",".join(PERF_EVENTS), "-p", str(self.pid)], stdout=subprocess.DEVNULL, stderr=subprocess.PIPE, text=True)

    def stop(self) -> dict:
        none = dict.fromkeys(PERF_EVENTS.values())
        if not self.run:
            return none | {"reason": "no perf on this host"}
        self.run.send_signal(signal.SIGINT)
        told = self.run.communicate()[1]
        found = {}
        for line in told.splitlines():
            part = line.split(",")
            if len(part) > 2 and part[2].split(":")[0] in PERF_EVENTS and part[0].isdigit():
                found[PERF_EVENTS[part[2].split(":")[0]]] = int(part[0])
        out = none | found
        if out["cycles"] and out["instructions"]:
            out["cpi"] = out["cycles"] / out["instructions"]
        return out | {"reason": None if found else told.strip()[-200:] or "perf counted nothing"}


def hardware_counters() -> dict:
    """The counters' names without values, and why: for records made without a meter."""
    return dict.fromkeys(PERF_EVENTS.values()) | {"reason": "no meter was started" if shutil.which("perf") else "no perf on this host"}
