"""Experiments: iterations of formats over degrees of parallelism, one fresh session per degree, in subprocesses."""

from __future__ import annotations

import json
import subprocess
import sys
from pathlib import Path

#: Degrees of parallelism of the two hosts.
SERVER_DEGREES = (1, 2, 4, 8, 16, 24, 32, 40, 48)
BOARD_DEGREES = (1, 2, 4, 8)

_RUN = """
import json, sys, time
sys.path.insert(0, sys.argv[1])
a = json.loads(sys.argv[2])
from pyspark.sql import SparkSession
spark = SparkSession.builder.master(f"local[{a['degree']}]").config("spark.driver.memory", a["heap"]).config("spark.sql.shuffle.partitions", str(max(2, a["degree"]))).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
from boolmat.sweep import run_one
for dataset, fmt in a["pairs"]:
    print("RUN " + json.dumps(run_one(spark, a["sf"], dataset, fmt, a["degree"], a["iterations"], a["opts"].get(fmt, {}))), flush=True)
"""


def run_one(spark, sf_dir: str, dataset: str, fmt: str, degree: int, iterations: int, opts: dict) -> dict:
    """One record. encode_seconds: transposing, encoding and storing; seconds, joules and counters: the iterations alone."""
    import time

    from .metrics.measures import HardwareCounters, PackageEnergyMeter, bits_per_edge, peak_memory, work_report
    from .model import BoolMatrix, encode
    from .operators.pagerank import pagerank, product_of
    from .plans.spmv import spmv
    from .sources.graphs import matrix
    from .sources.tables import stored

    m = matrix(spark, sf_dir, dataset, square=True)
    m = BoolMatrix(stored(m.df, "sweep"), m.n_rows, m.n_cols)
    began = time.perf_counter()
    if fmt == "edgelist":
        step, space, work = product_of(m, fmt), {"bits_per_edge": 64.0, "total_per_edge": 64.0}, {"touched": m.df.count()}
    else:
        cm = encode(m.transpose(), fmt, degree, **opts)
        cm = cm.held(stored(cm.df, "sweep"))
        step, space, work = (lambda x: spmv(cm, x)), bits_per_edge(cm).first().asDict(), {r.counter: r.n for r in work_report(cm).collect()}
    encoded = time.perf_counter() - began
    pagerank(m, iterations=1, step=step, keep_history=False).ranks.count()  # workers and code are warm before the clock starts
    meter, counters = PackageEnergyMeter(), HardwareCounters()
    meter.start()
    counters.start()
    began = time.perf_counter()
    pagerank(m, iterations=iterations, step=step, keep_history=False).ranks.count()
    seconds, energy, counted = time.perf_counter() - began, meter.stop(), counters.stop()
    peak = peak_memory(spark)
    return {"dataset": dataset, "format": fmt, "degree": degree, "blocks": degree, "iterations": iterations, "encode_seconds": round(encoded, 3), "seconds": round(seconds, 3), "joules": energy["joules"], "joules_reason": energy["reason"], "bits": space["bits_per_edge"], "total_bits": space["total_per_edge"], "peak_mb": round(peak["driver_jvm_mb"] + peak["worker_python_mb"], 1), "counters": {k: float(v) for k, v in (work | counted).items() if isinstance(v, (int, float))}, "counters_reason": counted["reason"]}


def sweep(sf_dir: str, datasets: tuple[str, ...], formats: tuple[str, ...], degrees: tuple[int, ...] = (1, 2, 4), iterations: int = 100, profile: str = "server", timeout: int = 900, opts: dict | None = None) -> list[dict]:
    """A record per dataset, format and degree, one fresh session per degree. profile 'edge' gives the session a small heap.

    opts: encoder options by format. What a session has not ended within `timeout` seconds is recorded with seconds = None.
    """
    out = []
    for degree in degrees:
        pairs = [(d, f) for d in datasets for f in formats]
        args = {"sf": sf_dir, "pairs": pairs, "degree": degree, "iterations": iterations, "heap": "1g" if profile == "edge" else "4g", "opts": opts or {}}
        try:
            done = subprocess.run([sys.executable, "-c", _RUN, str(Path(__file__).resolve().parent.parent), json.dumps(args)], capture_output=True, text=True, timeout=timeout)
            told, why = done.stdout, done.stderr[-300:]
        except subprocess.TimeoutExpired as late:
            told, why = (late.stdout or b"").decode(), f"more than {timeout} s"
        found = [json.loads(x[4:]) for x in told.splitlines() if x.startswith("RUN ")]
        have = {(r["dataset"], r["format"]) for r in found}
        out += found + [{"dataset": d, "format": f, "degree": degree, "seconds": None, "reason": why} for d, f in pairs if (d, f) not in have]
    return out


def load_runs(spark, path: str | None = None):
    """Stored records as (dataset, format, degree, iterations, encode_seconds, seconds, joules, bits, total_bits, peak_mb,
    counters); by default those beside this file, measured on the host that RUNS.json names."""
    records = json.loads(Path(path or Path(__file__).with_name("RUNS.json")).read_text())["runs"]
    schema = "dataset string, format string, degree int, iterations int, encode_seconds double, seconds double, joules double, bits double, total_bits double, peak_mb double, counters map<string,double>"
    names = [x.split()[0] for x in schema.split(", ")]
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in records if r.get("seconds") is not None], schema)


def prepare(spark, sf_dir: str, dataset: str, formats: tuple[str, ...], blocks: int, path: str, **opts) -> dict[str, str]:
    """Extracts, transposes and encodes a dataset in each format, with its out-degrees beside; paths by name."""
    from .model import encode, write_matrix
    from .operators.pagerank import outdegrees
    from .sources.graphs import matrix

    m = matrix(spark, sf_dir, dataset, square=True)
    outdegrees(m).write.mode("overwrite").parquet(f"{path}/{dataset}/outdegree")
    paths = {"outdegree": f"{path}/{dataset}/outdegree"}
    for fmt in formats:
        paths[fmt] = f"{path}/{dataset}/format={fmt}"
        write_matrix(encode(m.transpose(), fmt, blocks, **opts), paths[fmt])
    return paths
