"""Headline timings: prints ONE JSON line. $BENCH_SF_DIR (default sf0.1), local[$BENCH_CPUS] (default 8), $BENCH_BUDGET seconds.

Per format: encoding the co-purchase matrix, its bits per edge, and the median of three products with a warm session;
then PageRank steps, some catalogue queries, and the products' kernels alone. What the budget leaves no time for is listed under "skipped".
"""

import json
import os
import statistics
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def kernel_seconds(n: int = 10_000) -> dict[str, dict[str, float]]:
    """Median seconds of right and left products of one tile in this process, without Spark: a matrix whose rows copy rows before."""
    import numpy as np

    from boolmat.formats.base import Tile
    from boolmat.formats.registry import FORMATS

    rng = np.random.default_rng(10)
    rows = [np.unique(rng.integers(0, n, 20))]
    for i in range(1, n):
        old = rows[max(0, i - int(rng.integers(1, 8)))]
        old = old[rng.random(len(old)) < 0.97]
        rows.append(np.unique(np.concatenate([old, np.rint(rng.normal(i, 30, max(0, 20 - len(old)))).astype(np.int64) % n])))
    tile = Tile(n, n, np.repeat(np.arange(n), [len(r) for r in rows]), np.concatenate(rows), None, {"mode": "batched"})
    x, out = rng.random(n), {}
    for name in ("csr", "pg_w32", "pg_packed", "pg_folded", "quadbits", "blocktree2d", "refcopy_stream", "refcopy_prefix", "deflate", "lzma"):
        parts, _ = FORMATS[name].encode(tile)
        told = {"bits_per_edge": round(8 * sum(map(len, parts.values())) / tile.nnz, 2)}
        for side, call in (("right", FORMATS[name].right), ("left", FORMATS[name].left)):
            times = []
            for _ in range(3):
                t = time.perf_counter()
                call(parts, n, n, x)
                times.append(time.perf_counter() - t)
            told[side] = round(statistics.median(times), 5)
        out[name] = told
    return out


def main() -> None:
    from pyspark.sql import SparkSession

    sf, cpus, budget = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), float(os.environ.get("BENCH_BUDGET", "240"))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g")).config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from boolmat.metrics.measures import PackageEnergyMeter, bits_per_edge
    from boolmat.model import BoolMatrix, encode
    from boolmat.operators.pagerank import pagerank
    from boolmat.plans.spmv import spmv, spmv_edges
    from boolmat.queries import QUERIES, v1
    from boolmat.sources.graphs import matrix
    from boolmat.sources.tables import stored

    began, out, bits, skipped = time.perf_counter(), {}, {}, []
    meter = PackageEnergyMeter()
    meter.start()

    def clock(name, action, repeat=1):
        if time.perf_counter() - began > budget:
            skipped.append(name)
            return None
        times = []
        for _ in range(repeat):
            t = time.perf_counter()
            result = action()
            times.append(time.perf_counter() - t)
        out[name] = round(statistics.median(times), 3)
        return result

    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    m = matrix(spark, sf, "F2")
    m = BoolMatrix(stored(m.df, "bench"), m.n_rows, m.n_cols)
    x = stored(v1(m.n_cols, spark), "bench")
    noop(spmv_edges(m, x))
    clock("product_edgelist", lambda: noop(spmv_edges(m, x)), 3)
    for fmt, opts in (("csr", {}), ("quadbits", {}), ("pg_w32", {"mode": "batched"}), ("pg_packed", {"mode": "batched"}), ("pg_folded", {"mode": "batched"}), ("deflate", {}), ("refcopy_stream", {})):
        def make(fmt=fmt, opts=opts):
            cm = encode(m.transpose(), fmt, int(cpus), **opts)
            return cm.held(stored(cm.df, "bench"))

        cm = clock(f"encode_{fmt}", make)
        if cm:
            bits[fmt] = round(bits_per_edge(cm).first()["bits_per_edge"], 3)
            clock(f"product_{fmt}", lambda cm=cm: noop(spmv(cm, x)), 3)
    clock("pagerank_edgelist_5", lambda: noop(pagerank(m, iterations=5).ranks))
    clock("pagerank_quadbits_5", lambda: noop(pagerank(m, iterations=5, fmt="quadbits", blocks=int(cpus)).ranks))
    for name in ("graph_profile_F1", "spmv_edgelist", "spmv_valued_edgelist", "quadbits_level_counts_F2", "join_hash", "power_asof", "energy_trace_integral", "cube", "stream_tumbling_power"):
        clock(name, lambda name=name: noop(QUERIES[name](spark, sf)))
    kernels = kernel_seconds()
    base = out.get("product_edgelist") or 1.0
    ratios = {k[8:]: round(v / base, 3) for k, v in out.items() if k.startswith("product_")}
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": sf, "bits_per_edge": bits, "product_ratio_to_edgelist": ratios, "kernel_seconds": kernels, "energy": meter.stop(), "skipped": skipped}))


if __name__ == "__main__":
    main()
