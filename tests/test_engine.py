"""The Spark layer: catalogue queries against DuckDB, PageRank's properties, plans, energy, streams, storage."""

import numpy as np
import pytest
from harness import compare, duck
from pyspark.sql import functions as F

from boolmat.metrics.measures import PackageEnergyMeter, bits_per_edge, hardware_counters, integrate_power, space_table
from boolmat.model import BoolMatrix, decode, encode, read_matrix, write_matrix
from boolmat.operators.pagerank import pagerank
from boolmat.plans.spmv import choose_spmv, spmv, spmv_edges
from boolmat.queries import ORACLES, QUERIES, v1
from boolmat.sources.generator import copy_model_graph
from boolmat.sources.graphs import matrix


def test_three_vertices(spark):
    m = BoolMatrix(spark.createDataFrame([(0, 1), (1, 0)], "row bigint, col bigint"), 3, 3)
    one = [r.value for r in pagerank(m, iterations=1).ranks.orderBy("id").collect()]
    assert np.allclose(one, [0.427778, 0.427778, 0.144444], atol=1e-6)
    far = pagerank(m, iterations=40, start=spark.createDataFrame([(2, 5.0)], "id bigint, value double"))
    assert np.allclose([r.value for r in far.ranks.orderBy("id").collect()], [0.465116, 0.465116, 0.069767], atol=1e-5)
    assert all(abs(r.mass - 1) < 1e-9 for r in far.history.collect())


@pytest.mark.parametrize("name", ["edges_web", "spmv_quadbits_dictionary", "spmv_left_dictionary", "spmv_pairgrammar_relational", "spmv_refcopy_relational", "pagerank_left", "submatrix", "quadbits_cell_lookup", "power_asof", "pareto_front", "stream_edge_delta_spmv", "join_theta"])
def test_against_duckdb(spark, sf, name):
    assert compare(QUERIES[name](spark, sf), duck(sf), ORACLES[name]) == ""


def test_block_count_does_not_matter(spark, sf):
    m = matrix(spark, sf, "F4")
    x = v1(m.n_cols, spark)
    want = sorted(map(tuple, spmv_edges(m, x).collect()))
    for blocks in (1, 3, 8):
        for by in ("rows", "nnz"):
            assert sorted(map(tuple, spmv(encode(m, "quadbits", blocks, by), x, emit="nonzero").collect())) == want


def test_store_and_read(spark, sf, tmp_path):
    m = matrix(spark, sf, "F3")
    write_matrix(encode(m, "pg_folded", 2), str(tmp_path / "m"))
    back = read_matrix(spark, str(tmp_path / "m"))
    assert decode(back).exceptAll(m.df).count() == 0 and m.df.exceptAll(decode(back)).count() == 0
    from boolmat.sources.datasource import MatrixSource

    spark.dataSource.register(MatrixSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    df = spark.read.format("boolmat").load(str(tmp_path / "m"))
    assert df.where("row < 5").count() == m.df.where("row < 5").count()


def test_order_of_sizes_on_a_web_like_graph(spark):
    g = copy_model_graph(spark, 3_000, blocks=1).select(F.col("u").alias("row"), F.col("v").alias("col"))
    sizes = space_table({"web": BoolMatrix(g, 3_000, 3_000)}, mode="batched").first()
    assert sizes.pg_w32 > sizes.pg_packed > sizes.pg_folded > sizes.quadbits > sizes.refcopy_stream
    assert sizes.deflate > sizes.lzma


def test_vector_strategies_and_plans(spark, sf):
    assert choose_spmv(1_000) == "broadcast" and choose_spmv(1 << 40) == "dictionary" and choose_spmv(10, 1, False) == "edges"
    m = matrix(spark, sf, "F4")
    cm = encode(m, "csr", 2)
    plan = spmv(cm, v1(m.n_cols, spark), "broadcast")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" in plan and "CartesianProduct" not in plan
    plan = spmv(cm, v1(m.n_cols, spark), "dictionary")._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "CartesianProduct" not in plan and "FlatMapCoGroupsInArrow" in plan


def test_energy(spark):
    rows = [(1, float(t), 2.0) for t in range(11)] + [(2, float(t), float(t)) for t in range(11)]
    trace = spark.createDataFrame(rows, "device bigint, s double, amps double").withColumn("ts", F.timestamp_seconds("s"))
    got = dict(integrate_power(trace, 5.0).collect())
    assert got[1] == pytest.approx(100) and got[2] == pytest.approx(250)
    told = PackageEnergyMeter("/nowhere").stop()
    assert told["joules"] is None and told["reason"]
    assert hardware_counters()["cycles"] is None


def test_bits_per_edge_of_pairs(spark, sf):
    assert bits_per_edge(encode(matrix(spark, sf, "F4"), "edgelist", 2)).first().bits_per_edge == 64


def test_embedding_product_takes_every_component(spark, sf):
    got = QUERIES["spmm_embeddings_whole"](spark, sf)
    assert {r.k for r in got.select("k").distinct().collect()} == set(range(64))
    assert compare(got, duck(sf), ORACLES["spmm_embeddings_whole"]) == ""


@pytest.mark.parametrize("name", ["union_all_edges", "union_edges", "intersect_all_edges", "intersect_edges", "except_all_edges", "except_edges", "join_full_vectors"])
def test_set_operators_and_full_join_over_whole_inputs(spark, sf, name):
    got = QUERIES[name](spark, sf)
    assert compare(got, duck(sf), ORACLES[name]) == ""
    n = matrix(spark, sf, "F2").df.count()
    if name == "join_full_vectors":
        assert got.where("a IS NULL").count() and got.where("b IS NULL").count()
    else:
        assert got.count() == {"union_all": 2 * n, "except": 0, "except_all": 0}.get(name.removesuffix("_edges"), n)


def test_space_tables_name_all_matrices_formats_and_counts(spark, sf, monkeypatch):
    from boolmat import queries

    assert queries.SURVEYED == ("F1", "F2", "F3", "F4", "F5", "F6", "F7", "F8", "F10")
    monkeypatch.setattr(queries, "SURVEYED", ("F3", "F5"))
    table = {r.dataset: r for r in QUERIES["space_table"](spark, sf).collect()}
    exact = bits_per_edge(encode(matrix(spark, sf, "F3"), "pg_packed", 1)).first().bits_per_edge
    assert set(table) == {"F3", "F5"} and table["F3"].pg_packed == exact and table["F5"].pg_packed > 0 and table["F5"].refcopy_stream is None
    monkeypatch.setattr(queries, "SURVEYED", ("F3",))
    got = {(r.dataset, r.format, r.blocks): r for r in QUERIES["space_vs_blocks"](spark, sf).collect()}
    formats = ("pg_w32", "pg_packed", "pg_folded", "quadbits", "refcopy_stream", "deflate", "lzma")
    assert set(got) == {("F3", f, b) for f in formats for b in (1, 2, 4, 8, 16, 24, 32, 40, 48)}
    assert got["F3", "pg_packed", 1].bits_per_edge == exact and got["F3", "pg_packed", 1].inflation == 1


def test_heavy_rows_are_spread_over_tiles(spark, monkeypatch):
    from boolmat import model
    from boolmat.model import cells_lookup, row_of
    from boolmat.plans.spmv import spmm, spmv_left

    monkeypatch.setattr(model.balanced_blocks, "__defaults__", (50,))
    rng = np.random.default_rng(4)
    cells = {(3, int(c)) for c in rng.choice(400, 180, replace=False)} | {(int(r), int(c)) for r, c in rng.integers(0, 300, (600, 2))}
    m = BoolMatrix(spark.createDataFrame(sorted(cells), "row bigint, col bigint"), 300, 400)
    dense = np.zeros((300, 400))
    dense[tuple(np.array(sorted(cells)).T)] = 1
    cm = encode(m, "quadbits", 6, by="nnz")
    assert cm.segmented and cm.df.where("row_hi = row_lo + 1 AND row_lo = 3").count() == 4
    assert sorted(map(tuple, decode(cm).collect())) == sorted(cells)
    x, z = np.arange(400) % 7, np.arange(300) % 5
    frame = lambda v: spark.createDataFrame([(i, float(a)) for i, a in enumerate(v)], "id bigint, value double")
    for how in ("broadcast", "dictionary"):
        right, left = (dict(f(cm, frame(v), how).collect()) for f, v in ((spmv, x), (spmv_left, z)))
        assert [right[i] for i in range(300)] == (dense @ x).tolist() and all(left.get(j, 0.0) == v for j, v in enumerate(z @ dense))
    wide = dict(spmm(cm, spark.createDataFrame([(i, [float(a), 1.0]) for i, a in enumerate(x)], "id bigint, vec array<double>"), 2).collect())
    assert wide[3] == (dense[3] @ np.column_stack([x, np.ones(400)])).tolist()
    assert sorted(r.col for r in row_of(cm, 3).collect()) == np.flatnonzero(dense[3]).tolist()
    asked = spark.createDataFrame([(3, c) for c in range(0, 400, 9)] + [(250, 1)], "row bigint, col bigint")
    assert all(r.found == bool(dense[r.row, r.col]) for r in cells_lookup(cm, asked).collect())


def test_plans_hold_no_list_of_tiles(spark, sf):
    from boolmat.plans.spmv import spmv_left

    m = matrix(spark, sf, "F4")
    cm = encode(m, "csr", 300, by="nnz")
    plan = spmv_left(cm, v1(m.n_rows, spark), "dictionary")._jdf.queryExecution().optimizedPlan().toString()
    assert "array(" not in plan.replace("FlatMap", "") and plan.count("Literal") < 50
    assert cm.df.agg(F.sum("nnz")).first()[0] == m.df.count() and cm.df.agg(F.max("nnz")).first()[0] < 10 * m.df.count() / 300 + 50


def test_steps_leave_no_old_tables(spark):
    m = BoolMatrix(spark.createDataFrame([(0, 1), (1, 0), (2, 0)], "row bigint, col bigint"), 3, 3)
    done = pagerank(m, iterations=6, keep_history=False)
    assert done.history.count() == 0 and done.ranks.count() == 3
