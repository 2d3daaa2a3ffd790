"""The query catalogue: a Spark plan per method, variant, baseline, measure, workload and operator, and its SQL twin."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .formats.registry import COMPARED
from .functions.scalar import byte_bits, gaps, list_diff, merge_metrics, morton, register_functions, runs, width_bits
from .metrics import measures, reports
from .model import BoolMatrix, cells_lookup, decode, encode, read_matrix, row_blocks, row_of, submatrix
from .operators import algebra, pagerank as pr
from .operators import relational as rel
from .plans import spmv as plans
from .sources import graphs
from .sources.graphs import SQL, edges_cte
from .sources.tables import load, reverse_host, shared_dir, stored, url_path
from .streaming import power
from .sweep import prepare

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def rounded(df: DataFrame, *cols: str, digits: int = 9) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), digits) + F.lit(0.0) for c in cols})


def v1(n: int, spark: SparkSession) -> DataFrame:
    """The integer test vector: exact in any order of summation."""
    return spark.range(n).select("id", ((F.col("id") * 7919 + 13) % 101).cast("double").alias("value"))


_X = lambda c: f"((({c}) * 7919 + 13) % 101)::DOUBLE"


# Datasets -----------------------------------------------------------------------------------------------------------
def _edges(name: str) -> Query:
    return lambda s, d: graphs.GRAPHS[name](s, d).select(F.col("u").cast("bigint").alias("u"), F.col("v").cast("bigint").alias("v"))


for _f, _label in (("F1", "succession"), ("F2", "copurchase"), ("F3", "user_next"), ("F6", "web"), ("F7", "page_href"), ("F8", "doc_token"), ("F11", "cust_part")):
    add(f"edges_{_label}", _edges(_f), f"WITH {edges_cte(_f)} SELECT DISTINCT u::BIGINT AS u, v::BIGINT AS v FROM e")
_SIZE = {"F1": "(SELECT max(c_custkey) + 1 FROM customer)", "F2": "(SELECT max(p_partkey) + 1 FROM part)", "F3": "(SELECT greatest(max(u), max(v)) + 1 FROM e)", "F4": "(SELECT max(o_orderkey) + 1 FROM orders)", "F5": "(SELECT max(o_orderkey) + 1 FROM orders)", "F6": "(SELECT greatest(max(u), max(v)) + 1 FROM e)"}
for _f in ("F1", "F2", "F3", "F4", "F5", "F6", "F7", "F8", "F9", "F11"):
    _n = _SIZE.get(_f, "(SELECT max(u) + 1 FROM e)")
    add(f"graph_profile_{_f}", lambda s, d, f=_f: rounded(measures.graph_profile(graphs.matrix(s, d, f)), "mean_degree"), f"WITH {edges_cte(_f)} SELECT {_n}::BIGINT AS n, count(*) AS m, round(count(*) / {_n}::DOUBLE, 9) AS mean_degree, ({_n} - count(DISTINCT u))::BIGINT AS dangling FROM e")
add("graph_profile_F10", lambda s, d: rounded(measures.graph_profile(graphs.matrix(s, d, "F10", square=True)), "mean_degree"))
add("outdegree", lambda s, d: pr.outdegrees(graphs.matrix(s, d, "F6")), f"WITH {edges_cte('F6')} SELECT r.i AS id, count(e.u) AS degree FROM range({_SIZE['F6']}) r(i) LEFT JOIN e ON e.u = r.i GROUP BY 1")
add("transpose_edges", lambda s, d: graphs.matrix(s, d, "F4").transpose().df, f"WITH {edges_cte('F4')} SELECT v AS row, u AS col FROM e")
add("dangling_vertices", lambda s, d: rel.join_anti(s.range(graphs.matrix(s, d, "F6").n_rows), graphs.matrix(s, d, "F6").df.select(F.col("row").alias("id")), "id"), f"WITH {edges_cte('F6')} SELECT i AS id FROM range({_SIZE['F6']}) r(i) WHERE i NOT IN (SELECT u FROM e)")
add("random_walk_row_sums", lambda s, d: rounded(pr.random_walk_matrix(graphs.matrix(s, d, "F2")).groupBy("row").agg(F.sum("val").alias("total")), "total"), f"WITH {edges_cte('F2')} SELECT u AS row, 1.0::DOUBLE AS total FROM e GROUP BY u")

# Products -----------------------------------------------------------------------------------------------------------
_RIGHT = lambda f: f"WITH {edges_cte(f)} SELECT u::BIGINT AS id, sum({_X('v')}) AS value FROM e GROUP BY u"
_LEFT = lambda f: f"WITH {edges_cte(f)} SELECT v::BIGINT AS id, sum({_X('u')}) AS value FROM e GROUP BY v"


def _right(f: str, fmt: str, blocks: int = 4, strategy: str = "auto", **opts) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        m = graphs.matrix(s, d, f)
        return plans.spmv(encode(m, fmt, blocks, **opts), v1(m.n_cols, s), strategy, "nonzero")

    return run


def _left(f: str, fmt: str, blocks: int = 4, strategy: str = "auto", **opts) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        m = graphs.matrix(s, d, f)
        return plans.spmv_left(encode(m, fmt, blocks, **opts), v1(m.n_rows, s), strategy)

    return run


def _over_edges(f: str, how: Callable) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        m = graphs.matrix(s, d, f)
        return how(m, v1(max(m.n_cols, m.n_rows), s))

    return run


add("spmv_edgelist", _over_edges("F4", plans.spmv_edges), _RIGHT("F4"))
add("spmv_edgelist_merge", _over_edges("F4", lambda m, x: plans.spmv_edges(m, x, "merge")), _RIGHT("F4"))
for _name, _f, _fmt, _o in (
    ("csr", "F4", "csr", {}), ("dense", "F3", "dense", {}), ("deflate", "F4", "deflate", {}), ("lzma", "F4", "lzma", {}),
    ("refcopy_prefix", "F4", "refcopy_prefix", {}), ("refcopy_stream", "F8", "refcopy_stream", {"blocks": 8}), ("refcopy_nowindow", "F7", "refcopy_prefix", {"window": 0}),
    ("quadbits_k2", "F2", "quadbits", {}), ("quadbits_k4", "F4", "quadbits", {"k": 4}), ("quadbits_hybrid", "F2", "quadbits", {"top_k": 4, "top_levels": 2}), ("quadbits_leaf8", "F2", "quadbits", {"leaf_side": 8}), ("quadbits_rank", "F4", "quadbits", {"rank_directory": True}),
    ("pairgrammar_w32", "F4", "pg_w32", {}), ("pairgrammar_packed", "F4", "pg_packed", {}), ("pairgrammar_folded", "F4", "pg_folded", {}), ("pairgrammar_batched", "F8", "pg_w32", {"mode": "batched", "blocks": 8}),
    ("biclique", "F7", "biclique", {}), ("blocktree2d", "F4", "blocktree2d", {}), ("colgroup", "F7", "colgroup", {}),
):
    add(f"spmv_{_name}", _right(_f, _fmt, **_o), _RIGHT(_f))
add("spmv_quadbits_dictionary", _right("F4", "quadbits", 8, "dictionary"), _RIGHT("F4"))
add("spmv_quadbits_balanced", lambda s, d: plans.spmv(encode(graphs.matrix(s, d, "F8"), "quadbits", 8, by="nnz"), v1(graphs.matrix(s, d, "F8").n_cols, s), "dictionary", "nonzero"), _RIGHT("F8"))
add("spmv_quadbits_relational", _over_edges("F2", algebra.spmv_quad_relational), _RIGHT("F2"))
add("spmv_refcopy_relational", _over_edges("F7", algebra.spmv_refcopy_relational), _RIGHT("F7"))
add("spmv_pairgrammar_relational", _over_edges("F7", lambda m, x: algebra.spmv_pair_relational(m, x, 3)), _RIGHT("F7"))
add("spmv_left_edgelist", _over_edges("F4", plans.spmv_left_edges), _LEFT("F4"))
for _name, _fmt in (("csr", "csr"), ("refcopy", "refcopy_prefix"), ("quadbits", "quadbits"), ("pairgrammar", "pg_w32"), ("pairgrammar_folded", "pg_folded"), ("colgroup", "colgroup"), ("biclique", "biclique"), ("blocktree2d", "blocktree2d")):
    add(f"spmv_left_{_name}", _left("F7" if _name in ("colgroup", "biclique") else "F4", _fmt), _LEFT("F7" if _name in ("colgroup", "biclique") else "F4"))
add("spmv_left_dictionary", _left("F4", "pg_packed", 8, "dictionary"), _LEFT("F4"))
_VALUED = f"WITH {edges_cte('F5')} SELECT u::BIGINT AS id, sum(val * {_X('v')}) AS value FROM e GROUP BY u"
_VALUED_LEFT = f"WITH {edges_cte('F5')} SELECT v::BIGINT AS id, sum(val * {_X('u')}) AS value FROM e GROUP BY v"
add("spmv_valued_pairgrammar", _right("F5", "pg_w32"), _VALUED)
add("spmv_valued_colgroup", _right("F5", "colgroup"), _VALUED)
add("spmv_valued_edgelist", _over_edges("F5", plans.spmv_edges), _VALUED)
add("spmv_left_valued", _left("F5", "pg_packed"), _VALUED_LEFT)


def _ternary(s: SparkSession, d: str) -> DataFrame:
    plus, minus = algebra.quantize_ternary(load(s, d, "embeddings"), 0.075)
    n = (load(s, d, "embeddings").agg(F.max("vec_id")).first()[0] or 0) + 1
    return plans.spmv_ternary(encode(BoolMatrix(plus, n, 64), "quadbits", 2), encode(BoolMatrix(minus, n, 64), "quadbits", 2), v1(64, s))


add("spmv_ternary", _ternary, f"SELECT r.i AS id, coalesce(sum(s * {_X('v')}), 0)::DOUBLE AS value FROM range((SELECT max(vec_id) + 1 FROM embeddings)) r(i) LEFT JOIN (SELECT u, v, 1 AS s FROM ({SQL['F9']}) UNION ALL SELECT u, v, -1 FROM ({SQL['F9m']})) t ON t.u = r.i GROUP BY 1")


def _spmm(s: SparkSession, d: str) -> DataFrame:
    m = graphs.matrix(s, d, "F3")
    x = load(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.slice("embedding", 1, 4).cast("array<double>").alias("vec"))
    y = plans.spmm(encode(m, "pg_w32", 2), x, 4)
    return y.select("id", F.posexplode("vec").alias("k", "value")).where("value <> 0").select("id", F.col("k").cast("bigint").alias("k"), (F.round("value", 9) + F.lit(0.0)).alias("value"))


def _spmm_whole(s: SparkSession, d: str) -> DataFrame:
    """All components, for the rows with a one whose column has a vector."""
    m, vectors = graphs.matrix(s, d, "F3"), load(s, d, "embeddings")
    x = vectors.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    width = vectors.agg(F.max(F.size("embedding"))).first()[0] or 0
    met = m.df.join(x.select(F.col("id").alias("col")), "col", "left_semi").select(F.col("row").alias("id")).distinct()
    y = plans.spmm(encode(m, "pg_w32", 2), x, width).join(met, "id", "left_semi")
    return rounded(y.select("id", F.posexplode("vec").alias("k", "value")).withColumn("k", F.col("k").cast("bigint")), "value")


add("spmm_embeddings", _spmm, f"WITH {edges_cte('F3')}, x AS (SELECT vec_id, unnest(embedding[1:4]) AS c, generate_subscripts(embedding[1:4], 1) - 1 AS k FROM embeddings) SELECT u AS id, k::BIGINT AS k, round(sum(c::DOUBLE), 9) AS value FROM e JOIN x ON e.v = x.vec_id GROUP BY 1, 2")
add("spmm_embeddings_whole", _spmm_whole, f"WITH {edges_cte('F3')}, x AS (SELECT vec_id, unnest(embedding) AS c, generate_subscripts(embedding, 1) - 1 AS k FROM embeddings) SELECT u AS id, k::BIGINT AS k, round(sum(c::DOUBLE), 9) AS value FROM e JOIN x ON e.v = x.vec_id GROUP BY 1, 2")

# Round trips, access, algebra ---------------------------------------------------------------------------------------
def _roundtrip(f: str, fmt: str, blocks: int) -> Query:
    """Encodes, stores the tiles, decodes what is stored: chained, a task would hold two Python workers at once."""
    def run(s: SparkSession, d: str) -> DataFrame:
        cm = encode(graphs.matrix(s, d, f), fmt, blocks)
        return decode(cm.held(stored(cm.df, "tiles")))

    return run


for _fmt, _f, _b in (("csr", "F6", 3), ("dense", "F3", 2), ("deflate", "F7", 2), ("lzma", "F7", 2), ("refcopy_prefix", "F6", 3), ("refcopy_stream", "F2", 4), ("quadbits", "F8", 4), ("pg_w32", "F1", 4), ("pg_packed", "F6", 3), ("pg_folded", "F2", 4), ("blocktree2d", "F2", 4), ("biclique", "F6", 3), ("colgroup", "F7", 3)):
    add(f"roundtrip_{_fmt}", _roundtrip(_f, _fmt, _b), f"WITH {edges_cte(_f)} SELECT u::BIGINT AS row, v::BIGINT AS col FROM e")
add("roundtrip_valued", _roundtrip("F5", "pg_folded", 4), f"WITH {edges_cte('F5')} SELECT u AS row, v AS col, val FROM e")
add("row_of_refcopy", lambda s, d: row_of(encode(graphs.matrix(s, d, "F2"), "refcopy_prefix", 3), 7), f"WITH {edges_cte('F2')} SELECT u::BIGINT AS row, v::BIGINT AS col FROM e WHERE u = 7")
add("submatrix", lambda s, d: submatrix(encode(graphs.matrix(s, d, "F2"), "quadbits", 8), (100, 300), (50, 150)), f"WITH {edges_cte('F2')} SELECT u AS row, v AS col FROM e WHERE u >= 100 AND u < 300 AND v >= 50 AND v < 150")
add("quadbits_cell_lookup", lambda s, d: cells_lookup(encode(graphs.matrix(s, d, "F3"), "quadbits", 2), s.range(400).select((F.col("id") % 20).alias("row"), F.floor(F.col("id") / 20).alias("col"))), f"WITH {edges_cte('F3')} SELECT (i % 20)::BIGINT AS row, (i // 20)::BIGINT AS col, EXISTS (SELECT 1 FROM e WHERE u = i % 20 AND v = i // 20) AS found FROM range(400) r(i)")


def _levels(f: str, k: int) -> str:
    step = k.bit_length() - 1
    return f"""WITH {edges_cte(f)}, side AS (SELECT greatest((SELECT max(u) FROM e), (SELECT max(v) FROM e), coalesce({_SIZE.get(f, '0')}, 0) - 1) + 1 AS n), h AS (SELECT greatest(1, ceil(log2(n::DOUBLE)))::INT AS b FROM side)
        SELECT l::INT AS level, count(DISTINCT ((u >> ({step} * l)::INT) * 1000000000 + (v >> ({step} * l)::INT))) AS nodes FROM e, range(1, 40) r(l), h WHERE {step} * (l - 1) < b GROUP BY 1"""


for _f in ("F1", "F2", "F3", "F8"):
    add(f"quadbits_level_counts_{_f}", lambda s, d, f=_f: algebra.quad_level_counts(graphs.matrix(s, d, f)), _levels(_f, 2))
for _k in (2, 4):
    add(f"quadbits_total_bits_k{_k}", lambda s, d, k=_k: algebra.quad_level_counts(graphs.matrix(s, d, "F2"), k).agg((F.sum("nodes") * k * k).alias("bits")), f"SELECT ({_k * _k} * sum(nodes))::BIGINT AS bits FROM ({_levels('F2', _k)})")
add("quadbits_packed_bits", lambda s, d: measures.tree_space(graphs.matrix(s, d, "F2")).select(F.col("tree_bits").alias("bits")), f"SELECT (4 * sum(nodes))::BIGINT AS bits FROM ({_levels('F2', 2)})")
add("mat_sum_bool", lambda s, d: algebra.mat_sum(graphs.matrix(s, d, "F1"), graphs.matrix(s, d, "F1").transpose()), f"WITH {edges_cte('F1')} SELECT u AS row, v AS col FROM e UNION SELECT v, u FROM e")
add("mat_mul_count", lambda s, d: algebra.mat_mul(graphs.matrix(s, d, "F3"), graphs.matrix(s, d, "F3")), f"WITH {edges_cte('F3')} SELECT a.u AS row, b.v AS col, count(*)::DOUBLE AS val FROM e a JOIN e b ON a.v = b.u GROUP BY 1, 2")
add("mat_mul_bool", lambda s, d: algebra.mat_mul(graphs.matrix(s, d, "F1"), graphs.matrix(s, d, "F3"), "bool"), f"WITH {edges_cte('F1')}, f AS ({SQL['F3']}) SELECT DISTINCT e.u::BIGINT AS row, f.v::BIGINT AS col FROM e JOIN f ON e.v = f.u")


def _tree(s: SparkSession, d: str, f: str, turned: bool = False) -> tuple[DataFrame, int]:
    m = graphs.matrix(s, d, f)
    return stored(algebra.quad_nodes(m.transpose() if turned else m), "tree"), algebra.depth_of(max(m.n_rows, m.n_cols))


def _tree_sum(s: SparkSession, d: str) -> DataFrame:
    (a, h), (b, _) = _tree(s, d, "F1"), _tree(s, d, "F1", True)
    return algebra.quad_cells(stored(algebra.quad_sum(a, b), "tree"), h)


add("mat_sum_tree", _tree_sum, f"WITH {edges_cte('F1')} SELECT u::BIGINT AS row, v::BIGINT AS col FROM e UNION SELECT v::BIGINT, u::BIGINT FROM e")
for _kind, _cells in (("count", "count(*)::DOUBLE AS val FROM e a JOIN e b ON a.v = b.u GROUP BY 1, 2"), ("bool", None)):
    _q = lambda s, d, k=_kind: (lambda t: algebra.quad_product(t[0], t[0], t[1], k))(_tree(s, d, "F3"))
    add(f"mat_mul_tree_{_kind}", _q, f"WITH {edges_cte('F3')} SELECT {'a.u::BIGINT AS row, b.v::BIGINT AS col, ' + _cells if _cells else 'DISTINCT a.u::BIGINT AS row, b.v::BIGINT AS col FROM e a JOIN e b ON a.v = b.u'}")


def _transpose_tree(s: SparkSession, d: str) -> DataFrame:
    m = graphs.matrix(s, d, "F3")
    h = algebra.depth_of(max(m.n_rows, m.n_cols))
    return m.df.select(algebra.transposed_codes(morton(F.col("row"), F.col("col"), h), h).alias("z"))


add("transpose_quadbits", _transpose_tree, f"WITH {edges_cte('F3')} SELECT list_sum([(((v >> i) & 1) << (2 * i + 1)) + (((u >> i) & 1) << (2 * i)) for i in range(0, 31)])::BIGINT AS z FROM (SELECT u::BIGINT AS u, v::BIGINT AS v FROM e)")

# Ranks --------------------------------------------------------------------------------------------------------------
_T = 10


def rank_sql(f: str, steps: int = _T, alpha: float = 0.15, tp: str = "1.0::DOUBLE / (SELECT n FROM size)", out: str | None = None) -> str:
    """A chain of power-iteration steps, one CTE each."""
    ctes = [edges_cte(f), f"size AS (SELECT {_SIZE[f]}::BIGINT AS n)", "deg AS MATERIALIZED (SELECT u, count(*) AS d FROM e GROUP BY u)", f"vert AS MATERIALIZED (SELECT i AS id, coalesce(d, 0) AS d, ({tp})::DOUBLE AS tp FROM range((SELECT n FROM size)) r(i) LEFT JOIN deg ON u = i)", "r0 AS MATERIALIZED (SELECT id, 1.0::DOUBLE / (SELECT n FROM size) AS value FROM vert)"]
    for t in range(1, steps + 1):
        p = f"r{t - 1}"
        ctes.append(f"r{t} AS MATERIALIZED (SELECT vert.id, {alpha} * tp + {1 - alpha} * (coalesce(y, 0) + (SELECT coalesce(sum(value), 0) FROM {p} JOIN vert USING (id) WHERE d = 0) / (SELECT n FROM size)) AS value FROM vert LEFT JOIN (SELECT e.v AS id, sum(value / d) AS y FROM e JOIN {p} ON {p}.id = e.u JOIN vert ON vert.id = e.u GROUP BY 1) USING (id))")
    return "WITH " + ", ".join(ctes) + (out or f" SELECT id::BIGINT AS id, round(value, 9) AS value FROM r{steps}")


def _ranks(f: str, **opts) -> Query:
    return lambda s, d: rounded(pr.pagerank(graphs.matrix(s, d, f), iterations=_T, **opts).ranks, "value")


for _name, _f, _o in (("edgelist", "F6", {}), ("refcopy", "F6", {"fmt": "refcopy_stream", "blocks": 3}), ("quadbits", "F2", {"fmt": "quadbits", "blocks": 4}), ("pairgrammar", "F2", {"fmt": "pg_w32", "blocks": 4, "mode": "batched"}), ("left", "F6", {"fmt": "pg_packed", "blocks": 3, "side": "left"})):
    add(f"pagerank_{_name}", _ranks(_f, **_o), rank_sql(_f))


def _personal(s: SparkSession, d: str) -> DataFrame:
    tp = load(s, d, "customer").select(F.col("c_custkey").alias("id"), (F.col("c_nationkey") % 5).cast("double").alias("value"))
    return rounded(pr.pagerank(graphs.matrix(s, d, "F1"), iterations=5, teleport=tp).ranks, "value")


add("pagerank_personalised", _personal, rank_sql("F1", 5, tp="(SELECT (c_nationkey % 5)::DOUBLE FROM customer WHERE c_custkey = i) / (SELECT sum(c_nationkey % 5) FROM customer)"))
add("pagerank_start", lambda s, d: rounded(pr.pagerank(graphs.matrix(s, d, "F3"), iterations=12, start=s.range(1).select("id", F.lit(1.0).alias("value"))).ranks, "value"), None)
add("pagerank_threshold", lambda s, d: rounded(pr.pagerank(graphs.matrix(s, d, "F3"), iterations=30, tol=1e-3, check_every=5).ranks, "value"), rank_sql("F3", 5))
add("pagerank_history", lambda s, d: rounded(pr.pagerank(graphs.matrix(s, d, "F6"), iterations=5).history, "delta", "mass", "dangling"), rank_sql("F6", 5, out=" " + " UNION ALL ".join(f"SELECT {t}::INT AS t, round((SELECT sum(abs(a.value - b.value)) FROM r{t} a JOIN r{t - 1} b USING (id)), 9) AS delta, round((SELECT sum(value) FROM r{t}), 9) AS mass, round((SELECT coalesce(sum(value), 0) FROM r{t - 1} JOIN vert USING (id) WHERE d = 0), 9) AS dangling" for t in range(1, 6))))


def _eigen_sql(steps: int) -> str:
    ctes = [edges_cte("F3"), f"size AS (SELECT {_SIZE['F3']}::BIGINT AS n)", "r0 AS (SELECT i AS id, 1.0::DOUBLE / n AS value FROM size, range((SELECT n FROM size)) r(i))"]
    for t in range(1, steps + 1):
        ctes += [f"s{t} AS MATERIALIZED (SELECT v AS id, sum(value) AS value FROM e JOIN r{t - 1} ON id = u GROUP BY 1)", f"r{t} AS MATERIALIZED (SELECT id, value / (SELECT sqrt(sum(value * value)) FROM s{t}) AS value FROM s{t})"]
    return "WITH " + ", ".join(ctes) + f" SELECT id, round(value, 9) AS value FROM r{steps}"


add("eigen_centrality", lambda s, d: rounded(pr.eigen_centrality(graphs.matrix(s, d, "F3"), 4), "value"), _eigen_sql(4))
add("eigen_centrality_quadbits", lambda s, d: rounded(pr.eigen_centrality(graphs.matrix(s, d, "F3"), 4, "quadbits", blocks=2).where("value <> 0"), "value"), _eigen_sql(4))


def _hits_sql(steps: int) -> str:
    ctes = [edges_cte("F3"), f"size AS (SELECT {_SIZE['F3']}::BIGINT AS n)", "h0 AS (SELECT i AS id, 1.0::DOUBLE AS value FROM range((SELECT n FROM size)) r(i))"]
    for t in range(1, steps + 1):
        for name, src, a, b in ((f"a{t}", f"h{t - 1}", "v", "u"), (f"h{t}", f"a{t}", "u", "v")):
            ctes += [f"s{name} AS MATERIALIZED (SELECT {a} AS id, sum(value) AS value FROM e JOIN {src} ON id = {b} GROUP BY 1)", f"{name} AS MATERIALIZED (SELECT id, value / (SELECT sqrt(sum(value * value)) FROM s{name}) AS value FROM s{name})"]
    return "WITH " + ", ".join(ctes) + f" SELECT h0.id, round(coalesce(h.value, 0), 9) AS hub, round(coalesce(a.value, 0), 9) AS authority FROM h0 LEFT JOIN h{steps} h USING (id) LEFT JOIN a{steps} a USING (id)"


add("hits", lambda s, d: rounded(pr.hits(graphs.matrix(s, d, "F3"), 3), "hub", "authority"), _hits_sql(3))
add("katz", lambda s, d: rounded(pr.katz(graphs.matrix(s, d, "F1"), 0.001, 3), "value"), "WITH " + edges_cte("F1") + f", n AS (SELECT i AS id FROM range({_SIZE['F1']}) r(i)), k0 AS (SELECT id, 1.0::DOUBLE AS value FROM n)" + "".join(f", k{t} AS MATERIALIZED (SELECT n.id, 1.0 + 0.001::DOUBLE * coalesce(y, 0) AS value FROM n LEFT JOIN (SELECT v AS id, sum(value) AS y FROM e JOIN k{t - 1} ON id = u GROUP BY 1) USING (id))" for t in (1, 2, 3)) + " SELECT id, round(value, 9) AS value FROM k3")


def _cg_sql(steps: int) -> str:
    ctes = [edges_cte("F3"), f"n AS (SELECT i AS id FROM range({_SIZE['F3']}) r(i))", "b AS (SELECT id, ((id * 7919 + 13) % 101)::DOUBLE AS value FROM n)", "r0 AS MATERIALIZED (SELECT n.id, coalesce(s, 0) AS value FROM n LEFT JOIN (SELECT v AS id, sum(value) AS s FROM e JOIN b ON id = u GROUP BY 1) USING (id))", "p0 AS (SELECT * FROM r0)", "x0 AS (SELECT id, 0.0::DOUBLE AS value FROM n)"]
    for t in range(1, steps + 1):
        o = t - 1
        ctes += [
            f"m{t} AS MATERIALIZED (SELECT u AS id, sum(value) AS value FROM e JOIN p{o} ON id = v GROUP BY 1)",
            f"q{t} AS MATERIALIZED (SELECT n.id, coalesce(s, 0) AS value FROM n LEFT JOIN (SELECT v AS id, sum(value) AS s FROM e JOIN m{t} ON id = u GROUP BY 1) USING (id))",
            f"a{t} AS MATERIALIZED (SELECT (SELECT sum(value * value) FROM r{o}) / (SELECT sum(p.value * q.value) FROM p{o} p JOIN q{t} q USING (id)) AS a)",
            f"x{t} AS MATERIALIZED (SELECT id, x.value + (SELECT a FROM a{t}) * p.value AS value FROM x{o} x JOIN p{o} p USING (id))",
            f"r{t} AS MATERIALIZED (SELECT id, r.value - (SELECT a FROM a{t}) * q.value AS value FROM r{o} r JOIN q{t} q USING (id))",
            f"p{t} AS MATERIALIZED (SELECT id, r.value + (SELECT sum(value * value) FROM r{t}) / (SELECT sum(value * value) FROM r{o}) * p.value AS value FROM r{t} r JOIN p{o} p USING (id))",
        ]
    return "WITH " + ", ".join(ctes) + f" SELECT id, round(value, 6) AS value FROM x{steps}"


def _cg(s: SparkSession, d: str) -> DataFrame:
    m = graphs.matrix(s, d, "F3")
    return rounded(pr.cg_normal(encode(m, "pg_w32", 2), v1(m.n_rows, s), 2), "value", digits=6)


add("cg_normal", _cg, _cg_sql(2))

# Measures -----------------------------------------------------------------------------------------------------------
#: The matrices of the space tables.
SURVEYED = ("F1", "F2", "F3", "F4", "F5", "F6", "F7", "F8", "F10")


def _surveyed(s: SparkSession, d: str) -> dict[str, BoolMatrix]:
    return {f: graphs.matrix(s, d, f, f == "F10") for f in SURVEYED}


add("space_table", lambda s, d: measures.space_table(_surveyed(s, d)))
for _f in ("F1", "F2"):
    _cells = f"SELECT count(*) AS m FROM ({SQL[_f]})"
    add(f"space_quadbits_{_f}", lambda s, d, f=_f: rounded(measures.tree_space(graphs.matrix(s, d, f)).select("nnz", "bits", "bits_per_edge"), "bits_per_edge"), f"SELECT m AS nnz, b AS bits, round(b / m::DOUBLE, 9) AS bits_per_edge FROM (SELECT (8 * ceil(sum(nodes) / 2.0) + 64 * (count(*) + 1))::BIGINT AS b FROM ({_levels(_f, 2)})), ({_cells})")
add("web_vs_social", lambda s, d: measures.web_vs_social({"web": graphs.matrix(s, d, "F10", square=True)}, {"social": graphs.matrix(s, d, "F2")}))
add("space_breakdown", lambda s, d: measures.space_report(encode(graphs.matrix(s, d, "F6"), "pg_folded", 1)))
add("space_vs_blocks", lambda s, d: measures.space_vs_blocks(_surveyed(s, d), (*COMPARED, "deflate", "lzma")))
add("work_report_edgelist", lambda s, d: measures.work_report(encode(graphs.matrix(s, d, "F4"), "edgelist", 4)), f"WITH {edges_cte('F4')} SELECT 'touched' AS counter, count(*)::BIGINT AS n FROM e")
add("product_error", lambda s, d: (lambda m: measures.product_error(plans.spmv(encode(m, "refcopy_prefix", 3), v1(m.n_cols, s), emit="nonzero"), plans.spmv_edges(m, v1(m.n_cols, s))))(graphs.matrix(s, d, "F6")), "SELECT 0.0::DOUBLE AS max_abs, 0.0::DOUBLE AS max_rel, 0::BIGINT AS only_one")
add("byte_compressor_bits", lambda s, d: row_blocks(graphs.matrix(s, d, "F7"), 4)[0].select("blk", "row", "col").groupBy("blk").applyInArrow(lambda t: byte_bits("deflate")(t.drop(["blk"])), "bits bigint").agg(F.sum("bits").alias("bits")))
_DEVICES = "(SELECT user_id AS device, ts, value AS amps FROM events)"


def _trace(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events").select(F.col("user_id").alias("device"), "ts", F.col("value").alias("amps"))


add("energy_trace_integral", lambda s, d: rounded(measures.integrate_power(_trace(s, d), 5.0), "joules", digits=1), f"SELECT device, round(sum((epoch_us(t2) - epoch_us(ts)) / 1000000.0::DOUBLE * (amps + a2) / 2 * 5.0), 1) AS joules FROM (SELECT *, lead(ts) OVER w AS t2, lead(amps) OVER w AS a2 FROM {_DEVICES} WINDOW w AS (PARTITION BY device ORDER BY ts, amps)) WHERE t2 IS NOT NULL GROUP BY 1")
add("rolling_power", lambda s, d: rounded(rel.rolling(load(s, d, "events"), ["user_id"], "ts", 86_400, "value").select("event_id", "rolling"), "rolling", digits=6), "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW), 6) AS rolling FROM events")
add("power_asof", lambda s, d: rel.join_asof(load(s, d, "events").where("event_type = 'error'").select("event_id", "user_id", "ts"), load(s, d, "events").where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value")), "ts", ["user_id"], "value").select("event_id", "asof_value"), "WITH p AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) SELECT l.event_id, p.value AS asof_value FROM (SELECT * FROM events WHERE event_type = 'error') l ASOF LEFT JOIN p ON l.user_id = p.user_id AND l.ts >= p.ts")
add("power_interval_join", lambda s, d: rel.join_interval(load(s, d, "events").select("event_id", "ts"), load(s, d, "events").where("event_type = 'purchase'").select(F.col("event_id").alias("run"), F.col("ts").alias("start"), (F.col("ts") + F.expr("INTERVAL 30 MINUTES")).alias("end")), "ts", "start", "end").groupBy("run").agg(F.count("*").alias("samples")), "SELECT r.event_id AS run, count(*) AS samples FROM events r JOIN events p ON p.ts >= r.ts AND p.ts < r.ts + INTERVAL 30 MINUTE WHERE r.event_type = 'purchase' GROUP BY 1")

# Run reports on records derived from events: not measurements -------------------------------------------------------
_RUNS_SQL = "(SELECT 'd' || (user_id % 3) AS dataset, event_type AS format, (1 << (day(ts) % 5)::INT)::INT AS degree, count(*)::DOUBLE AS seconds, round(sum(value), 6) AS joules, max(value) AS bits FROM events GROUP BY 1, 2, 3)"


def pseudo_runs(s: SparkSession, d: str) -> DataFrame:
    """Run records made from events by rule, to test reports only."""
    e = load(s, d, "events")
    return e.groupBy(F.concat(F.lit("d"), F.col("user_id") % 3).alias("dataset"), F.col("event_type").alias("format"), F.expr("shiftleft(1, CAST(day(ts) % 5 AS INT))").alias("degree")).agg(F.count("*").cast("double").alias("seconds"), F.round(F.sum("value"), 6).alias("joules"), F.max("value").alias("bits"))


add("scaling", lambda s, d: rounded(reports.scaling(pseudo_runs(s, d)), "speedup", "energy_ratio", "efficiency", digits=6), f"SELECT dataset, format, degree, round(first_value(seconds) OVER w / seconds, 6) AS speedup, round(first_value(joules) OVER w / joules, 6) AS energy_ratio, round(first_value(seconds) OVER w / seconds / degree, 6) AS efficiency FROM {_RUNS_SQL} WINDOW w AS (PARTITION BY dataset, format ORDER BY degree)")
add("optimal_degree", lambda s, d: reports.optimal_degree(pseudo_runs(s, d)), f"SELECT dataset, format, t AS p_time, e AS p_energy, t - e AS gap FROM (SELECT dataset, format, arg_min(degree, (seconds, degree)) AS t, arg_min(degree, (joules, degree)) AS e FROM {_RUNS_SQL} GROUP BY 1, 2)")
add("pareto_front", lambda s, d: reports.pareto(pseudo_runs(s, d)).select("dataset", "format", "degree", "seconds", "joules"), f"WITH r AS {_RUNS_SQL} SELECT dataset, format, degree, seconds, joules FROM r a WHERE NOT EXISTS (SELECT 1 FROM r b WHERE b.dataset = a.dataset AND b.seconds <= a.seconds AND b.joules <= a.joules AND (b.seconds < a.seconds OR b.joules < a.joules))")
add("choose_config", lambda s, d: reports.choose_config(pseudo_runs(s, d), max_joules=1e9, max_bits=1e9), f"SELECT dataset, b.format AS format, b.degree AS degree, b.seconds AS seconds, b.joules AS joules FROM (SELECT dataset, min({{'seconds': seconds, 'format': format, 'degree': degree, 'joules': joules}}) AS b FROM {_RUNS_SQL} GROUP BY 1)")
add("metric_energy_correlation", lambda s, d: rounded(reports.metric_energy_correlation(pseudo_runs(s, d)), "r", "slope", "r2", digits=6), f"SELECT format, round(corr(seconds, joules), 6) AS r, round(regr_slope(joules, seconds), 6) AS slope, round(regr_r2(joules, seconds), 6) AS r2 FROM {_RUNS_SQL} GROUP BY 1")
add("rank_formats", lambda s, d: reports.rank_formats(pseudo_runs(s, d)), f"SELECT dataset, format, seconds, (rank() OVER (PARTITION BY dataset ORDER BY seconds))::INT AS place FROM (SELECT dataset, format, min(seconds) AS seconds FROM {_RUNS_SQL} GROUP BY 1, 2)")
add("space_inflation", lambda s, d: rounded(reports.space_inflation(pseudo_runs(s, d)).select("dataset", "format", "degree", "inflation"), "inflation"), f"SELECT dataset, format, degree, round(bits / first_value(bits) OVER (PARTITION BY dataset, format ORDER BY degree), 9) AS inflation FROM {_RUNS_SQL}")
add("report_q2", lambda s, d: rounded(reports.report_q2(pseudo_runs(s, d)), "differ", "mean_gap"), f"SELECT format, round(avg((t <> e)::INT), 9) AS differ, round(avg(t - e), 9) AS mean_gap FROM (SELECT dataset, format, arg_min(degree, (seconds, degree)) AS t, arg_min(degree, (joules, degree)) AS e FROM {_RUNS_SQL} GROUP BY 1, 2) GROUP BY 1")

add("report_q1", lambda s, d: rounded(reports.report_q1(pseudo_runs(s, d), "click"), "time_ratio", "energy_ratio", "space_ratio"), f"WITH b AS (SELECT dataset, format, min(seconds) AS s, min(joules) AS j, min(bits) AS b FROM {_RUNS_SQL} GROUP BY 1, 2) SELECT x.dataset, x.format, round(x.s / y.s, 9) AS time_ratio, round(x.j / y.j, 9) AS energy_ratio, round(x.b / y.b, 9) AS space_ratio FROM b x LEFT JOIN b y ON x.dataset = y.dataset AND y.format = 'click'")
add("report_q3", lambda s, d: rounded(reports.report_q3(pseudo_runs(s, d).withColumn("counters", F.create_map(F.lit("seconds"), "seconds", F.lit("bits"), "bits", F.lit("other"), "joules")), ("seconds", "bits")), "r", digits=6), f"SELECT format, counter, round(corr(n, joules), 6) AS r FROM (SELECT format, joules, unnest(['seconds', 'bits']) AS counter, unnest([seconds, bits]) AS n FROM {_RUNS_SQL}) GROUP BY 1, 2")

# Reports on records derived from orders: the sweep's own records (RUNS.json) are no table ------------------------------
_ORDER_RUNS_SQL = "(SELECT o_orderstatus AS dataset, o_orderpriority AS format, (1 << (month(o_orderdate) % 5)::INT)::INT AS degree, count(*)::DOUBLE AS seconds, sum(round(o_totalprice * 100)::BIGINT)::DOUBLE AS joules, max(o_totalprice) AS bits, count(DISTINCT o_custkey)::DOUBLE AS touched FROM orders GROUP BY 1, 2, 3)"


def order_runs(s: SparkSession, d: str) -> DataFrame:
    """Run records made from orders by rule: no measurements."""
    o = load(s, d, "orders", ["o_orderstatus", "o_orderpriority", "o_orderdate", "o_totalprice", "o_custkey"])
    keys = F.col("o_orderstatus").alias("dataset"), F.col("o_orderpriority").alias("format"), F.expr("shiftleft(1, CAST(month(o_orderdate) % 5 AS INT))").alias("degree")
    return o.groupBy(*keys).agg(F.count("*").cast("double").alias("seconds"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).cast("double").alias("joules"), F.max("o_totalprice").alias("bits"), F.count_distinct("o_custkey").cast("double").alias("touched"))


for _name, _report in (
    ("scaling", lambda r: rounded(reports.scaling(r), "speedup", "energy_ratio", "efficiency", digits=6)), ("optimal_degree", reports.optimal_degree), ("rank_formats", reports.rank_formats),
    ("report_q1", lambda r: rounded(reports.report_q1(r, "5-LOW"), "time_ratio", "energy_ratio", "space_ratio")), ("report_q2", lambda r: rounded(reports.report_q2(r), "differ", "mean_gap")),
    ("space_inflation", lambda r: rounded(reports.space_inflation(r).select("dataset", "format", "degree", "inflation"), "inflation")),
):
    add(f"runs_{_name}", lambda s, d, report=_report: report(order_runs(s, d)), ORACLES[_name].replace(_RUNS_SQL, _ORDER_RUNS_SQL).replace("'click'", "'5-LOW'"))
add("runs_time_against_work", lambda s, d: rounded(reports.report_q3(order_runs(s, d).select("format", F.col("seconds").alias("joules"), F.create_map(F.lit("touched"), "touched").alias("counters")), ("touched",)).withColumnRenamed("r", "r_seconds"), "r_seconds", digits=6), f"SELECT format, 'touched' AS counter, round(corr(touched, seconds), 6) AS r_seconds FROM {_ORDER_RUNS_SQL} GROUP BY 1")


def _prepared(s: SparkSession, d: str) -> DataFrame:
    """Extracts, transposes and stores F7 in three formats, then counts what is read back."""
    paths = prepare(s, d, "F7", ("csr", "quadbits", "pg_packed"), 2, f"{shared_dir(s)}/boolmat-prepared-{uuid.uuid4().hex}")
    counts = [decode(read_matrix(s, p)).agg(F.count("*").alias("ones"), F.sum("row").alias("sum_rows")).select(F.lit(f).alias("format"), "ones", "sum_rows") for f, p in paths.items() if f != "outdegree"]
    return reduce(DataFrame.unionAll, counts)


add("prepare", _prepared, f"WITH {edges_cte('F7')} SELECT unnest(['csr', 'quadbits', 'pg_packed']) AS format, count(*) AS ones, sum(v)::BIGINT AS sum_rows FROM e")

# Streams ------------------------------------------------------------------------------------------------------------
_ev = lambda s, d: power.stream_events(s, f"{d}/events.parquet")
add("stream_tumbling_power", lambda s, d: rounded(power.run_available(power.stream_power(_ev(s, d), "tumbling"), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "total"), "total", digits=6), "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY 1")
add("stream_sliding_power", lambda s, d: rounded(power.run_available(power.stream_power(_ev(s, d), "sliding", "1 day", "12 hours"), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "total"), "total", digits=6), "SELECT start, count(*) AS n, round(sum(value), 6) AS total FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR]) AS start, value FROM events) GROUP BY 1")
add("stream_session", lambda s, d: rounded(power.run_available(power.stream_power(_ev(s, d), "session"), "complete").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n", "total"), "total", digits=6), "SELECT user_id, min(ts) AS start, count(*) AS n, round(sum(value), 6) AS total FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, (coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE, true))::INT AS fresh FROM events)) GROUP BY user_id, s")
add("stream_energy", lambda s, d: rounded(power.run_updates(power.stream_energy(_ev(s, d), 5.0), "device"), "joules", digits=1), f"SELECT device, round(coalesce(sum((epoch_us(t2) - epoch_us(ts)) / 1000000.0::DOUBLE * (amps + a2) / 2 * 5.0), 0.0), 1) AS joules FROM (SELECT *, lead(ts) OVER w AS t2, lead(amps) OVER w AS a2 FROM {_DEVICES} WINDOW w AS (PARTITION BY device ORDER BY ts, amps)) GROUP BY 1")
add("stream_dedup", lambda s, d: power.run_available(power.stream_dedup(_ev(s, d)).select("event_id")), "SELECT DISTINCT event_id FROM events")
add("stream_enrich", lambda s, d: power.run_available(power.stream_enrich(_ev(s, d), load(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey"), "user_id").select("event_id", "c_nationkey")), "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey")
add("stream_pair", lambda s, d: power.run_available(power.stream_pair(_ev(s, d).where("event_type = 'click'"), _ev(s, d).where("event_type = 'purchase'"), "user_id")).select("k", F.col("start_ts").cast("timestamp_ntz").alias("start_ts"), F.col("stop_ts").cast("timestamp_ntz").alias("stop_ts")), "SELECT a.user_id AS k, a.ts AS start_ts, b.ts AS stop_ts FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")


def _delta(s: SparkSession, d: str) -> DataFrame:
    m = graphs.matrix(s, d, "F3")
    old = BoolMatrix(m.df.where("(row + col) % 5 <> 0").unionAll(s.range(1).select(F.col("id").alias("row"), F.col("id").alias("col"))), m.n_rows, m.n_cols)
    live = power.DeltaMatrix(old, "quadbits", 2)
    live.apply(m.df.where("(row + col) % 5 = 0"), s.range(1).select(F.col("id").alias("row"), F.col("id").alias("col")))
    return live.product(v1(m.n_cols, s))


add("stream_edge_delta_spmv", _delta, f"WITH {edges_cte('F3')} SELECT i AS id, coalesce(sum({_X('v')}), 0)::DOUBLE AS value FROM range({_SIZE['F3']}) r(i) LEFT JOIN e ON u = i GROUP BY 1")

# Operators around ---------------------------------------------------------------------------------------------------
_net = "l_extendedprice * (1 - l_discount)"
add("scan_pruned", lambda s, d: load(s, d, "lineitem", ["l_orderkey", "l_shipdate"], F.col("l_shipdate") > F.lit("1998-01-01").cast("timestamp_ntz")), "SELECT l_orderkey, l_shipdate FROM lineitem WHERE l_shipdate > TIMESTAMP '1998-01-01'")
add("project_net", lambda s, d: rounded(rel.project(load(s, d, "lineitem"), l_orderkey=F.col("l_orderkey"), l_linenumber=F.col("l_linenumber"), net=F.expr(_net)), "net", digits=4), "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
add("restrict_orders", lambda s, d: rel.restrict(load(s, d, "orders"), (F.col("o_orderstatus") == "F") | F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F' OR o_orderpriority IN ('1-URGENT', '2-HIGH')")
_LO = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
for _k, _j in (("hash", rel.join_hash), ("merge", rel.join_merge)):
    add(f"join_{_k}", lambda s, d, j=_j: j(load(s, d, "lineitem", ["l_orderkey", "l_partkey"]), load(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey").select("o_custkey", "l_partkey").distinct(), f"SELECT DISTINCT o_custkey, l_partkey {_LO}")
add("join_broadcast", lambda s, d: rel.join_broadcast(load(s, d, "customer"), load(s, d, "nation").withColumnRenamed("n_nationkey", "c_nationkey"), "c_nationkey").groupBy("n_name").agg(F.count("*").alias("n")), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
add("join_full", lambda s, d: rel.join_outer(load(s, d, "customer").select(F.col("c_custkey").alias("k")).where("k % 2 = 0").withColumn("a", F.lit(1)), load(s, d, "customer").select(F.col("c_custkey").alias("k")).where("k % 3 = 0").withColumn("b", F.lit(1)), "k"), "SELECT coalesce(x.k, y.k) AS k, a, b FROM (SELECT c_custkey AS k, 1 AS a FROM customer WHERE c_custkey % 2 = 0) x FULL JOIN (SELECT c_custkey AS k, 1 AS b FROM customer WHERE c_custkey % 3 = 0) y ON x.k = y.k")
for _side in ("left", "right"):
    add(f"join_{_side}", lambda s, d, side=_side: rel.join_outer(load(s, d, "customer").select(F.col("c_custkey").alias("k")), load(s, d, "orders").groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").alias("n")), "k", side), f"SELECT {'c' if _side == 'left' else 'o'}.k AS k, n FROM (SELECT c_custkey AS k FROM customer) c {_side.upper()} JOIN (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1) o ON c.k = o.k")
add("join_semi", lambda s, d: rel.join_semi(load(s, d, "customer").select("c_custkey"), load(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
add("join_anti", lambda s, d: rel.join_anti(load(s, d, "orders").select("o_orderkey"), load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
add("join_theta", lambda s, d: rel.join_theta(load(s, d, "supplier").select("s_suppkey", "s_acctbal"), load(s, d, "nation").select((F.col("n_nationkey") * 400.0).alias("floor"), "n_name"), F.col("s_acctbal") >= F.col("floor")).groupBy("s_suppkey").agg(F.count("*").alias("n")), "SELECT s_suppkey, count(*) AS n FROM supplier JOIN nation ON s_acctbal >= n_nationkey * 400.0 GROUP BY 1")
add("with_scalar", lambda s, d: rounded(rel.with_scalar(load(s, d, "supplier").select("s_suppkey", "s_acctbal"), load(s, d, "supplier").agg(F.sum("s_acctbal").alias("all"))).select("s_suppkey", (F.col("s_acctbal") / F.col("all")).alias("share")), "share"), "SELECT s_suppkey, round(s_acctbal / (SELECT sum(s_acctbal) FROM supplier), 9) AS share FROM supplier")
add("lines_per_order", lambda s, d: rel.aggregate(load(s, d, "lineitem"), ["l_orderkey"], lines=F.count("*"), qty=F.sum("l_quantity")), "SELECT l_orderkey, count(*) AS lines, sum(l_quantity) AS qty FROM lineitem GROUP BY 1")
add("tokens", lambda s, d: graphs.tokens(load(s, d, "documents")).groupBy("doc_id").agg(F.count("*").alias("n")), r"SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+'))) AS token FROM documents) GROUP BY 1")
add("count_unique", lambda s, d: rel.count_unique(load(s, d, "lineitem"), "l_orderkey", "l_partkey"), "SELECT l_orderkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
add("approx_unique", lambda s, d: rel.approx_unique(load(s, d, "lineitem"), "l_partkey"))
add("quantiles", lambda s, d: rounded(rel.quantiles(load(s, d, "lineitem"), "l_extendedprice", [0.25, 0.5, 0.9]), "q25", "q50", "q90", digits=4), "SELECT round(quantile_cont(l_extendedprice, 0.25), 4) AS q25, round(quantile_cont(l_extendedprice, 0.5), 4) AS q50, round(quantile_cont(l_extendedprice, 0.9), 4) AS q90 FROM lineitem")
add("correlate", lambda s, d: rounded(rel.correlate(load(s, d, "lineitem"), "l_quantity", "l_extendedprice"), "r", "slope", "r2", "sd", digits=5), "SELECT round(corr(l_quantity, l_extendedprice), 5) AS r, round(regr_slope(l_extendedprice, l_quantity), 5) AS slope, round(regr_r2(l_extendedprice, l_quantity), 5) AS r2, round(stddev_samp(l_quantity), 5) AS sd FROM lineitem")
add("arg_best", lambda s, d: rel.arg_best(load(s, d, "orders").withColumn("by", F.struct("o_totalprice", "o_orderkey")), ["o_custkey"], "o_orderkey", "by"), "SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS best FROM orders GROUP BY 1")
add("mask_union", lambda s, d: rel.mask_union(load(s, d, "lineitem"), "l_orderkey", F.expr("shiftleft(1, CAST(l_partkey & 3 AS INT))")), "SELECT l_orderkey, bit_or((1 << (l_partkey & 3)::INT)::INT) AS mask FROM lineitem GROUP BY 1")
_EV = "(SELECT event_type, user_id % 3 AS grp, value FROM events)"
_ev2 = lambda s, d: load(s, d, "events").select("event_type", (F.col("user_id") % 3).alias("grp"), "value")
_aggs = lambda: {"n": F.count("*")}
add("grouping_sets", lambda s, d: rel.grouping_sets(_ev2(s, d), [["event_type"], ["grp"]], _aggs()), f"SELECT event_type, grp, count(*) AS n FROM {_EV} GROUP BY GROUPING SETS ((event_type), (grp))")
for _kind in ("rollup", "cube"):
    add(_kind, lambda s, d, k=_kind: rel.cube_report(_ev2(s, d), ["event_type", "grp"], _aggs(), k), f"SELECT event_type, grp, count(*) AS n FROM {_EV} GROUP BY {_kind.upper()} (event_type, grp)")
add("pivot", lambda s, d: rel.space_pivot(_ev2(s, d).groupBy("event_type", "grp").count(), "event_type", "grp", "count", [0, 1, 2]).toDF("event_type", "g0", "g1", "g2"), f"SELECT event_type, nullif(count(*) FILTER (grp = 0), 0) AS g0, nullif(count(*) FILTER (grp = 1), 0) AS g1, nullif(count(*) FILTER (grp = 2), 0) AS g2 FROM {_EV} GROUP BY 1")
add("unpivot", lambda s, d: rel.melt(load(s, d, "supplier").select("s_suppkey", F.col("s_acctbal").alias("bal"), F.col("s_nationkey").cast("double").alias("nat")), ["s_suppkey"], ["bal", "nat"]), "SELECT s_suppkey, 'bal' AS name, s_acctbal AS value FROM supplier UNION ALL SELECT s_suppkey, 'nat', s_nationkey::DOUBLE FROM supplier")
add("dense_rank_values", lambda s, d: graphs.order_part_qty(s, d).groupBy("val").agg(F.count("*").alias("n")).withColumn("idx", F.dense_rank().over(Window.orderBy("val"))), f"WITH {edges_cte('F5')} SELECT val, count(*) AS n, (dense_rank() OVER (ORDER BY val))::INT AS idx FROM e GROUP BY val")
add("ntile_blocks", lambda s, d: rel.bucketize(load(s, d, "supplier"), [F.col("s_suppkey")], 4, ["s_nationkey"]).select("s_suppkey", "tile"), "SELECT s_suppkey, (ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey))::INT AS tile FROM supplier")
add("ranked_parts", lambda s, d: rel.ranked(load(s, d, "part"), ["p_brand"], [F.desc("p_size")], "rank").select("p_partkey", "rank"), "SELECT p_partkey, (rank() OVER (PARTITION BY p_brand ORDER BY p_size DESC))::INT AS rank FROM part")
add("successor", lambda s, d: rel.successor(load(s, d, "orders"), ["o_custkey"], [F.col("o_orderdate"), F.col("o_orderkey")], "o_orderkey").select("o_orderkey", "next"), "SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS next FROM orders")
add("baseline_of", lambda s, d: rel.baseline_of(load(s, d, "orders"), ["o_custkey"], [F.col("o_orderdate"), F.col("o_orderkey")], "o_totalprice").select("o_orderkey", "base"), "SELECT o_orderkey, first_value(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS base FROM orders")
add("running_nnz", lambda s, d: rel.running(load(s, d, "lineitem").groupBy("l_suppkey", "l_returnflag").agg(F.count("*").alias("n")), ["l_returnflag"], [F.col("l_suppkey")], "n").select("l_suppkey", "l_returnflag", "running"), "SELECT l_suppkey, l_returnflag, (sum(n) OVER (PARTITION BY l_returnflag ORDER BY l_suppkey ROWS UNBOUNDED PRECEDING))::BIGINT AS running FROM (SELECT l_suppkey, l_returnflag, count(*) AS n FROM lineitem GROUP BY 1, 2)")
add("top_k", lambda s, d: rel.top(load(s, d, "orders"), [F.desc("o_totalprice"), F.col("o_orderkey")], 10, 5).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
add("top_per_group", lambda s, d: rel.top_per(load(s, d, "part"), "p_brand", [F.desc("p_retailprice"), F.col("p_partkey")], 3).select("p_brand", "p_partkey", "rank"), "SELECT p_brand, p_partkey, rank FROM (SELECT p_brand, p_partkey, (row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey))::INT AS rank FROM part) WHERE rank <= 3")
_k = lambda s, d, m: load(s, d, "customer").where(f"c_custkey % {m} = 0").select("c_nationkey")
for _op, _all in (("union", True), ("union", False), ("intersect", True), ("intersect", False), ("except", True), ("except", False)):
    add(f"{_op}{'_all' if _all else ''}", lambda s, d, o=_op, a=_all: rel.set_op(_k(s, d, 2), _k(s, d, 3), o, a), f"SELECT c_nationkey FROM customer WHERE c_custkey % 2 = 0 {_op.upper()} {'ALL' if _all else ''} SELECT c_nationkey FROM customer WHERE c_custkey % 3 = 0")


def _with_transpose(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    cells = graphs.matrix(s, d, "F2").df
    return cells, cells.select(F.col("col").alias("row"), F.col("row").alias("col"))


for _op, _all in (("union", True), ("union", False), ("intersect", True), ("intersect", False), ("except", True), ("except", False)):
    add(f"{_op}{'_all' if _all else ''}_edges", lambda s, d, o=_op, a=_all: rel.set_op(*_with_transpose(s, d), o, a), f"WITH {edges_cte('F2')} SELECT u AS row, v AS col FROM e {_op.upper()} {'ALL' if _all else ''} SELECT v, u FROM e")


def _both_products(s: SparkSession, d: str) -> DataFrame:
    """The right and the left product of F6 side by side: rows without a one and columns without a one meet nothing."""
    m = graphs.matrix(s, d, "F6")
    x = v1(m.n_rows, s)
    return rel.join_outer(plans.spmv_edges(m, x).withColumnRenamed("value", "a"), plans.spmv_left_edges(m, x).withColumnRenamed("value", "b"), "id")


add("join_full_vectors", _both_products, f"WITH {edges_cte('F6')}, x AS (SELECT u::BIGINT AS id, sum({_X('v')}) AS a FROM e GROUP BY 1), y AS (SELECT v::BIGINT AS id, sum({_X('u')}) AS b FROM e GROUP BY 1) SELECT coalesce(x.id, y.id) AS id, a, b FROM x FULL JOIN y ON x.id = y.id")
add("sample_rows", lambda s, d: rel.sample_rows(load(s, d, "lineitem"), 0.1).select("l_orderkey"))
add("url_functions", lambda s, d: load(s, d, "pages").select("page_id", reverse_host(F.col("url")).alias("rev"), url_path(F.col("url")).alias("path")), "SELECT page_id, array_to_string(list_reverse(string_split(regexp_extract(url, '^(?:[a-z]+://)?([^/?#]*)', 1), '.')), '.') AS rev, regexp_extract(url, '^(?:[a-z]+://)?[^/?#]*([^?#]*)', 1) AS path FROM pages")
add("date_functions", lambda s, d: load(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n")), "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n FROM orders GROUP BY 1")
add("json_props", lambda s, d: rel.prop(load(s, d, "events"), "k").select("event_id", "k"), "SELECT event_id, (props->>'$.k')::INT AS k FROM events")
add("array_diff", lambda s, d: load(s, d, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_set("l_partkey")).alias("a"), F.sort_array(F.collect_set("l_suppkey")).alias("b")).select("l_orderkey", F.size(list_diff(F.col("a"), F.col("b"))["added"]).alias("added"), F.size(runs(F.col("b"))).alias("stretches"), F.aggregate(gaps(F.col("a")), F.lit(0).cast("bigint"), lambda x, y: x + y).alias("last")), "SELECT l_orderkey, len(list_filter(a, lambda x: NOT list_contains(b, x)))::INT AS added, len(list_filter(b, lambda x: NOT list_contains(b, x - 1)))::INT AS stretches, list_max(a) AS last FROM (SELECT l_orderkey, list(DISTINCT l_partkey) AS a, list(DISTINCT l_suppkey) AS b FROM lineitem GROUP BY 1)")
add("map_merge", lambda s, d: load(s, d, "supplier").select("s_suppkey", merge_metrics(F.create_map(F.lit("a"), F.col("s_suppkey")), F.create_map(F.lit("a"), F.lit(1).cast("bigint"), F.lit("b"), F.lit(2).cast("bigint"))).alias("m")).select("s_suppkey", F.col("m")["a"].alias("a"), F.col("m")["b"].alias("b")), "SELECT s_suppkey, s_suppkey + 1 AS a, 2::BIGINT AS b FROM supplier")
add("width_bits", lambda s, d: load(s, d, "part").select("p_partkey", width_bits(F.greatest("p_size", F.lit(1))).alias("w")), "SELECT p_partkey, (floor(log2(greatest(p_size, 1))) + 1)::INT AS w FROM part")


def _udtf(s: SparkSession, d: str) -> DataFrame:
    register_functions(s)
    m = graphs.matrix(s, d, "F6")
    encode(m, "quadbits", 1).df.createOrReplaceTempView("boolmat_tiles")
    return s.sql("SELECT c.row, c.col FROM boolmat_tiles t, LATERAL quad_leaves(t.parts, CAST(t.row_hi - t.row_lo AS INT), CAST(t.n_cols AS INT)) c").agg(F.count("*").alias("n"))


add("udtf_expand", _udtf, f"WITH {edges_cte('F6')} SELECT count(*) AS n FROM e")


def flagship(s: SparkSession, d: str) -> DataFrame:
    """Ten PageRank steps on the pair-grammar form of the transposed co-purchase matrix: the 20 best vertices."""
    ranks = pr.pagerank(graphs.matrix(s, d, "F2"), iterations=10, fmt="pg_w32", blocks=4, mode="batched").ranks
    return rel.top(ranks, [F.desc("value"), F.col("id")], 20)
