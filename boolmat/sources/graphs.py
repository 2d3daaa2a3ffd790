"""The matrices F1-F11 of FIXTURES.md on the given tables, and their DuckDB twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import BoolMatrix
from .generator import copy_model_graph
from .tables import assign_ids, load, reverse_host, stored, url_path

LINK = r'href="(/[^"]*)"'
TOKEN = r"\p{L}+"


def succession(spark: SparkSession, sf: str) -> DataFrame:
    lines = load(spark, sf, "lineitem", ["l_orderkey", "l_partkey", "l_linenumber"]).join(load(spark, sf, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]), F.col("l_orderkey") == F.col("o_orderkey"))
    w = Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey", "l_linenumber")
    return lines.select(F.col("o_custkey").alias("u"), F.lead("o_custkey").over(w).alias("v")).where("v IS NOT NULL AND u <> v").distinct()


def copurchase(spark: SparkSession, sf: str) -> DataFrame:
    a = load(spark, sf, "lineitem", ["l_orderkey", "l_partkey"]).distinct()
    b = a.select("l_orderkey", F.col("l_partkey").alias("v"))
    return a.join(b, "l_orderkey").where("l_partkey <> v").select(F.col("l_partkey").alias("u"), "v").distinct()


def user_next(spark: SparkSession, sf: str) -> DataFrame:
    """Successor over the whole event order: hour buckets carry their last user over, so no window spans the table."""
    e = load(spark, sf, "events", ["event_id", "ts", "user_id"]).withColumn("hour", F.date_trunc("hour", "ts"))
    inside = e.select("hour", F.col("user_id").alias("u"), F.lead("user_id").over(Window.partitionBy("hour").orderBy("ts", "event_id")).alias("v"))
    ends = e.groupBy("hour").agg(F.max(F.struct("ts", "event_id", "user_id"))["user_id"].alias("last"), F.min(F.struct("ts", "event_id", "user_id"))["user_id"].alias("first"))
    across = ends.select(F.col("last").alias("u"), F.lead("first").over(Window.orderBy("hour")).alias("v"))  # one row per hour
    return inside.select("u", "v").unionAll(across).where("v IS NOT NULL AND u <> v").distinct()


def order_part(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem", ["l_orderkey", "l_partkey"]).select(F.col("l_orderkey").alias("u"), F.col("l_partkey").alias("v")).distinct()


def order_part_qty(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("u"), F.col("l_partkey").alias("v")).agg(F.sum("l_quantity").alias("val"))


def cust_part(spark: SparkSession, sf: str) -> DataFrame:
    o = load(spark, sf, "orders", ["o_orderkey", "o_custkey"])
    return load(spark, sf, "lineitem", ["l_orderkey", "l_partkey"]).join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("u"), F.col("l_partkey").alias("v")).distinct()


def _host(url):
    return F.regexp_extract(url, "^(?:[a-z]+://)?([^/?#]*)", 1)


def explode_links(pages: DataFrame) -> DataFrame:
    """(page_id, src, dst): node of the page and node of each of its relative links (host and path)."""
    return pages.select("page_id", F.concat(_host(F.col("url")), url_path(F.col("url"))).alias("src"), _host(F.col("url")).alias("host"), F.explode(F.regexp_extract_all("html", F.lit(LINK), 1)).alias("path")).select("page_id", "src", F.concat("host", "path").alias("dst"), "path")


def weblink_named(spark: SparkSession, sf: str) -> DataFrame:
    return explode_links(load(spark, sf, "pages")).where("src <> dst").select("src", "dst").distinct()


def weblink(spark: SparkSession, sf: str) -> DataFrame:
    named = weblink_named(spark, sf)
    pages = load(spark, sf, "pages").select(F.concat(_host(F.col("url")), url_path(F.col("url"))).alias("node"))
    links = explode_links(load(spark, sf, "pages"))
    ids = assign_ids(pages.unionAll(links.select("dst")), "node", "revurl")
    return named.join(ids.select(F.col("key").alias("src"), F.col("id").alias("u")), "src").join(ids.select(F.col("key").alias("dst"), F.col("id").alias("v")), "dst").select("u", "v")


def page_href(spark: SparkSession, sf: str) -> DataFrame:
    links = explode_links(load(spark, sf, "pages")).select("page_id", "path").distinct()
    ids = assign_ids(links, "path")
    return links.join(ids.withColumnRenamed("key", "path"), "path").select(F.col("page_id").alias("u"), F.col("id").alias("v"))


def tokens(documents: DataFrame) -> DataFrame:
    return documents.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(TOKEN), 0))).alias("token"))


def doc_token(spark: SparkSession, sf: str) -> DataFrame:
    t = tokens(load(spark, sf, "documents", ["doc_id", "text"]))
    ids = assign_ids(t, "token")
    return t.join(ids.withColumnRenamed("key", "token"), "token").select(F.col("doc_id").alias("u"), F.col("id").alias("v")).distinct()


def ternary(spark: SparkSession, sf: str, sign: int, threshold: float = 0.075) -> DataFrame:
    cells = load(spark, sf, "embeddings").select(F.col("vec_id").alias("u"), F.posexplode("embedding").alias("v", "c"))
    return cells.where(F.col("c") > threshold if sign > 0 else F.col("c") < -threshold).select("u", F.col("v").cast("bigint").alias("v"))


def copymodel(spark: SparkSession, sf: str) -> DataFrame:
    """A copying graph over the parts: a row per part, whose draws are seeded by the part's name, brand and type."""
    parts = load(spark, sf, "part").select(F.col("p_partkey").alias("id"), F.xxhash64("p_partkey", "p_name", "p_brand", "p_type").alias("seed"))
    return copy_model_graph(spark, (parts.agg(F.max("id")).first()[0] or 0) + 1, vertices=parts)


GRAPHS = {"F1": succession, "F2": copurchase, "F3": user_next, "F4": order_part, "F5": order_part_qty, "F6": weblink, "F7": page_href, "F8": doc_token, "F9": lambda s, d: ternary(s, d, 1), "F10": copymodel, "F11": cust_part}


def matrix(spark: SparkSession, sf: str, name: str, square: bool = False) -> BoolMatrix:
    """F-matrix by name; its shape comes from one aggregate over the edges, or from the table that names its vertices.

    The edges are stored: what makes them (joins, windows, numbered names) runs once, not for every pass over the matrix.
    """
    edges = stored(GRAPHS[name](spark, sf), f"edges-{name}")
    *top, nnz = edges.agg(F.max("u"), F.max("v"), F.count("*")).first()
    n_rows, n_cols = ((x if x is not None else -1) + 1 for x in top)
    table = {"F1": ("customer", "c_custkey"), "F2": ("part", "p_partkey")}.get(name)
    if table:
        n_rows = n_cols = max(n_rows, n_cols, (load(spark, sf, table[0]).agg(F.max(table[1])).first()[0] or 0) + 1)
    if name == "F4" or name == "F5":
        n_rows = max(n_rows, (load(spark, sf, "orders").agg(F.max("o_orderkey")).first()[0] or 0) + 1)
    if square or name in ("F3", "F6"):
        n_rows = n_cols = max(n_rows, n_cols)
    return BoolMatrix(edges.select(F.col("u").cast("bigint").alias("row"), F.col("v").cast("bigint").alias("col"), *(["val"] if "val" in edges.columns else [])), n_rows, n_cols, nnz)


_SQL_LINKS = """SELECT page_id, regexp_extract(url, '^(?:[a-z]+://)?([^/?#]*)', 1) AS host, regexp_extract(url, '^(?:[a-z]+://)?[^/?#]*([^?#]*)', 1) AS own, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages"""
SQL = {
    "F1": "SELECT DISTINCT u, v FROM (SELECT o_custkey AS u, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey, l_linenumber) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey) WHERE v IS NOT NULL AND u <> v",
    "F2": "SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey",
    "F3": "SELECT DISTINCT u, v FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL AND u <> v",
    "F4": "SELECT DISTINCT l_orderkey AS u, l_partkey AS v FROM lineitem",
    "F5": "SELECT l_orderkey AS u, l_partkey AS v, sum(l_quantity) AS val FROM lineitem GROUP BY 1, 2",
    "F6": f"""SELECT DISTINCT s.id AS u, d.id AS v FROM (SELECT host || own AS src, host || path AS dst FROM ({_SQL_LINKS})) l
        JOIN web_ids s ON s.node = src JOIN web_ids d ON d.node = dst WHERE src <> dst""",
    "F7": f"SELECT DISTINCT page_id AS u, dense_rank() OVER (ORDER BY path) - 1 AS v FROM ({_SQL_LINKS})",
    "F8": r"SELECT DISTINCT doc_id AS u, dense_rank() OVER (ORDER BY token) - 1 AS v FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+'))) AS token FROM documents)",
    "F9": "SELECT vec_id AS u, (i - 1)::BIGINT AS v FROM (SELECT vec_id, unnest(embedding) AS c, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE c > 0.075::DOUBLE",
    "F9m": "SELECT vec_id AS u, (i - 1)::BIGINT AS v FROM (SELECT vec_id, unnest(embedding) AS c, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE c < -0.075::DOUBLE",
    "F11": "SELECT DISTINCT o_custkey AS u, l_partkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
}
_WEB_IDS = f"""web_ids AS (SELECT node, row_number() OVER (ORDER BY array_to_string(list_reverse(string_split(regexp_extract(node, '^([^/?#]*)', 1), '.')), '.'), node) - 1 AS id FROM (
    SELECT host || path AS node FROM ({_SQL_LINKS}) UNION SELECT regexp_extract(url, '^(?:[a-z]+://)?([^/?#]*)', 1) || regexp_extract(url, '^(?:[a-z]+://)?[^/?#]*([^?#]*)', 1) FROM pages))"""


def edges_cte(name: str) -> str:
    """CTE list that defines e(u, v[, val]) for an F-matrix."""
    return (f"{_WEB_IDS}, " if name == "F6" else "") + f"e AS MATERIALIZED ({SQL[name]})"
