"""PageRank by power iteration on a stored matrix, and other iterations of the same kind.

The random-walk matrix is never built: the ranks are divided by the out-degrees before the product. Rows without ones
are replaced by 1/n implicitly: their total rank is one number that joins the plan as a one-row table.
new = alpha * teleport + (1 - alpha) * (A' (rank / degree) + dangling / n)
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import BoolMatrix, CompressedMatrix, encode
from ..plans.spmv import spmv, spmv_edges, spmv_left
from ..sources.tables import remove_table, stored


@dataclass
class RankResult:
    """ranks (id, value); history (t, delta, mass, dangling), one row per step."""

    ranks: DataFrame
    history: DataFrame


def outdegrees(matrix: BoolMatrix) -> DataFrame:
    """(id, degree) of every vertex, 0 included."""
    spark = matrix.df.sparkSession
    counted = matrix.df.groupBy(F.col("row").alias("id")).agg(F.count("*").alias("degree"))
    return spark.range(matrix.n_rows).join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("bigint").alias("degree"))


def random_walk_matrix(matrix: BoolMatrix) -> DataFrame:
    """(row, col, val): each one divided by its row's sum. Only for inspection; products scale the vector instead."""
    deg = matrix.df.groupBy("row").agg(F.count("*").alias("d"))
    return matrix.df.join(deg, "row").select("row", "col", (1 / F.col("d")).alias("val"))


def product_of(matrix: BoolMatrix, fmt: str, side: str = "right", blocks: int | None = None, **opts) -> Callable[[DataFrame], DataFrame]:
    """x -> A' x as a function: from the transposed matrix (side='right') or from the matrix itself (side='left')."""
    if fmt == "edgelist" and not blocks:
        held = matrix.transpose()
        held = BoolMatrix(stored(held.df.repartition("col"), "edges"), held.n_rows, held.n_cols)
        return lambda x: spmv_edges(held, x)
    cm = encode(matrix.transpose() if side == "right" else matrix, fmt, blocks, **opts)
    cm = cm.held(stored(cm.df, "tiles"))
    return (lambda x: spmv(cm, x)) if side == "right" else (lambda x: spmv_left(cm, x))


def pagerank(matrix: BoolMatrix, *, alpha: float = 0.15, iterations: int = 100, tol: float | None = None, norm: str = "l1", check_every: int = 5, start: DataFrame | None = None, teleport: DataFrame | None = None, fmt: str = "edgelist", side: str = "right", blocks: int | None = None, keep_history: bool = True, step: Callable[[DataFrame], DataFrame] | None = None, **opts) -> RankResult:
    """Ranks after `iterations` steps, or earlier where the change falls below tol (looked at every check_every steps).

    step: a product made by product_of() before, so that encoding is not part of the iterations.
    keep_history=False leaves out the record of every step and the job that makes it. start, teleport: (id, value), scaled to sum 1; uniform by default. The limit depends on teleport, not on start.
    """
    n = matrix.n_rows
    step_of = step or product_of(matrix, fmt, side, blocks, **opts)
    base = outdegrees(matrix)

    def shares(v: DataFrame | None, name: str) -> DataFrame:
        if v is None:
            return base.select("id", F.lit(1.0 / n).alias(name))
        total = v.agg(F.sum("value").alias("total"))
        scaled = v.crossJoin(F.broadcast(total)).select("id", (F.col("value") / F.col("total")).alias(name))
        return base.select("id").join(scaled, "id", "left").select("id", F.coalesce(name, F.lit(0.0)).alias(name))

    fixed = base if teleport is None else base.join(shares(teleport, "tp"), "id")
    fixed = stored(fixed if teleport is not None else fixed.withColumn("tp", F.lit(1.0 / n)), "vertices")
    now = fixed.withColumn("value", F.lit(1.0 / n)) if start is None else fixed.join(shares(start, "value"), "id")
    history: list[DataFrame] = []
    for t in range(1, iterations + 1):
        x = now.select("id", F.when(F.col("degree") > 0, F.col("value") / F.col("degree")).otherwise(0.0).alias("value"))
        loose = now.agg(F.coalesce(F.sum(F.when(F.col("degree") == 0, F.col("value"))), F.lit(0.0)).alias("s"))
        y = step_of(x).select("id", F.col("value").alias("y"))
        joined = now.join(y, "id", "left").crossJoin(F.broadcast(loose))
        new = joined.select("id", "degree", "tp", (alpha * F.col("tp") + (1 - alpha) * (F.coalesce("y", F.lit(0.0)) + F.col("s") / n)).alias("value"), F.col("value").alias("old"), "s")
        new = stored(new, "ranks")  # a step reads its input three times, so plans must not nest
        change = F.abs(F.col("value") - F.col("old"))
        delta = {"l1": F.sum(change), "linf": F.max(change), "l2": F.sqrt(F.sum(change * change))}[norm]
        told = new.agg(delta.alias("delta"), F.sum("value").alias("mass"), F.max("s").alias("dangling")).select(F.lit(t).alias("t"), "delta", "mass", "dangling")
        # three numbers per step: kept as a table where they decide nothing, so that a step is one job; fetched to decide
        if keep_history:
            history.append(stored(told, "told"))
        if t > 1:
            remove_table(now)
        now = new.select("id", "degree", "tp", "value")
        if tol is not None and t % check_every == 0 and told.first()["delta"] < tol:
            break
    none = matrix.df.sparkSession.createDataFrame([], "t int, delta double, mass double, dangling double")
    return RankResult(now.select("id", "value"), reduce(DataFrame.unionAll, history, none))


def _normalised(v: DataFrame) -> DataFrame:
    total = v.agg(F.sqrt(F.sum(F.col("value") ** 2)).alias("total"))
    return v.crossJoin(F.broadcast(total)).select("id", F.when(F.col("total") > 0, F.col("value") / F.col("total")).otherwise(0.0).alias("value"))


def eigen_centrality(matrix: BoolMatrix, iterations: int = 10, fmt: str = "edgelist", **opts) -> DataFrame:
    """(id, value): A' x, scaled to length 1, repeated from the uniform vector; vertices without in-links end at 0."""
    step = product_of(matrix, fmt, **opts)
    v = matrix.df.sparkSession.range(matrix.n_rows).select("id", F.lit(1.0 / matrix.n_rows).alias("value"))
    for _ in range(iterations):
        v = stored(_normalised(step(v)), "vector")
    return v


def hits(matrix: BoolMatrix, iterations: int = 5) -> DataFrame:
    """(id, hub, authority): a = A' h and h = A a in turn, each scaled to length 1."""
    h = matrix.df.sparkSession.range(matrix.n_rows).select("id", F.lit(1.0).alias("value"))
    a = h
    for _ in range(iterations):
        a = stored(_normalised(spmv_edges(matrix.transpose(), h)), "vector")
        h = stored(_normalised(spmv_edges(matrix, a)), "vector")
    return matrix.df.sparkSession.range(matrix.n_rows).join(h.select("id", F.col("value").alias("hub")), "id", "left").join(a.select("id", F.col("value").alias("authority")), "id", "left").select("id", F.coalesce("hub", F.lit(0.0)).alias("hub"), F.coalesce("authority", F.lit(0.0)).alias("authority"))


def katz(matrix: BoolMatrix, beta: float = 0.001, iterations: int = 5) -> DataFrame:
    """(id, value): x = beta A' x + 1, repeated from 1."""
    ids = matrix.df.sparkSession.range(matrix.n_rows)
    x = ids.select("id", F.lit(1.0).alias("value"))
    for _ in range(iterations):
        y = spmv_edges(matrix.transpose(), x).select("id", F.col("value").alias("y"))
        x = stored(ids.join(y, "id", "left").select("id", (1.0 + beta * F.coalesce("y", F.lit(0.0))).alias("value")), "vector")
    return x


def cg_normal(cm: CompressedMatrix, b: DataFrame, iterations: int = 3) -> DataFrame:
    """(id, value): conjugate gradients for A'A x = A'b, from 0: a right and a left product per step, two dot products."""
    spark = cm.df.sparkSession
    zero = spark.range(cm.n_cols).select("id", F.lit(0.0).alias("value"))
    axpy = lambda a, u, v: u.join(v.select("id", F.col("value").alias("w")), "id", "left").select("id", (F.col("value") + a * F.coalesce("w", F.lit(0.0))).alias("value"))
    dot = lambda u, v: u.join(v.select("id", F.col("value").alias("w")), "id").agg(F.sum(F.col("value") * F.col("w"))).first()[0] or 0.0
    x = zero
    r = stored(axpy(1.0, zero, spmv_left(cm, b)), "cg")
    p, rho = r, dot(r, r)
    for _ in range(iterations):
        if rho == 0:
            break
        q = stored(axpy(1.0, zero, spmv_left(cm, spmv(cm, p))), "cg")
        step = rho / dot(p, q)
        x, r = stored(axpy(step, x, p), "cg"), stored(axpy(-step, r, q), "cg")
        new = dot(r, r)
        p = stored(axpy(new / rho, r, p), "cg")
        rho = new
    return x
