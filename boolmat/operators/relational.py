"""Relational operators around the matrix methods: thin names over DataFrame plans."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A side that is joined by broadcast or nested loop has at most this many rows.
SMALL_ROWS = 1_000_000


def small(df: DataFrame, most: int = SMALL_ROWS) -> DataFrame:
    """df marked for broadcast if a count shows that it is small; otherwise as it is, so that a shuffle join is planned."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def project(df: DataFrame, **exprs: Column) -> DataFrame:
    return df.select(*[e.alias(n) for n, e in exprs.items()])


def restrict(df: DataFrame, cond: Column) -> DataFrame:
    return df.where(cond)


def unique(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.select(*cols).distinct()


def join_hash(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right.hint("shuffle_hash"), on)


def join_merge(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right.hint("merge"), on)


def join_broadcast(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(small(right), on)


def join_outer(left: DataFrame, right: DataFrame, on, side: str = "full") -> DataFrame:
    return left.join(right, on, side)


def join_semi(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_semi")


def join_anti(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_anti")


def join_theta(left: DataFrame, right: DataFrame, cond: Column, how: str = "inner") -> DataFrame:
    """A join without equality: only against a side that is proven small."""
    if right.limit(SMALL_ROWS + 1).count() > SMALL_ROWS:
        raise ValueError("the right side of a theta join is too large")
    return left.join(F.broadcast(right), cond, how)


def with_scalar(df: DataFrame, one_row: DataFrame) -> DataFrame:
    return df.crossJoin(F.broadcast(one_row.limit(1)))


def join_interval(points: DataFrame, spans: DataFrame, point: str, lo: str, hi: str, bucket: int = 3600) -> DataFrame:
    """points with lo <= point < hi (timestamps): spans are listed under each time bucket they touch, then an equality
    join on buckets, then the exact test."""
    b = lambda c: F.floor(F.unix_timestamp(c.cast("timestamp")) / bucket)
    listed = spans.withColumn("__b", F.explode(F.sequence(b(F.col(lo)), b(F.col(hi)))))
    return points.withColumn("__b", b(F.col(point))).join(listed, "__b").where((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("__b")


def join_asof(left: DataFrame, right: DataFrame, on: str, by: list[str], value: str, direction: str = "backward", strict: bool = False) -> DataFrame:
    """left with the right row's `value` at the latest (or, forward, earliest) `on` not after (before) its own, per key.

    One union, one window per key: no pair is ever built.
    """
    side = lambda df, is_left: df.select(*by, on, F.lit(is_left).alias("__left"), *([F.lit(None).cast(right.schema[value].dataType).alias("__v")] if is_left else [F.col(value).alias("__v")]), *([F.struct(*left.columns).alias("__row")] if is_left else [F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("__row")]))
    both = side(left, True).unionAll(side(right, False))
    tie = F.col("__left").cast("int")
    tie = -tie if strict else tie
    if direction == "backward":
        w = Window.partitionBy(*by).orderBy(F.col(on).asc(), tie.asc()).rowsBetween(Window.unboundedPreceding, 0)
    else:
        w = Window.partitionBy(*by).orderBy(F.col(on).desc(), tie.asc()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("__found", F.last("__v", ignorenulls=True).over(w)).where("__left").select("__row.*", F.col("__found").alias(f"asof_{value}"))


def aggregate(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*[e.alias(n) for n, e in aggs.items()])


def count_unique(df: DataFrame, key: str, col: str) -> DataFrame:
    return df.groupBy(key).agg(F.count_distinct(col).alias("n"))


def approx_unique(df: DataFrame, col: str, rsd: float = 0.05) -> DataFrame:
    return df.agg(F.approx_count_distinct(col, rsd).alias("n"))


def quantiles(df: DataFrame, col: str, ps: list[float]) -> DataFrame:
    return df.agg(*[F.percentile(col, F.lit(p)).alias(f"q{round(100 * p)}") for p in ps])


def correlate(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.agg(F.corr(a, b).alias("r"), F.regr_slope(b, a).alias("slope"), F.regr_r2(b, a).alias("r2"), F.stddev_samp(a).alias("sd"))


def arg_best(df: DataFrame, keys: list[str], item: str, by: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.min_by(item, by).alias("best"))


def mask_union(df: DataFrame, key: str, bit: Column) -> DataFrame:
    return df.groupBy(key).agg(F.bit_or(bit).alias("mask"))


def ranked(df: DataFrame, by: list[str], order: list[Column], how: str = "row_number") -> DataFrame:
    f = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank}[how]
    return df.withColumn("rank", f().over(Window.partitionBy(*by).orderBy(*order)))


def bucketize(df: DataFrame, order: list[Column], k: int, by: list[str] | None = None) -> DataFrame:
    return df.withColumn("tile", F.ntile(k).over(Window.partitionBy(*(by or [])).orderBy(*order)))


def successor(df: DataFrame, by: list[str], order: list[Column], col: str) -> DataFrame:
    return df.withColumn("next", F.lead(col).over(Window.partitionBy(*by).orderBy(*order)))


def running(df: DataFrame, by: list[str], order: list[Column], col: str) -> DataFrame:
    return df.withColumn("running", F.sum(col).over(Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)))


def rolling(df: DataFrame, by: list[str], ts: str, seconds: int, value: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(F.unix_micros(F.col(ts).cast("timestamp"))).rangeBetween(-seconds * 1_000_000, 0)
    return df.withColumn("rolling", F.sum(value).over(w))


def baseline_of(df: DataFrame, by: list[str], order: list[Column], col: str) -> DataFrame:
    return df.withColumn("base", F.first_value(F.col(col)).over(Window.partitionBy(*by).orderBy(*order)))


def top(df: DataFrame, by: list[Column], k: int, offset: int = 0) -> DataFrame:
    return df.orderBy(*by).offset(offset).limit(k) if offset else df.orderBy(*by).limit(k)


def top_per(df: DataFrame, key: str, by: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(key).orderBy(*by))).where(F.col("rank") <= k)


def set_op(a: DataFrame, b: DataFrame, kind: str, all: bool = False) -> DataFrame:
    ops = {("union", True): DataFrame.unionAll, ("intersect", True): DataFrame.intersectAll, ("except", True): DataFrame.exceptAll, ("intersect", False): DataFrame.intersect, ("except", False): DataFrame.subtract}
    return a.unionAll(b).distinct() if (kind, all) == ("union", False) else ops[kind, all](a, b)


def cube_report(df: DataFrame, dims: list[str], aggs: dict[str, Column], kind: str = "cube") -> DataFrame:
    how = {"cube": df.cube, "rollup": df.rollup, "groupBy": df.groupBy}[kind]
    return how(*dims).agg(*[e.alias(n) for n, e in aggs.items()])


def grouping_sets(df: DataFrame, sets: list[list[str]], aggs: dict[str, Column]) -> DataFrame:
    dims = list(dict.fromkeys(d for s in sets for d in s))
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *dims).agg(*[e.alias(n) for n, e in aggs.items()])


def space_pivot(df: DataFrame, row: str, column: str, value: str, columns: list[str]) -> DataFrame:
    return df.groupBy(row).pivot(column, columns).agg(F.first(value))


def melt(df: DataFrame, ids: list[str], columns: list[str]) -> DataFrame:
    return df.unpivot(ids, columns, "name", "value")


def sample_rows(df: DataFrame, frac: float, seed: int = 1) -> DataFrame:
    return df.sample(frac, seed)


def prop(df: DataFrame, name: str) -> DataFrame:
    return df.withColumn(name, F.from_json("props", f"{name} int")[name])


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
