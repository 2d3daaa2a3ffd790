"""Mixing sources to target weights by pivotal dependent rounding. DataFrame functions only.

Every document gets a fractional number of copies, its source's target over its source's size. The whole part is
certain; the fractions of a source are rounded dependently: two fractions are paired, mass moves from one to the other
at random until one is 0 or 1, and the other goes on. Documents are dealt to blocks of bounded size, each block is
folded in order of document size, and the one open fraction of each block goes to the next level of a reduction tree.
A source's number of copies thus misses its expectation by less than one, its words by little.

Repeated rows of one (doc_id, source, text) are one unit of the rounding with as many rows: m rows of fraction p have
m * p extra copies together, the whole part of which is certain, and only the rest is rounded. So each row has a decision
of its own, and no task holds all rows of a unit.

Defined cases: a null text has size 0, a null source is a source of its own (last in order), null ids are ids, an empty
table gives no rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import keyed_join, n_words, uniform, written

#: Above this number of sources the target table is joined by a shuffle instead of a broadcast (about 100 bytes each).
BROADCAST_SOURCES = 100_000


def _ranged(df: DataFrame, order: list[str], tag: str) -> DataFrame:
    """df in ranges of `order`, stored with the number of the range (`pid`): bounds are sampled, so they are drawn once."""
    return written(df.repartitionByRange(*order).withColumn("pid", F.spark_partition_id()), tag)


def _before(ranged: DataFrame, **sums: Column) -> DataFrame:
    """(pid, one sum over all earlier ranges per name): one row per range."""
    per = ranged.groupBy("pid").agg(*[v.alias(k) for k, v in sums.items()])
    earlier = Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    return per.select("pid", *[F.coalesce(F.sum(k).over(earlier), F.lit(0)).alias(k) for k in sums])


def source_targets(sized: DataFrame, weights: tuple[float, ...] = (5, 2, 1), cap: float = 3.0) -> DataFrame:
    """(source, source_size, n_docs, target): all words shared by weight, none above cap times its source's size.

    The weights repeat over the sources in code-point order, null last. In order of cap over weight, a source is full
    exactly if the level that is left for it exceeds its ratio. Both orders are range sorts with offsets per range, so
    sources may be as many as hosts.
    """
    per_source = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs")).withColumn("last", F.col("source").isNull())
    listed = F.array(*[F.lit(float(w)) for w in weights])
    named = _ranged(per_source, ["last", "source"], "sources")
    place = F.row_number().over(Window.partitionBy("pid").orderBy("last", "source")) - 1 + F.col("offset")
    ranked = named.join(F.broadcast(_before(named, offset=F.count("*"))), "pid").withColumn("weight", F.element_at(listed, (place % len(weights) + 1).cast("int"))).drop("pid", "offset")
    ranked = ranked.withColumn("most", F.col("source_size") * F.lit(float(cap))).withColumn("ratio", F.col("most") / F.col("weight"))
    ratios = _ranged(ranked, ["ratio", "last", "source"], "ratios")
    totals = ratios.agg(F.coalesce(F.sum("source_size"), F.lit(0)).alias("all_words"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("all_weight"))
    inside = Window.partitionBy("pid").orderBy("ratio", "last", "source").rowsBetween(Window.unboundedPreceding, -1)
    so_far = lambda c, base: F.coalesce(F.sum(c).over(inside), F.lit(0.0)) + F.col(base)
    levels = ratios.join(F.broadcast(_before(ratios, most0=F.sum("most"), weight0=F.sum("weight"))), "pid").join(F.broadcast(totals))
    levels = levels.withColumn("level", (F.col("all_words") - so_far("most", "most0")) / (F.col("all_weight") - so_far("weight", "weight0")))
    water = levels.agg(F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "last", "source", "level")))["level"].alias("water"))
    target = F.when(F.col("water").isNull() | (F.col("ratio") < F.col("water")), F.col("most")).otherwise(F.col("water") * F.col("weight"))
    return levels.join(F.broadcast(water)).select("source", "source_size", "n_docs", F.least(target, F.col("most")).cast("double").alias("target"))


def _fold(units: str, seed: int) -> F.Column:
    """Sequential pivotal rounding of one block; units: array of (size, id, t, p) in order. Gives (open unit, its p, the winners)."""
    return F.expr(f"""
        aggregate({units}, named_struct('unit', CAST(NULL AS STRUCT<size: BIGINT, id: BIGINT, t: BIGINT, p: DOUBLE>), 'p', 0D, 'won', CAST(array() AS ARRAY<STRUCT<size: BIGINT, id: BIGINT, t: BIGINT, p: DOUBLE>>)),
          (a, u) -> CASE
            WHEN a.unit IS NULL THEN named_struct('unit', u, 'p', u.p, 'won', a.won)
            WHEN a.p + u.p < 1 - 1e-12D THEN named_struct(
              'unit', IF(shiftrightunsigned(xxhash64({seed}, a.unit.id, a.unit.size, a.unit.t, u.id, u.size, u.t), 11) * {2.0**-53!r}D < a.p / (a.p + u.p), a.unit, u),
              'p', a.p + u.p, 'won', a.won)
            ELSE IF(shiftrightunsigned(xxhash64({seed}, a.unit.id, a.unit.size, a.unit.t, u.id, u.size, u.t), 11) * {2.0**-53!r}D < (1 - u.p) / (2 - a.p - u.p),
              named_struct('unit', u, 'p', greatest(a.p + u.p - 1, 0D), 'won', concat(a.won, array(a.unit))),
              named_struct('unit', a.unit, 'p', greatest(a.p + u.p - 1, 0D), 'won', concat(a.won, array(u))))
          END)""")


def _decided(docs: DataFrame, weights: tuple[float, ...], cap: float, block: int, seed: int) -> DataFrame:
    """(doc_id, source, size, t, m, source_size, target, whole, extra): one row per unit of m rows; t: a hash of the text.

    Each row of a unit is taken `whole` times, `extra` of them (fewer than m) once more.
    """
    sized = written(docs.select("doc_id", "source", n_words(F.col("text")).alias("size"), F.xxhash64("text").alias("t")), "sizes")
    targets = written(source_targets(sized, weights, cap), "targets")
    n_sources, largest = targets.agg(F.count("*"), F.max("n_docs")).first()
    units = sized.groupBy("doc_id", "source", "size", "t").agg(F.count("*").alias("m"))
    side = F.broadcast(targets) if n_sources <= BROADCAST_SOURCES else targets
    rated = units.withColumnRenamed("source", "own").join(side, F.col("own").eqNullSafe(F.col("source"))).drop("own")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    rated = rated.withColumn("whole", F.floor(rate + 1e-9)).withColumn("part", F.greatest(rate - F.col("whole"), F.lit(0.0)) * F.col("m"))
    rated = written(rated.withColumn("sure", F.least(F.floor(F.col("part") + 1e-9), F.col("m"))).withColumn("p", F.greatest(F.col("part") - F.col("sure"), F.lit(0.0))), "units")
    blocks = F.ceil(F.col("n_docs") / block)
    open_units = rated.where((F.col("p") > 1e-9) & (F.col("size") > 0))
    level = open_units.select("source", F.pmod(F.xxhash64("doc_id", "size", "t", F.lit(seed)), blocks).alias("b"), F.struct("size", F.col("doc_id").alias("id"), "t", "p").alias("unit"))
    won, left = [], max(1, -(-(largest or 0) // block))
    while True:
        folded = written(level.groupBy("source", "b").agg(F.sort_array(F.collect_list("unit")).alias("units")).select("source", "b", _fold("units", seed).alias("f")), "pivots")
        won.append(folded.select("source", F.explode("f.won").alias("unit")))
        if left <= 1:
            break
        left = -(-left // block)
        level = folded.select("source", F.floor(F.col("b") / block).alias("b"), F.struct(F.col("f.unit.size").alias("size"), F.col("f.unit.id").alias("id"), F.col("f.unit.t").alias("t"), F.col("f.p").alias("p")).alias("unit")).where(F.col("unit.p") > 1e-12)
    won.append(folded.where(uniform(F.lit(seed + 1), F.col("f.unit.id"), F.col("f.unit.size"), F.col("f.unit.t")) < F.col("f.p")).select("source", F.col("f.unit").alias("unit")))
    winners = reduce(DataFrame.unionAll, won).select(F.col("source").alias("w_source"), F.col("unit.id").alias("w_id"), F.col("unit.size").alias("w_size"), F.col("unit.t").alias("w_t"), F.lit(1).alias("more"))
    same = F.col("doc_id").eqNullSafe(F.col("w_id")) & F.col("source").eqNullSafe(F.col("w_source")) & (F.col("size") == F.col("w_size")) & (F.col("t") == F.col("w_t"))
    extra = (F.col("sure") + F.coalesce(F.col("more"), F.lit(0))).cast("long")
    return rated.join(winners, same, "left").select("doc_id", "source", "size", "t", "m", "source_size", "target", F.col("whole").cast("long").alias("whole"), extra.alias("extra"))


def _spread(df: DataFrame, n: str, chunk: int = 10_000) -> DataFrame:
    """df with each row n times; rows of large n are dealt out before they are repeated."""
    times = lambda c: F.explode(F.sequence(F.lit(1).cast("long"), c))
    few = df.where((F.col(n) > 0) & (F.col(n) <= chunk)).withColumn("__time", times(F.col(n)))
    parts = df.where(F.col(n) > chunk).withColumn("__part", times(F.ceil(F.col(n) / chunk))).repartition("__part")
    many = parts.withColumn("__time", times(F.least(F.lit(chunk).cast("long"), F.col(n) - (F.col("__part") - 1) * chunk))).drop("__part")
    return few.unionByName(many).drop("__time")


def mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), cap: float = 3.0, block: int = 512, seed: int = 20) -> DataFrame:
    """docs' rows as (doc_id, source, size, source_size, target, copies, taken); copies * size = taken, copies <= cap for whole caps.

    block: expected number of units that one fold sees. Reruns agree: all draws are hashes of ids, sizes and texts.
    """
    units = _decided(docs, weights, cap, block, seed)
    some = F.explode(F.array(F.struct((F.col("whole") + 1).alias("copies"), F.col("extra").alias("n")), F.struct(F.col("whole").alias("copies"), (F.col("m") - F.col("extra")).alias("n"))))
    rows = _spread(units.select("doc_id", "source", "size", "source_size", "target", some.alias("k")).select("*", "k.copies", "k.n").drop("k"), "n")
    return rows.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_documents(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), cap: float = 3.0, block: int = 512, seed: int = 20) -> DataFrame:
    """docs with every row as often as the mix takes it; a row without words is left out, as it adds nothing.

    The rows of a unit are numbered where they lie, by offsets per partition, never in one task.
    """
    columns = [f"`{c}`" for c in docs.columns]
    units = _decided(docs, weights, cap, block, seed).where("size > 0")
    key = lambda doc, source, size, t: F.struct(F.col(doc).alias("a"), F.col(source).alias("b"), F.col(size).alias("c"), F.col(t).alias("d")).alias("key")
    rows = docs.select(F.struct(F.col("doc_id").alias("a"), F.col("source").alias("b"), n_words(F.col("text")).alias("c"), F.xxhash64("text").alias("d")).alias("key"), F.struct(*[F.col(c) for c in columns]).alias("row"))
    decided = written(units.select(key("doc_id", "source", "size", "t"), "m", "whole", "extra"), "decided")
    single = rows.join(decided.where("m = 1"), "key").select("row", (F.col("whole") + F.col("extra")).alias("copies"))
    several = written(keyed_join(rows, decided.where("m > 1"), ["key"], "m").withColumn("pid", F.spark_partition_id()), "several")
    numbered = several.withColumn("at", F.row_number().over(Window.partitionBy("key", "pid").orderBy(F.xxhash64("row"))))
    earlier = Window.partitionBy("key").orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    offsets = several.groupBy("key", "pid").count().select("key", "pid", F.coalesce(F.sum("count").over(earlier), F.lit(0)).alias("offset"))
    own = numbered.join(offsets, ["key", "pid"]).select("row", (F.col("whole") + (F.col("at") + F.col("offset") <= F.col("extra")).cast("long")).alias("copies"))
    taken = single.unionByName(own).where("copies > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("copy")).select("row.*")
