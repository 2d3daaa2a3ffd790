"""Reports over run records (dataset, format, degree, seconds, joules[, bits, counters])."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def scaling(runs: DataFrame) -> DataFrame:
    """Speedup, efficiency and energy ratio against the smallest degree of each dataset and format."""
    w = Window.partitionBy("dataset", "format").orderBy("degree")
    t, e = F.first_value("seconds").over(w), F.first_value("joules").over(w)
    out = runs.select("dataset", "format", "degree", (t / F.col("seconds")).alias("speedup"), (e / F.col("joules")).alias("energy_ratio"))
    return out.withColumn("efficiency", F.col("speedup") / F.col("degree"))


def optimal_degree(runs: DataFrame) -> DataFrame:
    """(dataset, format, p_time, p_energy, gap): the best degree by time and by energy, ties to fewer workers."""
    best = runs.groupBy("dataset", "format").agg(F.min_by("degree", F.struct("seconds", "degree")).alias("p_time"), F.min_by("degree", F.struct("joules", "degree")).alias("p_energy"))
    return best.withColumn("gap", F.col("p_time") - F.col("p_energy"))


def pareto(runs: DataFrame, axes: tuple[str, str] = ("seconds", "joules"), by: tuple[str, ...] = ("dataset",)) -> DataFrame:
    """Runs that no other run of the group beats in one axis without losing in the other: one sort, a running minimum."""
    a, b = axes
    ranked = runs.withColumn("__r", F.dense_rank().over(Window.partitionBy(*by).orderBy(a)))
    earlier = Window.partitionBy(*by).orderBy("__r").rangeBetween(Window.unboundedPreceding, -1)
    level = Window.partitionBy(*by, "__r")
    out = ranked.withColumn("__lower", F.min(b).over(earlier)).withColumn("__same", F.min(b).over(level))
    return out.where((F.col(b) == F.col("__same")) & (F.col("__lower").isNull() | (F.col(b) < F.col("__lower")))).drop("__r", "__lower", "__same")


def choose_config(runs: DataFrame, max_joules: float | None = None, max_bits: float | None = None, minimise: str = "seconds") -> DataFrame:
    """The best configuration of each dataset within the limits; ties to the smaller format name, then fewer workers."""
    ok = runs
    if max_joules is not None:
        ok = ok.where(F.col("joules") <= max_joules)
    if max_bits is not None:
        ok = ok.where(F.col("bits") <= max_bits)
    best = ok.groupBy("dataset").agg(F.min(F.struct(minimise, "format", "degree", "joules")).alias("b"))
    return best.select("dataset", F.col("b.format").alias("format"), F.col("b.degree").alias("degree"), F.col(f"b.{minimise}").alias(minimise), *([F.col("b.joules").alias("joules")] if minimise != "joules" else []))


def correlation(x: str, y: str) -> Column:
    """Pearson's coefficient over the rows that have both; null where one of the two is constant (corr() fails there)."""
    a, b = F.when(F.col(y).isNotNull(), F.col(x)), F.when(F.col(x).isNotNull(), F.col(y))
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(a) * F.stddev_pop(b))


def metric_energy_correlation(runs: DataFrame, metric: str = "seconds") -> DataFrame:
    return runs.groupBy("format").agg(correlation(metric, "joules").alias("r"), F.regr_slope("joules", metric).alias("slope"), F.regr_r2("joules", metric).alias("r2"))


def rank_formats(runs: DataFrame, by: str = "seconds") -> DataFrame:
    per = runs.groupBy("dataset", "format").agg(F.min(by).alias(by))
    return per.withColumn("place", F.rank().over(Window.partitionBy("dataset").orderBy(by)))


def space_inflation(runs: DataFrame) -> DataFrame:
    base = F.first_value("bits").over(Window.partitionBy("dataset", "format").orderBy("degree"))
    return runs.withColumn("inflation", F.col("bits") / base)


def report_q1(runs: DataFrame, plain: str = "edgelist") -> DataFrame:
    """Does compression save? Each format against the plain one: time, energy and space ratios at its best degree."""
    best = runs.groupBy("dataset", "format").agg(F.min("seconds").alias("seconds"), F.min("joules").alias("joules"), F.min("bits").alias("bits"))
    plain = best.where(F.col("format") == plain).select("dataset", F.col("seconds").alias("s0"), F.col("joules").alias("j0"), F.col("bits").alias("b0"))
    return best.join(plain, "dataset", "left").select("dataset", "format", (F.col("seconds") / F.col("s0")).alias("time_ratio"), (F.col("joules") / F.col("j0")).alias("energy_ratio"), (F.col("bits") / F.col("b0")).alias("space_ratio"))


def report_q2(runs: DataFrame) -> DataFrame:
    """Do the optima coincide? Share of (dataset, format) whose best degrees by time and energy differ, and the mean gap."""
    return optimal_degree(runs).groupBy("format").agg(F.avg((F.col("gap") != 0).cast("int")).alias("differ"), F.avg("gap").alias("mean_gap"))


def report_q3(runs: DataFrame, counters: tuple[str, ...]) -> DataFrame:
    """Which counters track energy? Correlation per format and counter from the counters map; absent ones give null."""
    long = runs.select("format", "joules", F.explode(F.map_filter("counters", lambda k, v: k.isin(*counters))).alias("counter", "n"))
    return long.groupBy("format", "counter").agg(correlation("n", "joules").alias("r"))
