"""Quality rules: text statistics and a learned decision list. DataFrame functions only.

Statistics per text, then an ordered list of threshold conjunctions that reject junk. The list is learned by sequential
covering on labelled rows: a rule grows by the condition with the best information gain on two thirds of the rows, is
pruned from its end on the last third, and is kept if it is precise there; covered rows leave and the next rule grows.
The list is emitted as one conditional Spark expression.

Defined cases: a null or empty text has no words, no symbols and no lines, and fails the base rule; without labels of
both kinds the list is empty and only the base rule rejects; columns of other names are left alone.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, GAP

#: Statistics that conditions may test, each from the text alone.
FEATURES = ("n_words", "symbol_share", "dup_line_share", "repeat_share", "word_length", "upper_share", "distinct_share", "mark_share", "digit_share")
#: Bound on the labelled rows that a list is fitted on (smallest hashes of their ids first).
FIT_ROWS = 20_000


def text_stats(docs: DataFrame) -> DataFrame:
    """docs and their statistics as columns: the five base counts, and the shares in FEATURES."""
    text = F.coalesce(F.col("text"), F.lit(""))
    bare = F.btrim(text, F.lit(BLANKS))
    out = docs.withColumn("__words", F.when(F.length(bare) == 0, F.array().cast("array<string>")).otherwise(F.split(bare, GAP)))
    out = out.withColumn("n_words", F.size("__words").cast("long"))
    out = out.withColumn("word_chars", F.length(F.translate(text, BLANKS, "")).cast("long"))
    out = out.withColumn("n_symbols", (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long"))
    lines = out.withColumn("__lines", F.expr(r"filter(split(coalesce(text, ''), '\n'), l -> length(translate(l, ' \t\n\u000b\u000c\r', '')) > 0)"))
    out = lines.withColumn("n_dup_lines", (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long"))
    # windows of eight words by hash; only texts in which a hash recurs sort theirs to find the words they cover
    out = out.withColumn("__hashes", F.expr("transform(__words, w -> xxhash64(w))"))
    out = out.withColumn("__windows", F.expr("CASE WHEN n_words >= 9 THEN transform(sequence(1, CAST(n_words AS INT) - 7), i -> xxhash64(slice(__hashes, i, 8))) END"))
    out = out.withColumn("__again", F.expr("""CASE WHEN size(array_distinct(__windows)) < size(__windows) THEN
        sort_array(transform(__windows, (h, i) -> named_struct('h', h, 'i', i))) END"""))
    out = out.withColumn("__places", F.expr("""sort_array(transform(filter(__again, (x, k) -> x.h = get(__again, k - 1).h OR x.h = get(__again, k + 1).h), x -> x.i))"""))
    out = out.withColumn("n_repeat_words", F.expr("""CASE WHEN __places IS NULL OR size(__places) = 0 THEN 0L ELSE CAST(
        aggregate(__places, named_struct('last', -8, 'n', 0L), (a, i) -> named_struct('last', i, 'n', a.n + least(8, i - a.last)), a -> a.n) AS BIGINT) END"""))
    words, chars = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1))
    shares = {
        "symbol_share": F.col("n_symbols") / chars,
        "dup_line_share": F.col("n_dup_lines") / F.greatest(F.size("__lines"), F.lit(1)),
        "repeat_share": F.col("n_repeat_words") / words,
        "word_length": F.col("word_chars") / words,
        "upper_share": (F.length(text) - F.length(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))) / chars,
        "distinct_share": F.size(F.array_distinct("__hashes")) / words,
        "mark_share": (F.length(text) - F.length(F.translate(text, "!?;:=_~^", ""))) / chars,
        "digit_share": (F.length(text) - F.length(F.translate(text, "0123456789", ""))) / chars,
    }
    out = out.withColumns({k: v.cast("double") for k, v in shares.items()})
    return out.drop("__words", "__lines", "__hashes", "__windows", "__again", "__places")


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def column(self) -> Column:
        return F.col(self.feature) > self.threshold if self.above else F.col(self.feature) <= self.threshold

    def holds(self, x: np.ndarray) -> np.ndarray:
        v = x[:, FEATURES.index(self.feature)]
        return v > self.threshold if self.above else v <= self.threshold

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.threshold:.6g}"


@dataclass(frozen=True)
class DecisionList:
    """Rules in order, each a conjunction that rejects; what none rejects is kept."""

    rules: tuple[tuple[Condition, ...], ...]

    def keeps(self) -> Column:
        out = F.lit(True)
        for rule in reversed(self.rules):
            both = rule[0].column()
            for c in rule[1:]:
                both = both & c.column()
            out = F.when(both, F.lit(False)).otherwise(out)
        return out

    def __str__(self) -> str:
        return "\n".join("reject if " + " and ".join(map(str, r)) for r in self.rules) or "keep all"


def _covers(rule: list[Condition], x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), bool)
    for c in rule:
        out &= c.holds(x)
    return out


def _grow(x: np.ndarray, junk: np.ndarray, longest: int, bins: int) -> list[Condition]:
    rule: list[Condition] = []
    inside = np.ones(len(x), bool)
    while len(rule) < longest and (~junk[inside]).any():
        p0, n0 = junk[inside].sum(), (~junk[inside]).sum()
        best, gain = None, 1e-9
        for f, name in enumerate(FEATURES):
            v = x[inside, f]
            levels = np.unique(np.quantile(v, np.linspace(0, 1, bins)))
            cuts = (levels[1:] + levels[:-1]) / 2
            for t in cuts:
                high = v > t
                for above in (True, False):
                    got = high if above else ~high
                    p, n = (junk[inside] & got).sum(), (~junk[inside] & got).sum()
                    if p == 0:
                        continue
                    g = p * (np.log2(p / (p + n)) - np.log2(p0 / (p0 + n0)))
                    if g > gain:
                        best, gain = Condition(name, above, float(t)), g
        if best is None:
            break
        rule.append(best)
        inside &= best.holds(x)
    return rule


def fit_list(x: np.ndarray, junk: np.ndarray, precision: float = 0.95, least: int = 5, longest: int = 4, most_rules: int = 12, bins: int = 33) -> DecisionList:
    """Sequential covering; x: rows by FEATURES, junk: booleans. Every third row, in the given order, is for pruning."""
    rules: list[tuple[Condition, ...]] = []
    held = np.arange(len(x)) % 3 == 2
    open_rows = np.ones(len(x), bool)
    while len(rules) < most_rules:
        grow, prune = open_rows & ~held, open_rows & held
        if junk[grow].sum() < least or not (~junk[grow]).any():
            break
        rule = _grow(x[grow], junk[grow], longest, bins)

        def worth(r: list[Condition]) -> float:
            got = _covers(r, x[prune])
            p, n = (junk[prune] & got).sum(), (~junk[prune] & got).sum()
            return (p - n) / (p + n) if p + n else -1.0

        while len(rule) > 1 and worth(rule[:-1]) >= worth(rule):
            rule = rule[:-1]
        if not rule:
            break
        got, everywhere = _covers(rule, x[open_rows]), junk[open_rows]
        p, n = (everywhere & got).sum(), (~everywhere & got).sum()
        if p < least or p / (p + n) < precision or worth(rule) < 2 * precision - 1:
            break
        rules.append(tuple(rule))
        open_rows[open_rows] = ~got
    return DecisionList(tuple(rules))


def learn_rules(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, **options) -> DecisionList:
    """A list from at most fit_rows labelled documents, those whose ids have the smallest hashes."""
    votes = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy(F.col("doc_id").alias("l_id")).agg(F.avg("quality").alias("l_quality"))
    sample = votes.orderBy(F.xxhash64("l_id"), "l_id").limit(fit_rows)
    rows = text_stats(docs.select("doc_id", "text").join(F.broadcast(sample), F.col("doc_id") == F.col("l_id"))).orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows).select("l_quality", *FEATURES).collect()
    if not rows:
        return DecisionList(())
    table = np.array([[float(v) for v in r] for r in rows])
    return fit_list(table[:, 1:], table[:, 0] < 0.5, **options)


def apply_rules(docs: DataFrame, rules: DecisionList) -> DataFrame:
    """docs, their statistics, base_failed and kept (false if base_failed, else the list's verdict).

    A filter on any of these would be pushed below the statistics, with all they are made of copied into it once per use.
    The generator of one element stands in its way.
    """
    made = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", *FEATURES[1:], "base_failed", "kept"]
    judged = text_stats(docs).withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & rules.keeps())
    untouched = [F.col(f"`{c}`") for c in docs.columns if c not in made]
    return judged.select(*untouched, F.explode(F.array(F.struct(*made))).alias("__judged")).select(*untouched, "__judged.*")
