"""Quality scores by pairwise ranking.

A Bradley-Terry model learns from preference pairs (a document labelled good, one labelled bad): the probability that
the first is better is the logistic function of the difference of their scores, which are linear in features of the
text. The scores are then cut at the quantile that the share of bad labels gives; the cut is placed at a stated value
of the logistic scale, 0.3 by default, so that `score >= 0.3` is the threshold by quantile.

Features are counts and shares of the whole text, each dealt to bins whose borders are quantiles of the fitted rows.

All labelled rows are fitted, and every good-bad pair of them counts once. A pair's loss depends on the two scores alone
and is smooth, so the rows of each label are summed at the nodes of polynomials in the score, and pairs are taken between
nodes: sums over all pairs to about 12 digits in one pass over the rows. Newton steps lead to the one minimum.

Defined cases: null and empty texts are texts of length 0 and get a score like any other; without labels of both kinds
all scores are 0.5; repeated labels of an id are averaged, ties count as good.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import POWERS, files_for, mixed, remove_table, slices, text_buffers, word_spans, written

#: Width of a stretch of scores, nodes in it, rows binned at once, and tasks that send sums to the driver.
WIDTH, NODES, CHUNK, TASKS = 4.0, 24, 4_096, 64
FEATURES = ("bytes", "words", "word_length", "long_words", "symbols", "bars", "marks", "upper", "digits", "high_bytes", "distinct_words", "repeat_shingles", "lines", "dup_lines", "stops")


def _repeats(owner: np.ndarray, keys: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct keys, keys) per owner."""
    order = np.lexsort((keys, owner))
    o, k = owner[order], keys[order]
    fresh = np.ones(len(o), bool)
    fresh[1:] = (o[1:] != o[:-1]) | (k[1:] != k[:-1])
    return np.bincount(o[fresh], minlength=n), np.bincount(owner, minlength=n)


def _class(chars: str) -> np.ndarray:
    table = np.zeros(256, bool)
    table[list(chars.encode())] = True
    return table


_CLASSES = {"symbols": _class("#*$%&|<>"), "bars": _class("|"), "marks": _class("!?;:=_~^"), "upper": _class("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), "digits": _class("0123456789"), "high_bytes": np.arange(256) >= 128, "stops": _class(".,")}


def features(data: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Rows by FEATURES for the texts data[cuts[i]:cuts[i + 1]]."""
    n = len(cuts) - 1
    size = np.diff(cuts).astype(float)
    start, end, owner = word_spans(data, cuts)
    prefix = POWERS.prefix(data)
    words = POWERS.span(prefix, start, end)
    length = end - start
    distinct, count = _repeats(owner, words, n)
    four = words.copy()
    for k in range(1, min(4, len(words))):
        four[: len(four) - k] = mixed(four[: len(four) - k]) * np.uint64(31) + words[k:]
    same = np.zeros(len(words), bool)
    if len(words) > 3:
        same[:-3] = owner[:-3] == owner[3:]
    d4, c4 = _repeats(owner[same], four[same], n)
    breaks = np.flatnonzero(data == 10)
    at = np.unique(np.concatenate([[0], breaks + 1, cuts[:-1]]))
    at = at[at < len(data)]
    stop = np.append(at[1:], len(data))
    line_owner = np.searchsorted(cuts, at, side="right") - 1
    stop = np.where((stop > at) & (data[np.maximum(stop - 1, 0)] == 10), stop - 1, stop) if len(at) else stop
    solid = stop > at
    dl, cl = _repeats(line_owner[solid], POWERS.span(prefix, at[solid], stop[solid]), n)
    some, wordy = np.maximum(size, 1), np.maximum(count, 1)
    out = {
        "bytes": np.log1p(size), "words": np.log1p(count), "word_length": np.bincount(owner, length, minlength=n) / wordy, "long_words": np.bincount(owner, length > 12, minlength=n) / wordy,
        "distinct_words": distinct / wordy, "repeat_shingles": 1 - d4 / np.maximum(c4, 1), "lines": cl / wordy, "dup_lines": 1 - dl / np.maximum(cl, 1),
    }
    out["repeat_shingles"][c4 == 0] = 0
    out["dup_lines"][cl == 0] = 0
    for name, table in _CLASSES.items():
        hits = np.concatenate([[0], np.cumsum(table[data])])
        out[name] = (hits[cuts[1:]] - hits[cuts[:-1]]) / some
    return np.column_stack([out[f] for f in FEATURES]).astype(float)


def _batches(column: pa.Array) -> Iterator[np.ndarray]:
    raw, offsets = text_buffers(column)
    for a, b in slices(offsets):
        yield features(raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])


@dataclass(frozen=True)
class Ranker:
    """borders: inner bin borders per feature; weights: one per bin; cut: raw score at the quantile; place: its score."""

    borders: tuple[np.ndarray, ...]
    weights: np.ndarray
    cut: float
    place: float = 0.3

    def bins(self, x: np.ndarray) -> np.ndarray:
        at, out = 0, np.empty(x.shape, np.int64)
        for f, b in enumerate(self.borders):
            out[:, f] = at + np.searchsorted(b, x[:, f], side="right")
            at += len(b) + 1
        return out

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.weights[self.bins(x)].sum(1)

    def score(self, x: np.ndarray) -> np.ndarray:
        if not len(self.weights):
            return np.full(len(x), 0.5)
        z = self.raw(x) - self.cut + np.log(self.place / (1 - self.place))
        return 1 / (1 + np.exp(-np.clip(z, -500, 500)))


_AT = np.cos(np.pi * (np.arange(NODES) + 0.5) / NODES)
_TO_NODES = np.cos(np.outer(np.arange(NODES), np.arccos(_AT))) * np.where(np.arange(NODES) > 0, 2, 1)[:, None] / NODES

#: Sums by (label, stretch): rows and rows per bin, at the stretch's nodes.
Sums = dict[tuple[bool, int], np.ndarray]


def _shares(scores: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(stretch, shares of its nodes) of each score: what a function has at the nodes, weighted by them, it has at the score."""
    stretch = np.floor(scores / WIDTH).astype(np.int64)
    at = np.arccos(np.clip(2 * (scores / WIDTH - stretch) - 1, -1, 1))
    return stretch, np.cos(at[:, None] * np.arange(NODES)) @ _TO_NODES


def _places(stretches: Iterable[int]) -> np.ndarray:
    return np.concatenate([(c + (_AT + 1) / 2) * WIDTH for c in stretches])


def _hot(bins: np.ndarray, size: int) -> np.ndarray:
    out = np.zeros((len(bins), size))
    np.put_along_axis(out, bins, 1.0, axis=1)
    return out


def _node_sums(model: Ranker, x: np.ndarray, good: np.ndarray) -> Sums:
    out: Sums = {}
    for i in range(0, len(x), CHUNK):
        bins, label = model.bins(x[i : i + CHUNK]), good[i : i + CHUNK]
        rows = np.column_stack([np.ones(len(bins)), _hot(bins, len(model.weights))])
        stretch, shares = _shares(model.weights[bins].sum(1))
        for c in np.unique(stretch).tolist():
            for g in (False, True):
                mine = (stretch == c) & (label == g)
                if mine.any():
                    out[g, c] = out.get((g, c), 0) + shares[mine].T @ rows[mine]
    return out


def _bends(model: Ranker, x: np.ndarray, good: np.ndarray, bend: dict[tuple[bool, int], np.ndarray]) -> Sums:
    """The rows' own part of the second derivatives; bend has the sum of a row's pairs at the nodes."""
    size = len(model.weights)
    out = np.zeros((size, size))
    for i in range(0, len(x), CHUNK):
        bins, label = model.bins(x[i : i + CHUNK]), good[i : i + CHUNK]
        stretch, shares = _shares(model.weights[bins].sum(1))
        weight = np.zeros(len(bins))
        for (g, c), v in bend.items():
            mine = (stretch == c) & (label == g)
            weight[mine] = shares[mine] @ v
        hot = _hot(bins, size)
        out += hot.T @ (hot * weight[:, None])
    return {(True, 0): out}


def descend(model: Ranker, total: Callable[[Callable[[np.ndarray, np.ndarray], Sums]], Sums], l2: float, rounds: int = 100) -> Ranker:
    """The ranker that minimises the mean logistic loss of all good-bad pairs and half of l2 times the squared weights.

    total adds up what a function gives for parts (features, whether good) of all rows.
    """
    def state(w: np.ndarray):
        now = replace(model, weights=w)
        sums = total(lambda x, good: _node_sums(now, x, good))
        stretches = [sorted(c for g, c in sums if g == k) for k in (True, False)]
        a, b = (np.concatenate([sums[k, c] for c in found]) for k, found in zip((True, False), stretches, strict=True))
        gap = _places(stretches[1])[None, :] - _places(stretches[0])[:, None]
        pairs = a[:, 0].sum() * b[:, 0].sum()
        return now, stretches, a, b, gap, pairs, a[:, 0] @ np.logaddexp(0, gap) @ b[:, 0] / pairs + l2 / 2 * (w @ w)

    here = state(model.weights)
    for _ in range(rounds):
        now, stretches, a, b, gap, pairs, loss = here
        pull = 1 / (1 + np.exp(-np.clip(gap, -500, 500)))
        curve = pull * (1 - pull)
        slope = (b[:, 1:].T @ (pull.T @ a[:, 0]) - a[:, 1:].T @ (pull @ b[:, 0])) / pairs + l2 * now.weights
        sides = zip((True, False), stretches, (curve @ b[:, 0], curve.T @ a[:, 0]), strict=True)
        bend = {(k, c): v for k, found, all_v in sides for c, v in zip(found, all_v.reshape(-1, NODES), strict=True)}
        cross = a[:, 1:].T @ curve @ b[:, 1:]
        own = total(lambda x, good, now=now, bend=bend: _bends(now, x, good, bend))[True, 0]
        step = np.linalg.solve((own - cross - cross.T) / pairs + l2 * np.eye(len(slope)), -slope)
        gain, part = float(-slope @ step), 1.0
        here = state(now.weights + step)
        while here[-1] > loss - 1e-4 * part * gain + 1e-11 and part > 1e-6:
            part /= 2
            here = state(now.weights + part * step)
        if gain < 1e-14:
            break
    return replace(model, weights=np.round(here[0].weights, 9))  # further digits depend on the order of sums


def _blank(borders: Iterable[np.ndarray], place: float) -> Ranker:
    borders = tuple(np.unique(b) for b in borders)
    return Ranker(borders, np.zeros(sum(len(b) + 1 for b in borders)), 0.0, place)


def fit_pairs(x: np.ndarray, good: np.ndarray, place: float = 0.3, n_bins: int = 12, l2: float = 1e-3) -> Ranker:
    """The ranker of all good-bad pairs of the rows of x, in this process."""
    if not good.any() or good.all():
        return Ranker((), np.zeros(0), 0.0, place)
    inner = np.linspace(0, 1, n_bins + 1)[1:-1]
    model = descend(_blank((np.quantile(x[:, f], inner) for f in range(x.shape[1])), place), lambda part: part(x, good), l2)
    return replace(model, cut=float(np.quantile(model.raw(x), 1 - good.mean())))


def quantiles(values: DataFrame, shares: np.ndarray) -> dict[int, np.ndarray]:
    """Exact quantiles of `value` for each `kind`, straight between neighbours: equal values are counted, then sorted by ranges."""
    spark = values.sparkSession
    counted = values.groupBy("kind", "value").agg(F.count("*").alias("n"))
    ranged = written(counted.repartitionByRange("kind", "value").withColumn("pid", F.spark_partition_id()), "ranged")
    parts = sorted((r.kind, r.pid, r.n) for r in ranged.groupBy("kind", "pid").agg(F.sum("n").alias("n")).collect())
    total: dict[int, int] = {}
    for kind, _, n in parts:
        total[kind] = total.get(kind, 0) + n
    place = {kind: (n - 1) * np.asarray(shares) for kind, n in total.items()}
    ranks = {kind: np.unique(np.concatenate([np.floor(p), np.ceil(p)])).astype(np.int64) for kind, p in place.items()}
    asked, before = [], dict.fromkeys(total, 0)
    for kind, pid, n in parts:
        mine = ranks[kind][(ranks[kind] >= before[kind]) & (ranks[kind] < before[kind] + n)]
        asked += [(kind, pid, int(r), int(r) - before[kind]) for r in mine]
        before[kind] += n
    if not asked:
        return {}
    wanted = spark.createDataFrame(asked, "kind int, pid int, rank bigint, at bigint")
    upto = F.sum("n").over(Window.partitionBy("kind", "pid").orderBy("value").rowsBetween(Window.unboundedPreceding, 0))
    met = ranged.withColumn("upto", upto).join(F.broadcast(wanted), ["kind", "pid"]).where("at < upto AND at >= upto - n")
    found = {(r.kind, r["rank"]): r.value for r in met.select("kind", "rank", "value").collect()}
    remove_table(ranged)
    out = {}
    for kind, p in place.items():
        low, high = (np.array([found[kind, int(r)] for r in edge(p)]) for edge in (np.floor, np.ceil))
        out[kind] = low + (high - low) * (p - np.floor(p))
    return out


def measured(docs: DataFrame) -> DataFrame:
    """(doc_id, FEATURES) for every row of docs."""
    if set(FEATURES) <= set(docs.columns):
        return docs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.concatenate([*_batches(batch.column(1)), np.zeros((0, len(FEATURES)))])
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c) for c in x.T)], names=["doc_id", *FEATURES])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id bigint, " + ", ".join(f"{f} double" for f in FEATURES))


def _matrix(batch: pa.RecordBatch, first: int) -> np.ndarray:
    return np.column_stack([np.asarray(batch.column(first + f)) for f in range(len(FEATURES))])


def fit(docs: DataFrame, labels: DataFrame, place: float = 0.3, n_bins: int = 12, l2: float = 1e-3) -> Ranker:
    """A ranker from all labelled documents; docs have texts or are measured. Only sums by node reach the driver."""
    votes = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.avg("quality").alias("quality"))
    labelled = measured(docs).join(votes, "doc_id").select((F.col("quality") >= 0.5).alias("good"), *FEATURES)
    rows = written(labelled, "labelled")
    n, n_good = rows.agg(F.count("*"), F.coalesce(F.count_if("good"), F.lit(0))).first()
    if not n_good or n_good == n:
        return Ranker((), np.zeros(0), 0.0, place)
    kinds = F.explode(F.array(*[F.struct(F.lit(i).alias("kind"), F.col(f).alias("value")) for i, f in enumerate(FEATURES)])).alias("c")
    borders = quantiles(rows.select(kinds).select("c.*"), np.linspace(0, 1, n_bins + 1)[1:-1])
    few = rows.coalesce(min(TASKS, files_for(rows.sparkSession, n)))

    def total(part: Callable[[np.ndarray, np.ndarray], Sums]) -> Sums:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: Sums = {}
            for batch in batches:
                for key, v in part(_matrix(batch, 1), np.asarray(batch.column(0))).items():
                    sums[key] = sums.get(key, 0) + v
            keys = list(sums)
            yield pa.RecordBatch.from_arrays([pa.array([g for g, _ in keys], pa.bool_()), pa.array([c for _, c in keys], pa.int64()), pa.array([sums[k].shape[1] for k in keys], pa.int32()), pa.array([sums[k].tobytes() for k in keys], pa.binary())], names=["good", "stretch", "width", "sums"])

        out: Sums = {}
        for r in few.mapInArrow(run, "good boolean, stretch bigint, width int, sums binary").collect():
            out[r.good, r.stretch] = out.get((r.good, r.stretch), 0) + np.frombuffer(r.sums).reshape(-1, r.width)
        return out

    model = descend(_blank((borders[f] for f in range(len(FEATURES))), place), total, l2)

    def raw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(batch.num_rows), pa.int32()), pa.array(model.raw(_matrix(batch, 0)))], names=["kind", "value"])

    cut = quantiles(rows.select(*FEATURES).mapInArrow(raw, "kind int, value double"), np.array([1 - n_good / n]))[0][0]
    remove_table(rows)
    return replace(model, cut=float(cut))


def score(docs: DataFrame, model: Ranker) -> DataFrame:
    """(doc_id, score) for every row of docs, which have texts or are measured."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(_matrix(batch, 1)), pa.float64())], names=["doc_id", "score"])

    return measured(docs).select("doc_id", *FEATURES).mapInArrow(run, "doc_id bigint, score double")
