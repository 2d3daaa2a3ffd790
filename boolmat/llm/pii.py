"""Personal data by weak supervision.

Four base detectors find e-mail addresses, IP addresses, card numbers and phone numbers. Beside them, wider candidates
are drawn from every text: long letter-digit strings and digit groups that no base detector took. Regex, gazetteer and
context labelers vote on every candidate; expectation maximisation over the counts of vote patterns estimates how
reliable each labeler is; the posteriors then train a logistic span classifier on properties of the span. Base spans
always stand; the classifier adds further ones.

What reaches the driver are counts of (votes, properties) patterns, whose number is bounded by the product of their
few values, not by the data. The counts cover all candidates of all texts.

Defined cases: a null or empty text has no spans; spans are code points, end exclusive; repeated rows each give a row;
without candidates nothing is added.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "secret", "number")

# The shapes of the base detectors. Matching from the first character of a run only (look-behind,
# possessive repeats) finds the same leftmost matches as the plain patterns in linear time.
_MAIL_HOST = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_MAIL_USER = re.compile(r"[A-Za-z0-9._%+-]")
_IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_ISLAND = re.compile(r"[0-9+][0-9\x20().+-]{5,}")
_LONG = re.compile(r"(?<![0-9A-Za-z_])[0-9A-Za-z_]{20,}+")
_DIGITS = re.compile(r"[0-9](?:[\x20().-]{0,2}[0-9])+")
_NOT_DIGIT = re.compile(r"[^0-9]")


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2])) + sum(int(d) * 2 - (9 if d > "4" else 0) for d in digits[-2::-2])
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int, int]]:
    """For each @ in order: the run of user characters before it (not into the last match), and the host after it."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and _MAIL_USER.match(text[start - 1]):
            start -= 1
        if start < at and (m := _MAIL_HOST.match(text, at + 1)):
            yield start, m.end(), 0
            done = m.end()
        at = text.find("@", max(at + 1, done))


def _numbers(text: str, start: int, end: int) -> Iterator[tuple[int, int, int]]:
    """Base matches within one run of digits, signs and gaps; none reaches beyond such a run."""
    for m in _IP.finditer(text, start, end):
        if all(len(g.lstrip("0")) <= 3 and int(g) <= 255 for g in m.groups()):
            yield m.start(), m.end(), 1
    for m in _CARD.finditer(text, start, end):
        digits = _NOT_DIGIT.sub("", m[0]) if m.end() - m.start() < 60 else ""
        if 14 <= len(digits) <= 19 and luhn(digits):
            yield m.start(), m.end(), 2
    for m in _PHONE.finditer(text, start, end):
        if 10 <= sum(c in "0123456789" for c in m[0]) <= 15:
            yield m.start(), m.end(), 3


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind number) by start, then kind."""
    out = list(_emails(text)) if "@" in text else []
    for m in _ISLAND.finditer(text):
        out.extend(_numbers(text, m.start(), m.end()))
    return sorted(out, key=lambda s: (s[0], s[2], s[1]))


class _Intervals:
    """Disjoint stretches that cover the given spans; tells by bisection whether a span overlaps none."""

    def __init__(self, spans: list[tuple[int, int, int]]):
        self.starts, self.ends = [], []
        for s, e, _ in sorted(spans):
            if self.ends and s < self.ends[-1]:
                self.ends[-1] = max(self.ends[-1], e)
            else:
                self.starts.append(s)
                self.ends.append(e)

    def free(self, s: int, e: int) -> bool:
        at = bisect_right(self.ends, s)
        return at == len(self.ends) or self.starts[at] >= e


def candidates(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Further spans that may be personal: none overlaps a base span or another."""
    taken = _Intervals(base)
    out = []
    for m in _LONG.finditer(text):
        s, e = m.span()
        body = m[0]
        if not body.isdigit() and any(c.isdigit() for c in body) and taken.free(s, e):
            out.append((s, e, 4))
    taken = _Intervals(base + out)
    for m in _ISLAND.finditer(text):
        for d in _DIGITS.finditer(text, m.start(), m.end()):
            if d.end() - d.start() >= 7 and 7 <= sum(map(str.isdigit, d[0])) <= 20 and taken.free(*d.span()):
                out.append((*d.span(), 5))
    return out


# Words that speak for and against personal data when they stand before a span.
CUES = frozenset("token key secret password passwd pwd api apikey bearer auth credential login phone tel telephone mobile call fax email mail contact card visa mastercard iban account ssn passport ip host address".split())
AGAINST = frozenset("version isbn issn page pages figure table section chapter doi vol line lines item year sum total".split())
_WORD = re.compile(r"[^\W\d_]+")
LABELERS = ("regex_shape", "regex_strict", "gazetteer_cue", "gazetteer_against", "context_assigned", "context_bounded", "context_variety")


def votes(text: str, span: tuple[int, int, int]) -> tuple[int, ...]:
    """One vote per labeler: 1 personal, -1 not, 0 abstains."""
    s, e, kind = span
    body = text[s:e]
    before = text[max(0, s - 40) : s]
    near = [w.lower() for w in _WORD.findall(before)[-3:]]
    digits = _NOT_DIGIT.sub("", body)
    if kind < 4:
        if kind == 0:
            strict = body.rpartition(".")[2].isalpha()
        elif kind == 1:
            strict = not any(p != "0" and p.startswith("0") for p in body.split("."))
        else:
            strict = digits[0] in "3456" if kind == 2 else digits[0] != "0"
        shape, exact = 1, 1 if strict else -1
    elif kind == 4:
        hexa = all(c in "0123456789abcdefABCDEF" for c in body)
        shape = 1 if hexa or len(digits) * 4 >= len(body) else -1
        exact = 1 if hexa and len(body) in (32, 40, 56, 64, 96, 128) else 0
    else:
        shape, exact = (0 if len(digits) >= 9 else -1), (-1 if len(digits) < 9 else 0)
    cue = 1 if any(w in CUES for w in near) else 0
    against = -1 if any(w in AGAINST for w in near) else 0
    lead = before.rstrip(" \"'")
    assigned = (1 if lead.endswith(("=", ":")) else 0) if kind >= 4 else 0
    left, right = text[s - 1 : s], text[e : e + 1]
    bounded = -1 if left.isalnum() or right.isalnum() else (1 if not left or not right or left in " \t\n\"'(=:<[," else 0)
    kinds = len(set(body))
    variety = -1 if kinds * 5 < min(len(body), 30) else 0
    return shape, exact, cue, against, assigned, bounded, variety


def properties(text: str, span: tuple[int, int, int]) -> tuple[int, ...]:
    """What the classifier sees, each a small number: kind, length, digit share, variety, sign before, sign after."""
    s, e, kind = span
    body = text[s:e]
    n = len(body)
    digits = sum(c in "0123456789" for c in body)
    sign = lambda c: 0 if not c else 1 if c.isspace() else 2 if c.isalnum() else 3 if c in "\"'=:" else 4
    return kind, min(7, n // 8), min(4, 4 * digits // n), min(3, 4 * len(set(body)) // n), sign(text[s - 1 : s]), sign(text[e : e + 1])


#: Number of values of each property.
_SIZES = (len(KINDS), 8, 5, 4, 5, 5)


@dataclass(frozen=True)
class SpanModel:
    """reliability[labeler][y][vote + 1]; weights of the logistic classifier by property value; its threshold."""

    prior: float
    reliability: np.ndarray
    weights: np.ndarray
    bias: float
    threshold: float = 0.5

    def score(self, p: tuple[int, ...]) -> float:
        z, at = self.bias, 0
        for v, size in zip(p, _SIZES, strict=True):
            z += self.weights[at + v]
            at += size
        return float(1 / (1 + np.exp(-z)))


def fit_votes(patterns: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[float, np.ndarray, np.ndarray]:
    """(prior, reliabilities, posterior per pattern) by expectation maximisation; starts from the majority of votes."""
    post = np.clip(0.5 + 0.2 * patterns.sum(1), 0.05, 0.95)
    prior, rel = 0.5, np.zeros((patterns.shape[1], 2, 3))
    for _ in range(rounds):
        for y, w in ((0, counts * (1 - post)), (1, counts * post)):
            for j in range(patterns.shape[1]):
                seen = np.array([w[patterns[:, j] == v].sum() for v in (-1, 0, 1)])
                # a labeler is taken to be no worse than chance: prior counts lean to its own side
                rel[j, y] = (seen + (np.array([1.0, 2.0, 2.0]) if y else np.array([2.0, 2.0, 1.0]))) / (seen.sum() + 5.0)
        prior = float(np.clip((counts * post).sum() / counts.sum(), 0.02, 0.98))
        odds = np.full(len(patterns), np.log(prior / (1 - prior)))
        for j in range(patterns.shape[1]):
            odds += np.log(rel[j, 1, patterns[:, j] + 1]) - np.log(rel[j, 0, patterns[:, j] + 1])
        post = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
    return prior, rel, post


def fit_classifier(props: np.ndarray, soft: np.ndarray, counts: np.ndarray, rounds: int = 300, l2: float = 1e-3) -> tuple[np.ndarray, float]:
    """Logistic regression of the posteriors on one-hot properties by accelerated gradient steps."""
    shift = np.concatenate([[0], np.cumsum(_SIZES)[:-1]])
    where = props + shift
    w, b = np.zeros(sum(_SIZES)), 0.0
    vw, vb, total = np.zeros_like(w), 0.0, counts.sum()
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-(w[where].sum(1) + b)))
        err = counts * (p - soft) / total
        g = np.bincount(where.ravel(), np.repeat(err, where.shape[1]), minlength=len(w)) + l2 * w
        vw, vb = 0.9 * vw - 0.5 * g, 0.9 * vb - 0.5 * err.sum()
        w, b = w + vw, b + vb
    return w, float(b)


def fit(docs: DataFrame) -> SpanModel | None:
    """The model of all candidates in docs; None without any."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                if text:
                    base = base_spans(text)
                    for span in base + candidates(text, base):
                        seen[",".join(map(str, votes(text, span) + properties(text, span)))] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], names=["pattern", "n"])

    rows = docs.select("text").mapInArrow(count, "pattern string, n bigint").groupBy("pattern").agg(F.sum("n").alias("n")).orderBy("pattern").collect()
    if not rows:
        return None
    table = np.array([[int(v) for v in r[0].split(",")] for r in rows])
    counts = np.array([float(r[1]) for r in rows])
    k = len(LABELERS)
    prior, rel, post = fit_votes(table[:, :k], counts)
    weights, bias = fit_classifier(table[:, k:], post, counts)
    return SpanModel(prior, rel, weights, bias)


def all_spans(text: str, model: SpanModel | None) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base spans, base and added spans), each by start, then kind."""
    base = base_spans(text)
    added = [] if model is None else [s for s in candidates(text, base) if model.score(properties(text, s)) >= model.threshold]
    return base, sorted(base + added, key=lambda s: (s[0], s[2], s[1])) if added else base


def written_out(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, e, k in spans)


def find_spans(docs: DataFrame, model: SpanModel | None) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added) for every row; the counts are of base spans."""
    names = ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added"]
    kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(7)]
            for text in batch.column(1).to_pylist():
                base, spans = all_spans(text or "", model)
                per_kind = Counter(k for _, _, k in base)
                row = [*(per_kind[k] for k in range(4)), hashlib.sha256(written_out(base).encode()).hexdigest(), written_out(spans), len(spans) - len(base)]
                for c, v in zip(out, row, strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(out, kinds[1:], strict=True))], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string, n_added bigint")


def masked(text: str, spans: list[tuple[int, int, int]]) -> str:
    """text with every span (overlapping ones as one) replaced by its kind's name in angle brackets."""
    out, at = [], 0
    for s, e, k in spans:
        if e <= at:
            continue
        if s >= at:
            out += [text[at:s], f"<{KINDS[k].upper()}>"]
        at = e
    return "".join(out) + text[at:]


def redact(docs: DataFrame, model: SpanModel | None) -> DataFrame:
    """docs, all columns and rows, with personal data in `text` replaced; n_chars follows if it is there."""
    columns = docs.columns
    where = columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if t is None else masked(t, all_spans(t, model)[1]) for t in batch.column(where).to_pylist()]
            arrays = list(batch.columns)
            arrays[where] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(arrays, names=columns)

    out = docs.mapInArrow(run, docs.schema)
    if "n_chars" in columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out
