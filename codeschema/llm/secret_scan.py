"""Secret scans: fixed patterns, and a battery of randomness tests with false-discovery control.

Patterns give the base spans.  Besides, every long run of token characters is tested.  Its encoding is inferred as
the smallest alphabet that holds it; against that alphabet the battery measures the uniformity of its symbols
(chi-squared), the runs about the alphabet's middle and of its classes of characters, and the serial correlation of
the symbols' places.  Two distributions of these measures are simulated for each encoding and length, with fixed seeds: for uniform
symbols, and for ordinary tokens (sticky character classes, letters as in text).  They are combined in the
direction that tells the two apart; the p-value is the chance that an ordinary token gets as far towards
randomness, from the simulated tokens and, beyond them, the normal tail through their mean and spread.  A run that
speaks against randomness itself is no candidate.  Benjamini-Hochberg on these p-values then runs over all
runs of the corpus in each class of length; it needs no more than a histogram of them.  Encodings in which
ordinary tokens are as uniform as random ones (numbers) get no small p-values, so they need no exception.

Offsets are code points, ends exclusive.  Defined cases: a null text is an empty one and has no span;
texts of any length are scanned whole; an empty table gives no rows; repeated rows each get their spans.
Runs of over 256 symbols are measured whole and compared with tokens of 256.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import in_pieces, slices, written

# The base patterns and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")  # a run that is too short holds no other match
HEX = re.compile(r"[0-9a-f]{16,}")
ASSIGN_LEAST = 12
KINDS = ("assign", "access", "hex", "random")

CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
_DIGITS, _LOWER, _UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ENCODINGS = {"decimal": _DIGITS, "hex": _DIGITS + "abcdef", "HEX": _DIGITS + "ABCDEF", "lower": _LOWER, "upper": _UPPER, "base32": _UPPER + "234567", "alnum_lower": _DIGITS + _LOWER, "alnum_upper": _DIGITS + _UPPER, "letters": _UPPER + _LOWER, "base62": _UPPER + _LOWER + _DIGITS, "base64": _UPPER + _LOWER + _DIGITS + "+/", "base64url": _UPPER + _LOWER + _DIGITS + "-_", "mixed": _UPPER + _LOWER + _DIGITS + "+/-_="}
# Shares of letters in English text, in percent, from a to z.
LETTERS = (8.2, 1.5, 2.8, 4.3, 12.7, 2.2, 2.0, 6.1, 7.0, 0.15, 0.77, 4.0, 2.4, 6.7, 7.5, 1.9, 0.095, 6.0, 6.3, 9.1, 2.8, 0.98, 2.4, 0.15, 2.0, 0.074)
STAY = 0.85  # chance that an ordinary token goes on in the same class of characters
LENGTH_CLASSES = (24, 40)  # ends of the classes of length for the false-discovery control
LENGTHS = (12, 14, 16, 18, 20, 24, 28, 32, 40, 48, 64, 96, 128, 192, 256)  # for which tokens are simulated
SIMULATED = 8000
MOST_BITS = 400
RATE, RANDOM_LEAST_P = 0.001, 1e-3

_CLASSES = (_LOWER, _UPPER, _DIGITS, "+/-_=")
_SHARES = [np.array(LETTERS), np.array(LETTERS), np.ones(10), np.ones(5)]
_SETS = [(name, frozenset(chars), {c: i for i, c in enumerate(chars)}) for name, chars in ENCODINGS.items()]


def measures(x: np.ndarray, chars: str) -> np.ndarray:
    """Tokens (rows of places in an alphabet) x 4: uniformity, runs about the middle, runs of classes, serial correlation, each
    about standard normal for uniform symbols."""
    (rows, n), size = x.shape, len(chars)
    counts = np.bincount((x + size * np.arange(rows)[:, None]).ravel(), minlength=rows * size).reshape(rows, size)
    chi = (counts.astype(np.float64) ** 2).sum(axis=1) * size / n - n
    uniform = (chi - (size - 1)) / math.sqrt(2 * (size - 1) * (n - 1) / n)
    high = x >= size / 2
    n1 = high.sum(axis=1).astype(np.float64)
    mean = 1 + 2 * n1 * (n - n1) / n
    spread = np.sqrt(np.maximum((mean - 1) * (mean - 2) / (n - 1), 0))
    runs = 1 + (high[:, 1:] != high[:, :-1]).sum(axis=1)
    turns = np.where(spread > 0, (runs - mean) / np.where(spread > 0, spread, 1), -math.sqrt(n))
    kind = np.array([next(i for i, members in enumerate(_CLASSES) if c in members) for c in chars])
    change = 1 - ((np.bincount(kind) / size) ** 2).sum()
    switches = (kind[x][:, 1:] != kind[x][:, :-1]).sum(axis=1)
    classes = (switches - change * (n - 1)) / math.sqrt(max(change * (1 - change) * (n - 1), 1e-9)) if change else np.zeros(rows)
    d = x - x.mean(axis=1, keepdims=True)
    total = (d * d).sum(axis=1)
    r = np.where(total > 0, (d[:, 1:] * d[:, :-1]).sum(axis=1) / np.where(total > 0, total, 1), 1.0)
    return np.stack([uniform, turns, classes, (r + 1 / n) * math.sqrt(n)], axis=1)


def ordinary(chars: str, n: int, rows: int, rng: np.random.Generator) -> np.ndarray:
    """Simulated ordinary tokens over an alphabet: classes of characters that last, letters by their shares in text."""
    place = {c: i for i, c in enumerate(chars)}
    groups = []
    for members, shares in zip(_CLASSES, _SHARES, strict=True):
        some = [(place[c], w) for c, w in zip(members, shares, strict=True) if c in place]
        if some:
            p = np.array([w for _, w in some])
            groups.append((np.array([i for i, _ in some]), p / p.sum()))
    kind = np.empty((rows, n), np.int64)
    kind[:, 0] = rng.integers(0, len(groups), rows)
    for j in range(1, n):
        step = rng.integers(1, max(2, len(groups)), rows)
        kind[:, j] = np.where(rng.random(rows) < STAY, kind[:, j - 1], (kind[:, j - 1] + step) % len(groups))
    out = np.empty((rows, n), np.int64)
    for g, (places, p) in enumerate(groups):
        at = kind == g
        out[at] = rng.choice(places, int(at.sum()), p=p)
    return out


class Nulls:
    """What the measures of one encoding and length are like for ordinary tokens and for random ones."""

    def __init__(self, name: str, n: int) -> None:
        chars, rng = ENCODINGS[name], np.random.default_rng([len(ENCODINGS[name]), n, sum(map(ord, name))])
        common = measures(ordinary(chars, n, SIMULATED, rng), chars)
        random = measures(rng.integers(0, len(chars), (SIMULATED, n)), chars)
        self.center = random.mean(axis=0)
        self.inverse = np.linalg.inv(np.cov(random.T) + 1e-9 * np.eye(4))
        self.farthest = float(np.quantile([self.against(x) for x in random], 1 - RANDOM_LEAST_P))
        self.way = np.linalg.solve(np.cov(common.T) + np.cov(random.T) + 1e-9 * np.eye(4), self.center - common.mean(axis=0))
        scores = np.sort(common @ self.way)
        self.scores, self.mean, self.spread = scores, float(scores.mean()), max(float(scores.std()), 1e-9)
        # Where the two are alike there is nothing to tell them by.
        self.apart = float(self.center @ self.way - self.mean) > self.spread

    def against(self, measured: np.ndarray) -> float:
        """How far the measures speak against randomness: symbols too unequal, runs too few, neighbours too much alike."""
        d = measured - self.center
        d = np.array([max(d[0], 0.0), min(d[1], 0.0), min(d[2], 0.0), max(d[3], 0.0)])
        return float(d @ self.inverse @ d)

    def p_value(self, measured: np.ndarray) -> float:
        """Chance that an ordinary token gets as far towards randomness; 1 for what random symbols would hardly give."""
        if not self.apart or self.against(measured) > self.farthest:
            return 1.0
        score = float(measured @ self.way)
        beyond = len(self.scores) - int(np.searchsorted(self.scores, score))
        tail = 0.5 * math.erfc((score - self.mean) / self.spread / math.sqrt(2))
        return max(tail, (beyond + 1) / (len(self.scores) + 1) if beyond else 0.0)


@cache
def nulls(name: str, n: int) -> Nulls:
    return Nulls(name, n)


def evidence(token: str) -> int | None:
    """The p-value of the token's battery in bits (-log2, rounded down); None if nothing speaks for a secret."""
    core = token.rstrip("=")
    chars = set(core)
    if len(core) < LENGTHS[0] or len(chars) < 6:
        return None
    for name, members, place in _SETS:
        if chars <= members:
            break
    else:
        return None
    n = LENGTHS[bisect_right(LENGTHS, len(core)) - 1]
    p = nulls(name, n).p_value(measures(np.array([[place[c] for c in core]]), ENCODINGS[name])[0])
    bits = MOST_BITS if p < 2.0**-MOST_BITS else int(-math.log2(p))
    return bits if bits > 0 else None


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, number of kind, end), sorted."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def length_class(n: int) -> int:
    return sum(n >= x for x in LENGTH_CLASSES)


def scan(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]], list[int]]:
    """(base spans, candidates (start, end, bits) beside them, number of tested runs by class of length)."""
    base = base_spans(text)
    found, tested = [], [0] * (len(LENGTH_CLASSES) + 1)
    for m in CANDIDATE.finditer(text):
        a, b = m.span()
        tested[length_class(b - a)] += 1
        bits = evidence(m.group())
        if bits is not None and not any(x < b and a < y for x, _, y in base):
            found.append((a, b, bits))
    return base, found, tested


def thresholds(histogram: dict[tuple[int, int], int], tested: dict[int, int], rate: float = RATE) -> list[int]:
    """Benjamini-Hochberg by class of length: the least evidence, in bits, that counts as a discovery.

    histogram: (class, bits) -> candidates; tested: class -> hypotheses.
    """
    out = []
    for c in range(len(LENGTH_CLASSES) + 1):
        least, found = MOST_BITS + 1, 0
        for bits in range(MOST_BITS, 0, -1):
            n = histogram.get((c, bits), 0)
            found += n
            if n and 2.0**-bits * max(1, tested.get(c, 0)) <= rate * found:
                least = bits
        out.append(least)
    return out


_SCANNED = "doc_id long, base array<struct<start:int,kind:int,end:int>>, found array<struct<start:int,end:int,bits:int>>, tested array<long>"


def scanned(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, base spans, candidates, numbers of tested runs."""
    base_type = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())]))
    found_type = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("bits", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_pieces(batches, 1):
            base, found, tested = [], [], []
            for t in batch.column(1).to_pylist():
                b, f, n = scan(t or "")
                base.append([dict(zip(("start", "kind", "end"), x, strict=True)) for x in b])
                found.append([dict(zip(("start", "end", "bits"), x, strict=True)) for x in f])
                tested.append(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, base_type), pa.array(found, found_type), pa.array(tested, pa.list_(pa.int64()))], names=["doc_id", "base", "found", "tested"])

    wanted = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return wanted.mapInArrow(run, _SCANNED)


def fit_thresholds(rows: DataFrame, rate: float = RATE) -> list[int]:
    """Thresholds from all candidates; what comes to the driver is a histogram of bounded size."""
    ends = [F.lit(x) for x in LENGTH_CLASSES]
    f = rows.select(F.explode("found").alias("f"))
    kind = sum((F.when(F.col("f.end") - F.col("f.start") >= x, 1).otherwise(0) for x in ends), F.lit(0))
    histogram = {(r["c"], r["bits"]): r["n"] for r in f.groupBy(kind.alias("c"), F.col("f.bits").alias("bits")).agg(F.count("*").alias("n")).collect()}
    sums = rows.agg(*[F.sum(F.col("tested")[i]).alias(f"t{i}") for i in range(len(LENGTH_CLASSES) + 1)]).first()
    return thresholds(histogram, {i: sums[f"t{i}"] or 0 for i in range(len(LENGTH_CLASSES) + 1)}, rate)


def discoveries(rows: DataFrame, least: list[int]) -> DataFrame:
    """doc_id, spans array<struct<start, kind, end>>: base spans and what the tests add, sorted."""

    def bound(x):
        n = x["end"] - x["start"]
        return F.when(n >= LENGTH_CLASSES[1], least[2]).when(n >= LENGTH_CLASSES[0], least[1]).otherwise(least[0])

    added = F.transform(F.filter("found", lambda x: x["bits"] >= bound(x)), lambda x: F.struct(x["start"].alias("start"), F.lit(3).alias("kind"), x["end"].alias("end")))
    return rows.withColumn("spans", F.array_sort(F.concat("base", added)))


def find_secrets(docs: DataFrame, rate: float = RATE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, base, spans of every document."""
    rows = written(scanned(docs, id_col, text_col), "secrets")
    return discoveries(rows, fit_thresholds(rows, rate)).select("doc_id", "base", "spans")


def digests(found: DataFrame) -> DataFrame:
    kinds = F.array(*[F.lit(k) for k in KINDS])

    def said(column: str):
        return F.array_join(F.transform(column, lambda x: F.concat_ws(":", F.element_at(kinds, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")

    def count(kind: int):
        return F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long")

    return found.select("doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.sha2(said("base"), 256).alias("base_sha256"), said("spans").alias("spans"))


def redacted(docs: DataFrame, rate: float = RATE, put: str = "<secret>", text_col: str = "text") -> DataFrame:
    """``docs`` with every span replaced by ``put``; texts without a span stay as they are.

    Thresholds come from a first pass over all texts, of which only the histogram is kept.
    """
    least = fit_thresholds(scanned(docs, docs.columns[0] if "doc_id" not in docs.columns else "doc_id", text_col), rate)
    at, names = docs.columns.index(text_col), docs.columns

    def clean(text: str | None) -> str | None:
        if not text:
            return text
        base, found, _ = scan(text)
        spans = sorted([(a, b) for a, _, b in base] + [(a, b) for a, b, bits in found if bits >= least[length_class(b - a)]])
        if not spans:
            return text
        out, done = [], 0
        for a, b in spans:
            if a >= done:
                out += [text[done:a], put]
            done = max(done, b)
        return "".join([*out, text[done:]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_pieces(batches, at):
            texts = batch.column(at).to_pylist()
            for i, j in slices([t or "" for t in texts], 4_000_000):
                columns = [c.slice(i, j - i) for c in batch.columns]
                columns[at] = pa.array([clean(t) for t in texts[i:j]], pa.string())
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.withColumn(text_col, F.col(text_col).cast("string")).mapInArrow(run, docs.schema)
