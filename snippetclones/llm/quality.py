"""Operator 9 - quality by ordinal cumulative-link regression on graded ratings.

One weight vector over hashed text features is shared by all grades; ordered
thresholds cut its score, so that P(grade <= k) = sigmoid(threshold_k - score).
The model gives the expected grade and the tail probability P(grade >= accept),
and documents are selected by the tail probability.

Features of a text, hashed to ``DIMS`` places; those seen in at least ``MIN_DOCS``
fitted documents whose presence depends on the grade (chi-square above
``MIN_GAIN``, less for few rows) carry weight, the others stay at zero and aren't stored: each distinct lower-cased word's
core, each word's shape (letter case and the punctuation around it), and the
tenth in which the share of words that repeat the one before falls.  Core words
count by presence, shapes by their share of the words.

Fitting takes at most ``ROWS`` labelled rows, chosen by hash (documented bound);
features are made on the executors and only sparse rows reach the driver.

Edge cases: null and empty texts have no features and get the thresholds' own
probabilities; rows without a usable grade aren't fitted; with fewer than two
grades, or where no feature depends on the grade, there is no model: every
document has tail probability 1 and nothing is rejected; an empty table gives no
rows; repeated rows are rated alike; input columns named like an output are replaced.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import TwoGenerations, held, in_order, named

BITS, ROWS, STEPS, RATE, RIDGE, WORDS_MEMO, MIN_DOCS, MIN_GAIN = 26, 6000, 300, 0.1, 1e-6, 60_000, 8, 60.0
DIMS = 1 << BITS
REJECT_BELOW = 0.5
SHAPES = re.compile(r"[^\W\d_]+")
EDGES = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum())
SHAPE_WEIGHT = 12.0


def _place(name: str) -> int:
    return xxhash.xxh64_intdigest(name, 9) & (DIMS - 1)


def _word(word: str) -> tuple[int, int]:
    """Places of a word's core and of its shape."""
    core = word.strip(EDGES).lower()
    shape = SHAPES.sub(lambda m: "A" if len(m[0]) > 1 and m[0].isupper() else "a", word)
    return _place("w" + core) if core else _place("w"), _place("s" + shape[:24])


REPEATS = [_place(f"repeats{i}") for i in range(11)]


def words_memo() -> TwoGenerations:
    """The places of words that this Python worker has met lately."""
    return held("words", WORDS_MEMO, lambda: TwoGenerations(WORDS_MEMO))


def features(text: str | None, memo: TwoGenerations | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Places and values of one whole text."""
    words = (text or "").split()
    if not words:
        return np.zeros(0, np.int64), np.zeros(0)
    memo = TwoGenerations(WORDS_MEMO) if memo is None else memo
    pairs = []
    for w in words:
        pair = memo.young.get(w) or memo.get(w)
        if pair is None:
            pair = _word(w)
            if len(w) <= 64:
                memo.put(w, pair)
        pairs.append(pair)
    cores, shapes = np.array(pairs, np.int64).T
    places, inverse = np.unique(shapes, return_counts=True)
    core = np.unique(cores)
    repeats = sum(map(str.__eq__, words[1:], words[:-1]))
    n = len(words)
    often = [REPEATS[10 * repeats // n]] if 10 * repeats >= n else []
    at = np.concatenate([core, places, often]).astype(np.int64)
    value = np.concatenate([np.ones(len(core)), SHAPE_WEIGHT * inverse / n, np.full(len(often), SHAPE_WEIGHT)])
    return at, value


@dataclass
class OrdinalModel:
    places: np.ndarray  # ascending
    weights: np.ndarray
    thresholds: np.ndarray
    grades: list[int]

    def score(self, text: str | None, memo: TwoGenerations | None = None) -> float:
        return self.of(*features(text, memo))

    def of(self, at: np.ndarray, value: np.ndarray) -> float:
        i = np.minimum(np.searchsorted(self.places, at), len(self.places) - 1)
        return float((self.weights[i] * value) @ (self.places[i] == at)) if len(at) else 0.0

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade >= k) for each grade but the least."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - np.atleast_1d(score)[:, None], -500, 500)))

    def expected(self, score: np.ndarray) -> np.ndarray:
        steps = np.diff(np.array(self.grades, float))
        return self.grades[0] + self.tails(score) @ steps


def fit_rows(rows: list[tuple[np.ndarray, np.ndarray, int]], steps: int = STEPS) -> OrdinalModel | None:
    """Maximise the cumulative-link likelihood with a ridge penalty by Adam; rarer grades weigh more, up to a factor of four."""
    grades = sorted({r[2] for r in rows})
    if len(grades) < 2:
        return None
    y = np.array([grades.index(r[2]) for r in rows])
    at = np.concatenate([r[0] for r in rows])
    value = np.concatenate([r[1] for r in rows])
    owner = np.repeat(np.arange(len(rows)), [len(r[0]) for r in rows])
    places, at, docs = np.unique(at, return_inverse=True, return_counts=True)
    held = docs >= min(MIN_DOCS, max(1, len(rows) // 50))
    chi = np.zeros(len(places))
    for g, n in enumerate(np.bincount(y)):
        expect = docs * (n / len(y))
        chi += (np.bincount(at[y[owner] == g], minlength=len(places)) - expect) ** 2 / expect
    held &= chi >= min(MIN_GAIN, max(20.0, len(rows) / 100), chi[held].max() / 2) if held.any() else held
    if not held.any():
        return None
    fitted = held[at]
    at, value, owner, places = (np.cumsum(held) - 1)[at[fitted]], value[fitted], owner[fitted], places[held]
    dims = len(places)
    count = np.bincount(y)
    weight = np.minimum(4.0, count.max() / count)[y]
    weight /= weight.sum()
    w = np.zeros(dims)
    cut = np.cumsum(count)[:-1] / len(y)
    first = np.log(cut / (1 - cut))
    raw = np.concatenate([first[:1], np.log(np.maximum(np.diff(first), 1e-3))])  # ordered by construction
    mw, vw, mt, vt = np.zeros(dims), np.zeros(dims), np.zeros(len(raw)), np.zeros(len(raw))
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
    rowsn = np.arange(len(y))
    for step in range(1, steps + 1):
        theta = np.cumsum(np.concatenate([raw[:1], np.exp(raw[1:])]))
        score = np.bincount(owner, value * w[at], len(y))
        below = np.concatenate([np.zeros((len(y), 1)), sig(theta[None, :] - score[:, None]), np.ones((len(y), 1))], axis=1)
        hi, lo = below[rowsn, y + 1], below[rowsn, y]
        p = np.maximum(hi - lo, 1e-12)
        dhi, dlo = hi * (1 - hi) / p * weight, lo * (1 - lo) / p * weight
        grad_score = dhi - dlo  # of the negative log-likelihood
        gw = np.bincount(at, value * grad_score[owner], dims) + RIDGE * w
        gt = np.bincount(y, -dhi, len(theta) + 1)[:-1] + np.bincount(y, dlo, len(theta) + 1)[1:]
        tail = np.cumsum(gt[::-1])[::-1]
        graw = tail * np.concatenate([[1.0], np.exp(raw[1:])])
        mw, vw = 0.9 * mw + 0.1 * gw, 0.999 * vw + 0.001 * gw**2
        mt, vt = 0.9 * mt + 0.1 * graw, 0.999 * vt + 0.001 * graw**2
        scale = RATE * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
        w -= scale * mw / (np.sqrt(vw) + 1e-9)
        raw -= scale * mt / (np.sqrt(vt) + 1e-9)
    return OrdinalModel(places, w, np.cumsum(np.concatenate([raw[:1], np.exp(raw[1:])])), grades)


def graded(labels: DataFrame) -> DataFrame:
    """``(doc_id, grade)``: 0 toxic, 1 of low quality, 2 good; repeated ids keep their least grade; rows without both labels drop out."""
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 1, 2).when(F.col("quality") == 0, 1)
    return labels.select(F.col("doc_id").cast("long").alias("doc_id"), grade.alias("grade")).where(F.col("doc_id").isNotNull() & F.col("grade").isNotNull()).groupBy("doc_id").agg(F.min("grade").alias("grade"))


def fit(docs: DataFrame, grades: DataFrame, rows: int = ROWS, doc_id: str = "doc_id", text: str = "text") -> OrdinalModel | None:
    """Fit on at most ``rows`` graded documents, those with the least hashes of their id."""
    picked = grades.orderBy(F.xxhash64(F.lit(17), "doc_id"), "doc_id").limit(rows)
    source = docs.select(named(doc_id).cast("long").alias("doc_id"), named(text).cast("string").alias("t")).join(F.broadcast(picked), "doc_id")  # at most `rows` ids

    def run(batches):
        memo = words_memo()
        for b in batches:
            got = [features(t.as_py(), memo) for t in b["t"]]
            yield pa.RecordBatch.from_arrays([pa.array([g[0].astype(np.int32) for g in got], pa.list_(pa.int32())), pa.array([g[1].astype(np.float32) for g in got], pa.list_(pa.float32())), b["grade"].cast(pa.int32()), b["doc_id"]], names=["at", "value", "grade", "doc_id"])

    sparse = source.select("t", "grade", "doc_id").mapInArrow(run, "at array<int>, value array<float>, grade int, doc_id long").orderBy("doc_id").limit(rows).toArrow()
    return fit_rows([(np.asarray(sparse["at"][i].values, dtype=np.int64), np.asarray(sparse["value"][i].values, dtype=float), sparse["grade"][i].as_py()) for i in range(sparse.num_rows)])


def rate(docs: DataFrame, model: OrdinalModel | None, accept: int = 2, reject_below: float = REJECT_BELOW, text: str = "text") -> DataFrame:
    """All columns of ``docs`` plus ``expected_grade``, ``p_accept`` = P(grade >= accept) and ``keep``. Narrow map, no shuffle."""
    new = ["expected_grade", "p_accept", "keep"]
    kept = [c for c in docs.columns if c.lower() not in new]
    schema = T.StructType([*(docs.schema[c] for c in kept), T.StructField("expected_grade", T.DoubleType()), T.StructField("p_accept", T.DoubleType()), T.StructField("keep", T.BooleanType())])
    shared = docs.sparkSession.sparkContext.broadcast(model)  # at most the features of ROWS documents, over MIN_DOCS
    at = next(i for i, c in enumerate(kept) if c.lower() == text.lower())

    def run(batches):
        own, memo = shared.value, words_memo()
        for b in batches:
            if own is None:
                expected, tail = np.full(b.num_rows, float(accept)), np.ones(b.num_rows)
            else:
                score = np.array([own.score(t.as_py(), memo) for t in b.column(at)])
                expected = own.expected(score)
                column = next((i for i, g in enumerate(own.grades[1:]) if g >= accept), None)
                tail = own.tails(score)[:, column] if column is not None else np.zeros(b.num_rows)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(expected), pa.array(tail), pa.array(tail >= reject_below)], names=[*kept, *new])

    return in_order(docs.select(*map(named, kept))).mapInArrow(run, schema)
