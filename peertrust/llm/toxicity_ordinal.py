"""Toxicity grades by cumulative-link ordinal regression on sparse text features.

``P(grade <= k) = sigmoid(theta_k - w.x)`` with ordered thresholds and one weight
vector for all of them; ``x`` marks which hashed words, and heads of words, a text
holds.  An L1 penalty keeps the weights sparse, so only telling ones have any.
Scores are the expected grade; a text is toxic from that probability of a grade
above 0 on which parts toxic from other texts of the sample best.

Any integer column of grades 0..K works.  The given labels only say toxic or not;
``severity_grades`` parts their toxic half in two: a first fit with one threshold
finds the telling words, and texts that hold more of them to the word than the
median toxic text get grade 2.

Training takes at most ``SAMPLE_ROWS`` labelled texts, those with the smallest
hashed ids (the sample is broadcast to find them, and their distinct hashed words, at
most ``BUCKETS`` of four bytes each a text, come to the driver).  They are taken in the
order of their ids, and a hash of the id says which of them set the cut, so the order
of the tables changes nothing.  Scoring covers every whole text, without a shuffle.

Defined results: null and empty texts have no features and get the base rates; a
label table with fewer than two grades gives every text its one grade (0, if none);
rows that repeat a labelled id count once, with the one whose features come last.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text, slices, utf8
from .quality_resampling import parting_value
from .wordhash import tokens

BUCKETS, SAMPLE_ROWS = 1 << 18, 20_000
#: Bytes of a word's head.
PREFIX = 4
#: A share of clean texts called toxic weighs as much as so many missed ones.
_FALSE_ALARM = 5.0
_ROUNDS, _L1, _LEAST_TEXTS = 150, 3e-3, 4


def hashed_words(buf: np.ndarray, offsets: np.ndarray, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    text, word = tokens(buf, offsets, "words", PREFIX)
    return text, (word % np.uint64(buckets)).astype(np.int64)


def distinct_words(buf: np.ndarray, offsets: np.ndarray, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    text, word = hashed_words(buf, offsets, buckets)
    both = np.unique(text * buckets + word)
    return both // buckets, both % buckets


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


class OrdinalModel:
    """Weights of hashed words, and the ordered thresholds."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray, cut: float = 0.5):
        self.weights, self.thresholds, self.cut = weights, thresholds, cut

    def cumulative(self, margin: np.ndarray) -> np.ndarray:
        """``P(grade <= k)`` for each threshold."""
        return _sigmoid(self.thresholds[None, :] - margin[:, None])

    def probabilities(self, margin: np.ndarray) -> np.ndarray:
        c = self.cumulative(margin)
        return np.diff(np.concatenate([np.zeros((len(c), 1)), c, np.ones((len(c), 1))], axis=1), axis=1)

    def margins(self, buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        text, word = hashed_words(buf, offsets, len(self.weights))
        telling = np.flatnonzero(self.weights[word])
        both = np.unique(text[telling] * len(self.weights) + word[telling])
        n = len(offsets) - 1
        return np.bincount(both // len(self.weights), weights=self.weights[both % len(self.weights)], minlength=n)[:n].astype(np.float64)


def train(row: np.ndarray, word: np.ndarray, grade: np.ndarray, buckets: int = BUCKETS, rounds: int = _ROUNDS, l1: float = _L1) -> OrdinalModel:
    """Adaptive proximal gradients on the mean log-likelihood; ``row, word`` are the
    ones of the design matrix.  Words of fewer than four texts are left out."""
    n, top = len(grade), int(grade.max(initial=0))
    if len(np.unique(grade)) < 2:
        # nothing to tell apart: the one grade is all but certain
        return OrdinalModel(np.zeros(buckets), np.array([-13.8 if n and top else 13.8]))
    share = np.clip([(grade <= k).mean() for k in range(top)], 1e-6, 1 - 1e-6)
    # only words whose slope at the start is half the penalty or more can come in
    edges = np.concatenate([[0.0], share, [1.0]])
    slope = (1 - edges[grade + 1]) - edges[grade]
    texts, pull = np.bincount(word, minlength=buckets), np.bincount(word, weights=slope[row], minlength=buckets) / n
    used = np.flatnonzero((texts >= _LEAST_TEXTS) & (np.abs(pull) >= l1 / 2))
    place = np.full(buckets, -1)
    place[used] = np.arange(len(used))
    keep = place[word] >= 0
    row, col = row[keep], place[word[keep]]
    base = np.log(share / (1 - share))
    first, gaps = base[0], np.log(np.maximum(np.diff(base), 1e-6))
    w = np.zeros(len(used))
    params = np.concatenate([[first], gaps])
    grads_w, grads_p = np.full(len(used), 1e-8), np.full(top, 1e-8)
    y_low, y_high = grade > 0, grade < top
    for i in range(2 * rounds):
        if i == rounds:  # the penalty has chosen the words; now they get their full weights
            l1, chosen = 0.0, w != 0
            grads_w[:] = 1e-8
        theta = params[0] + np.concatenate([[0], np.cumsum(np.exp(params[1:]))])
        margin = np.bincount(row, weights=w[col], minlength=n)
        upper = np.where(y_high, _sigmoid(theta[np.minimum(grade, top - 1)] - margin), 1.0)
        lower = np.where(y_low, _sigmoid(theta[np.maximum(grade - 1, 0)] - margin), 0.0)
        p = np.maximum(upper - lower, 1e-12)
        du, dl = upper * (1 - upper) / p, lower * (1 - lower) / p
        g_margin = (du - dl) / n  # of the negative log-likelihood
        g_w = np.bincount(col, weights=g_margin[row], minlength=len(used))
        if i >= rounds:
            g_w = np.where(chosen, g_w + 1e-4 * w, 0)
        g_theta = np.bincount(np.minimum(grade, top - 1)[y_high], weights=-du[y_high] / n, minlength=top) + np.bincount(np.maximum(grade - 1, 0)[y_low], weights=dl[y_low] / n, minlength=top)
        tail = np.cumsum(g_theta[::-1])[::-1]
        g_p = np.concatenate([[tail[0]], tail[1:] * np.exp(params[1:])])
        grads_w += g_w**2
        grads_p += g_p**2
        step = 0.2 / np.sqrt(grads_w)
        w -= step * g_w
        w = np.sign(w) * np.maximum(np.abs(w) - step * l1, 0)
        params -= 0.2 / np.sqrt(grads_p) * g_p
    weights = np.zeros(buckets)
    weights[used] = w
    return OrdinalModel(weights, params[0] + np.concatenate([[0], np.cumsum(np.exp(params[1:]))]))


def labelled_sample(labels: DataFrame, column: str = "toxic", rows: int = SAMPLE_ROWS) -> DataFrame:
    """``label_id, grade``: at most ``rows`` labels, the same ones on every run."""
    grade = F.col(column).cast("int")
    known = labels.filter(F.col("doc_id").isNotNull() & grade.isNotNull()).groupBy(F.col("doc_id").cast("long").alias("label_id")).agg(F.max(grade).alias("grade"))
    return known.orderBy(F.xxhash64("label_id"), "label_id").limit(rows)


def severity_grades(model: OrdinalModel, row: np.ndarray, word: np.ndarray, grade: np.ndarray) -> np.ndarray:
    """Grades 0, 1, 2 from 0 and 1, by the density of telling words."""
    n = len(grade)
    density = np.bincount(row, weights=model.weights[word] > 0, minlength=n) / np.maximum(np.bincount(row, minlength=n), 1)
    toxic = grade > 0
    return np.where(toxic, 1 + (density > np.median(density[toxic])), 0) if toxic.any() else grade


def fit(docs: DataFrame, sample: DataFrame, buckets: int = BUCKETS, refine: bool = True) -> OrdinalModel:
    """``sample``: ``label_id, grade``, bounded by its maker.  ``refine``: grades
    that are only 0 and 1 are made three by ``severity_grades``."""

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                text, word = distinct_words(*utf8(part.column(0)), buckets)
                cut = np.searchsorted(text, np.arange(1, part.num_rows))
                yield pa.RecordBatch.from_arrays([pa.array([w.astype(np.int32).tobytes() for w in np.split(word, cut)], pa.binary()), part.column(1), part.column(2)], names=["words", "grade", "label_id"])

    rows = id_and_text(docs)
    known = rows.join(F.broadcast(sample), rows.doc_id == sample.label_id).select("text", "grade", "label_id")
    features = known.mapInArrow(words, "words binary, grade int, label_id long").groupBy("label_id", "grade").agg(F.max("words").alias("words"), F.min(F.pmod(F.xxhash64("label_id", F.lit(5)), F.lit(5))).alias("part"))
    found = sorted(features.collect(), key=lambda r: r.label_id)  # as many as the sample has
    data = [np.frombuffer(r.words, np.int32) for r in found]
    row = np.repeat(np.arange(len(data)), [len(d) for d in data]) if data else np.empty(0, np.int64)
    word = np.concatenate(data).astype(np.int64) if data else np.empty(0, np.int64)
    grade = np.array([r.grade for r in found], np.int64)
    if len(np.unique(grade)) < 2:
        return train(row, word, grade, buckets)
    # a fifth of the texts sets the cut, the others train
    held = np.array([r.part for r in found]) == 4
    seen = ~held[row]
    row_t, word_t, grade_t = (np.cumsum(~held) - 1)[row[seen]], word[seen], grade[~held]
    model = train(row_t, word_t, grade_t, buckets)
    if refine and grade_t.max() == 1 and len(np.unique(finer := severity_grades(model, row_t, word_t, grade_t))) == 3:
        model = train(row_t, word_t, finer, buckets)
    margin = np.bincount(row, weights=model.weights[word], minlength=len(grade))
    model.cut = parting_value(1 - model.probabilities(margin)[held, 0], grade[held] > 0, 0.5, _FALSE_ALARM)
    return model


def score(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """``doc_id, expected_severity, p_toxic, grade, toxic`` of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                p = shared.value.probabilities(shared.value.margins(*utf8(part.column(1))))
                toxic = 1 - p[:, 0]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(p @ np.arange(p.shape[1])), pa.array(toxic), pa.array(p.argmax(axis=1).astype(np.int32)), pa.array(toxic >= shared.value.cut)],
                    names=["doc_id", "expected_severity", "p_toxic", "grade", "toxic"],
                )

    return id_and_text(docs).mapInArrow(run, "doc_id long, expected_severity double, p_toxic double, grade int, toxic boolean")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op8``: severity of all documents."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    return score(docs, fit(docs, labelled_sample(labels)))
