"""Quality by importance resampling with hashed n-gram models.

Two bags of hashed unigrams and bigrams are counted: the raw model over all
documents, the target model over labelled good ones.  A document's importance is
the ratio of the likelihoods of ``SPAN`` n-grams like its own (their geometric mean, to
the power of ``SPAN``), so that documents of all lengths are judged alike and a small
drift of the models does not add up to a verdict on long ones; ``k`` documents are
drawn without replacement, in proportion to it, by taking the ``k`` largest of
log-importance plus Gumbel noise.

* Counts are summed with one row per bucket and partition, so the driver gets
  ``2 * BUCKETS`` numbers, whatever the corpus.
* The labelled rows are a bounded sample: the ``SAMPLE_ROWS`` labels with the
  smallest hashed ids.  It is small enough to be broadcast.  Half of it makes the
  target model, the other half parts good from bad.  Everything else covers all
  documents.
* ``k``, unless the caller gives one, is the number of documents whose importance
  lies above the value that best parts good from bad rows of the sample (where the
  sample has one kind only: above even odds, by the share).
* The ``k``-th largest key is found by counting in bins and looking into one bin
  again, not by sorting or collecting.

A longer ``SPAN`` lets the model say more about a document: the draw gets sharper.
The noise is always that of a draw in proportion to the importance, and comes from a
hash of the id and a seed, so runs agree.

A word that repeats the one before it counts as a mark for repetition, so stuttered
text shows in the models.

Defined results: texts without any token have importance 1 (logarithm 0) and are
judged by the noise and the threshold as all others are; where no labelled document
is good there is no target, every importance is 1 and all documents are drawn; rows
that repeat an id share its noise.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytehash import mix
from .common import id_and_text, shared_dir, slices, utf8
from .wordhash import tokens

BUCKETS, SAMPLE_ROWS, SEED = 1 << 14, 20_000, 17
#: N-grams that a document's importance stands for.
SPAN = 20.0
#: Counts that a bucket is worth before it is counted: rare n-grams say little.
PRIOR = 100.0
_REPEAT = np.uint64(0xA0761D6478BD642F)
_BINS = 4096


def ngrams(buf: np.ndarray, offsets: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """``text number, bucket`` of every hashed unigram and bigram."""
    text, word = tokens(buf, offsets, "wordpunct")
    if not len(word):
        return text, word.astype(np.int64)
    same = text[1:] == text[:-1]
    pair = mix(word[:-1] * np.uint64(0x9E3779B97F4A7C15) + (word[1:] ^ np.uint64(0xD6E8FEB86659FD93)))
    pair = np.where(word[1:] == word[:-1], _REPEAT, pair)[same]
    return np.concatenate([text, text[:-1][same]]), (np.concatenate([word, pair]) % np.uint64(buckets)).astype(np.int64)


def labelled_sample(labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """``label_id, good, half``: at most ``rows`` labels, the same on every run."""
    known = labels.filter(F.col("doc_id").isNotNull() & F.col("quality").isNotNull())
    known = known.groupBy(F.col("doc_id").cast("long").alias("label_id")).agg(F.max(F.col("quality").cast("int")).alias("good"))
    return known.orderBy(F.xxhash64("label_id"), "label_id").limit(rows).withColumn("half", F.pmod(F.xxhash64("label_id", F.lit(1)), F.lit(2)))


class Model:
    """Log ratios of the hashed n-gram models, and the log odds of a raw document."""

    def __init__(self, target: np.ndarray, raw: np.ndarray, share: float):
        expected = raw * (target.sum() / max(raw.sum(), 1))
        self.ratio = np.log((target + PRIOR) / (expected + PRIOR))
        self.share, self.known = share, bool(target.sum())

    @property
    def threshold(self) -> float:
        """Importance from which a document is more likely good than not."""
        return -float(np.log(2 * min(max(self.share, 1e-6), 1.0)))

    def scores(self, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        text, bucket = ngrams(buf, offsets, len(self.ratio))
        n = len(offsets) - 1
        return np.bincount(text, weights=self.ratio[bucket], minlength=n)[:n].astype(np.float64), np.bincount(text, minlength=n)[:n]


def parting_value(scores: np.ndarray, good: np.ndarray, default: float, weight: float = 1.0) -> float:
    """The score with the least sum of lost good and (``weight`` times) kept bad
    shares from it on: the middle of the best gap."""
    s, y = np.asarray(scores), np.asarray(good).astype(bool)
    if not len(y) or y.all() or not y.any():
        return default
    order = np.argsort(s, kind="stable")
    s, y = s[order], y[order]
    cost = np.concatenate([[0], np.cumsum(y) / y.sum()]) + weight * (1 - np.concatenate([[0], np.cumsum(~y) / (~y).sum()]))
    edge = np.concatenate([[s[0] - 1], s, [s[-1] + 1]])
    gap = np.diff(edge)
    best = np.flatnonzero((cost <= cost.min() + 1e-12) & (gap > 0))
    i = best[np.argmax(gap[best])]
    return float((edge[i] + edge[i + 1]) / 2)


def importance(score: np.ndarray, n: np.ndarray, span: float = SPAN) -> np.ndarray:
    """Log-importance from summed log ratios and the number of n-grams."""
    return score / np.maximum(n, 1) * span


def gumbel(ids: np.ndarray, seed: int) -> np.ndarray:
    bits = mix(ids.astype(np.int64).view(np.uint64) ^ mix(np.array([seed], np.uint64)))
    u = ((bits >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)
    return -np.log(-np.log(u))


def fit(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, rows: int = SAMPLE_ROWS) -> Model:
    sample = labelled_sample(labels, rows)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, target = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64)
        for batch in batches:
            for part in slices(batch, "text"):
                text, bucket = ngrams(*utf8(part.column(0)), buckets)
                raw += np.bincount(bucket, minlength=buckets)
                good = np.asarray(part.column(1).to_numpy(zero_copy_only=False)) == 1
                if good.any():
                    target += np.bincount(bucket[good[text]], minlength=buckets)
        used = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(raw[used]), pa.array(target[used])], names=["bucket", "raw", "target"])

    rows_ = id_and_text(docs)
    marked = rows_.join(F.broadcast(sample), rows_.doc_id == sample.label_id, "left").select("text", F.when(F.col("half") == 0, F.col("good")).otherwise(-1).alias("good"))
    sums = marked.mapInArrow(count, "bucket int, raw long, target long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect()
    raw, target = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64)
    for r in sums:  # at most ``buckets`` rows
        raw[r.bucket], target[r.bucket] = r.raw, r.target
    share = sample.agg(F.avg("good")).first()[0]
    return Model(target, raw, float(share or 0.0))


def scored(docs: DataFrame, model: Model, span: float = SPAN, seed: int = SEED) -> DataFrame:
    """``doc_id, n_ngrams, log_ratio, log_importance, sample_key``; ``log_ratio`` is the
    sum over all n-grams."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                score, n = shared.value.scores(*utf8(part.column(1)))
                ids = part.column(0).fill_null(-1).to_numpy(zero_copy_only=False)
                weight = importance(score, n, span)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n.astype(np.int64)), pa.array(score), pa.array(weight), pa.array(weight + gumbel(ids, seed))], names=["doc_id", "n_ngrams", "log_ratio", "log_importance", "sample_key"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_ngrams long, log_ratio double, log_importance double, sample_key double")


def kth_largest(keys: DataFrame, column: str, k: int) -> float | None:
    """The ``k``-th largest value (None: there are not as many rows)."""
    if k <= 0:
        return float("inf")
    x = F.col(column)
    low, high, n = keys.agg(F.min(x), F.max(x), F.count(x)).first()
    if n < k:
        return None
    above = 0
    while True:
        inside = keys.filter((x >= low) & (x <= high))
        if n <= _BINS or low == high:
            return sorted((r[0] for r in inside.select(x).collect()), reverse=True)[k - above - 1] if low < high else low
        step = (high - low) / _BINS
        bins = inside.groupBy(F.least(F.floor((x - low) / F.lit(step)), F.lit(_BINS - 1)).alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min(x).alias("low"), F.max(x).alias("high"))
        for r in sorted(bins.collect(), key=lambda r: -r.b):  # at most ``_BINS`` rows
            if above + r.n >= k:
                low, high, n = r.low, r.high, r.n
                break
            above += r.n


def resample(docs: DataFrame, labels: DataFrame, k: int | None = None, span: float = SPAN, seed: int = SEED) -> tuple[DataFrame, Model, float | None]:
    """Scores of all documents with ``keep``, the model, and the key that the last
    drawn document has (None: all are drawn)."""
    model = fit(docs, labels)
    shared_dir(docs.sparkSession)
    scores = scored(docs, model, span, seed).checkpoint()
    if k is None and not model.known:
        return scores.withColumn("keep", F.lit(True)), model, None
    if k is None:
        sample = labelled_sample(labels).filter("half = 1")
        known = scores.join(F.broadcast(sample), scores.doc_id == sample.label_id).select("log_importance", "good").collect()  # the sample
        cut = parting_value(np.array([r.log_importance for r in known]), np.array([r.good for r in known], bool), span * model.threshold)
        k = scores.filter(F.col("log_importance") >= cut).count()
    last = kth_largest(scores, "sample_key", k)
    return scores.withColumn("keep", _drawn(F.col("sample_key"), last)), model, last


def _drawn(key: Column, last: float | None) -> Column:
    return F.lit(True) if last is None else key >= F.lit(last)


def select_documents(docs: DataFrame, labels: DataFrame, k: int | None = None, span: float = SPAN, seed: int = SEED) -> DataFrame:
    """The drawn rows of ``docs``, with their own columns.  They are scored again
    where they lie, which is cheaper than a join that moves the texts."""
    _, model, last = resample(docs, labels, k, span, seed)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def sample_key(doc_id: pd.Series, text: pd.Series) -> pd.Series:
        batch = pa.RecordBatch.from_arrays([pa.array(text, pa.string(), from_pandas=True)], names=["text"])
        score = [importance(*shared.value.scores(*utf8(part.column(0))), span) for part in slices(batch, "text")]
        return pd.Series(np.concatenate([*score, np.empty(0)]) + gumbel(doc_id.fillna(-1).to_numpy().astype(np.int64), seed))

    key = sample_key(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")))
    return docs.filter(_drawn(key, last))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op4``: importance, key and decision of all documents."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    return resample(docs, labels)[0]
