"""Quality classifier: hashed word n-gram logistic regression trained by FTRL-proximal updates.

Features are word runs and punctuation runs (case kept) and pairs of neighbouring ones, hashed to
``1 << BITS`` buckets; a text's feature vector is its counts divided by its number of n-grams. The
model is fitted on a bounded sample of labelled rows (``SAMPLE_PER_CLASS`` of each class at most):
``TRAINERS`` tasks each run follow-the-regularised-leader over their share of the sample, several
passes over its rows in an order that hashes of their ids and texts fix, and the models are averaged, so the
weights do not depend on how rows arrive. The weights are one array of fixed size, sent to all tasks,
and a text's score is a sparse dot product through the logistic function. Scoring reads every text
once, whole, without a shuffle.

Defined results: null and empty texts score by the intercept alone; without usable labels every
score is 0.5; repeated rows get equal scores; a null id is not held out; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labelled import fold_of, labelled_sample
from .runtime import table
from .textcore import U64, chunks, find_words, ngrams, per_doc_sum

BITS = 18
SAMPLE_PER_CLASS = 6000
TRAINERS = 4
PASSES = 8


def features(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bucket of each n-gram, text bounds)."""
    for lo, hi, buf, offs in chunks(texts):
        w = find_words(buf, offs, "mixed")
        two, at = ngrams(w.hash, w.ptr, 2)
        bucket = np.empty(len(w.hash) + len(two), np.int32)
        # each text's unigrams, then its pairs
        shift = np.searchsorted(at, w.ptr)
        doc_of_word = np.repeat(np.arange(hi - lo), w.count)
        doc_of_pair = np.repeat(np.arange(hi - lo), np.diff(shift))
        ptr = w.ptr + shift
        bucket[np.arange(len(w.hash)) + shift[doc_of_word]] = (w.hash >> U64(64 - BITS)).astype(np.int32)
        bucket[np.arange(len(two)) + w.ptr[doc_of_pair + 1]] = (two >> U64(64 - BITS)).astype(np.int32)
        yield lo, hi, bucket, ptr


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for logistic loss on sparse rows."""

    def __init__(self, size: int, alpha: float = 2.0, beta: float = 0.02, l1: float = 1e-4, l2: float = 1e-3):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros(size), np.zeros(size)

    def weights(self, i=slice(None)) -> np.ndarray:
        z, n = self.z[i], self.n[i]
        w = (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def learn(self, i: np.ndarray, x: np.ndarray, y: int, cost: float = 1.0) -> None:
        w = self.weights(i)
        p = 1 / (1 + np.exp(-np.clip(w @ x, -35, 35)))
        g = cost * (p - y) * x
        grown = self.n[i] + g * g
        self.z[i] += g - (np.sqrt(grown) - np.sqrt(self.n[i])) / self.alpha * w
        self.n[i] = grown


def _row(bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    i, c = np.unique(bucket, return_counts=True)
    return np.append(i, 1 << BITS), np.append(c / max(len(bucket), 1), 1.0)  # the last coordinate is the intercept


def _train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows = []
    for batch in batches:
        y = batch.column("y").to_pylist()
        for lo, hi, bucket, ptr in features(batch.column("text")):
            rows += [(*_row(bucket[ptr[k] : ptr[k + 1]]), y[lo + k]) for k in range(hi - lo)]
    if not rows:
        return
    share = sum(r[2] for r in rows) / len(rows)
    cost = {1: 0.5 / max(share, 1e-9), 0: 0.5 / max(1 - share, 1e-9)}
    model, order = Ftrl((1 << BITS) + 1), np.random.RandomState(5)
    for _ in range(PASSES):
        for k in order.permutation(len(rows)):
            model.learn(*rows[k], cost[rows[k][2]])
    w = model.weights()
    at = np.flatnonzero(w)
    yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(w[at]), pa.array(np.full(len(at), len(rows)), pa.int64())], names=["i", "w", "n"])


def fit(docs: DataFrame, labels: DataFrame, label: str, usable, per_class: int = SAMPLE_PER_CLASS) -> np.ndarray:
    """The averaged weights; the last is the intercept."""
    sample = labelled_sample(docs, labels, label, usable, per_class)
    dealt = sample.select("text", "y", F.xxhash64("doc_id", "text").alias("place"), F.pmod(F.xxhash64("doc_id"), F.lit(TRAINERS)).alias("trainer")).groupBy("trainer").applyInArrow(_train_group, "i int, w double, n long")
    averaged = dealt.groupBy("i").agg(F.sum(F.col("w") * F.col("n")).alias("w"))
    weights = np.zeros((1 << BITS) + 1)
    got = averaged.toPandas()  # at most one row for each bucket
    total = sample.count()
    if total:
        weights[got["i"].to_numpy()] = got["w"].to_numpy() / total
    return weights


def _train_group(tables: pa.Table) -> pa.Table:
    order = tables.sort_by([("y", "ascending"), ("place", "ascending"), ("text", "ascending")])
    out = list(_train(iter(order.combine_chunks().to_batches())))
    schema = pa.schema([("i", pa.int32()), ("w", pa.float64()), ("n", pa.int64())])
    return pa.Table.from_batches(out, schema)


def _score(weights):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = weights.value
        for batch in batches:
            p = np.zeros(batch.num_rows)
            for lo, hi, bucket, ptr in features(batch.column("text")):
                total = per_doc_sum(w[bucket].astype(np.float64), ptr)
                p[lo:hi] = total / np.maximum(np.diff(ptr), 1) + w[-1]
            p = 1 / (1 + np.exp(-np.clip(p, -35, 35)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p), pa.array((p >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return run


def score(docs: DataFrame, weights: np.ndarray, held_out) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of ``docs``."""
    sent = docs.sparkSession.sparkContext.broadcast(weights.astype(np.float32))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(_score(sent), "doc_id long, held_out boolean, score double, predicted int")


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = fold_of(3) == 1
    weights = fit(docs, table(spark, sf_dir, "labels"), "quality", ~held)
    return score(docs, weights, held)
