"""Toxic passages by maximum-scoring segment search over token log-odds.

1. Token scores. Tokens are alphanumeric words, case folded, each with its stems (its first
   ``STEMS`` bytes, so that inflected forms count together), hashed to ``1 << BITS`` buckets. A
   bucket's score is its log-odds between toxic and other labelled texts under a Dirichlet prior
   whose weights are the bucket's counts over *all* texts; scores that are small or whose z
   value is small count as zero, a word scores as the best of its word and stems, and a small drift is taken off every
   token, so that chance segments stay short.
2. Segments. One linear scan with a stack finds every maximal-scoring segment of a text.
3. Calibration. The best segment of a clean text of n tokens follows an extreme-value law
   P(max > s) = 1 - exp(-K n exp(-lambda s)); lambda and K are fitted by maximum likelihood on the
   clean part of the labelled sample. A segment is significant if fewer than one such is expected
   by chance; a text's evidence is the sum of the significant segments' log expectations with the
   combinatorial correction for how many there are.
4. The evidence becomes a probability by a logistic function on the labelled sample, weighted to
   the classes' frequencies among the labels: its slope by maximum likelihood, its middle at the
   cut that judges most weight rightly.

The labelled sample is bounded (``SAMPLE_PER_CLASS``); counts for the prior cover all texts, and the
score table has a fixed size, so it can be sent to all tasks. Texts are scanned whole, without a shuffle.

Defined results: null and empty texts have no segment and score by the intercept alone; without usable
labels of both classes every score is 0; repeated rows get equal scores; a null id is not held
out; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import lgamma

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labelled import fold_of, labelled_sample
from .runtime import materialise, table
from .textcore import U64, Words, chunks, find_words, prefix_hash

BITS = 20
SAMPLE_PER_CLASS = 6000
STEMS = (4, 5)
PRIOR_WEIGHT = 50_000.0
MIN_Z = 3.0
MIN_ODDS = 1.5
DRIFT = 0.05


@dataclass
class Model:
    token: np.ndarray  # score of each bucket
    decay: float  # lambda
    rate: float  # K
    slope: float
    intercept: float

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * evidence + self.intercept, -35, 35)))


def _buckets(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> U64(64 - BITS)).astype(np.int64)


def _tokens(buf: np.ndarray, w: Words) -> np.ndarray:
    """Buckets of each word and its stems, one row each."""
    return np.stack([_buckets(w.hash), *(_buckets(prefix_hash(buf, w, n)) for n in STEMS)])


def _count_tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(class, bucket, count) of one task's texts; a table without classes counts as class 0."""
    totals: dict[int, np.ndarray] = {}
    for batch in batches:
        classes = batch.column("y").to_numpy(zero_copy_only=False) if "y" in batch.schema.names else np.zeros(batch.num_rows, int)
        for lo, hi, buf, offs in chunks(batch.column("text")):
            w = find_words(buf, offs, "alnum")
            b, y = _tokens(buf, w), np.repeat(classes[lo:hi], w.count)
            for c in np.unique(y):
                own = totals.setdefault(int(c), np.zeros(1 << BITS, np.int64))
                at, n = np.unique(b[:, y == c], return_counts=True)
                own[at] += n
    for c, own in totals.items():
        at = np.flatnonzero(own)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), c), pa.int32()), pa.array(at, pa.int32()), pa.array(own[at])], names=["y", "bucket", "n"])


def _counts(texts: DataFrame) -> DataFrame:
    return texts.mapInArrow(_count_tokens, "y int, bucket int, n long").groupBy("y", "bucket").agg(F.sum("n").alias("n"))


def token_scores(sample: DataFrame, texts: DataFrame) -> np.ndarray | None:
    """Score of every bucket: log-odds with an informative Dirichlet prior where they are large and
    significant, else zero, less the drift; None where a class has no tokens.

    The odds are worked out in Spark; only buckets with a score come to the driver.
    """
    of = lambda y: F.coalesce(F.sum(F.when(F.col("y") == y, F.col("n"))), F.lit(0)).cast("double")
    by_class = materialise(_counts(sample).groupBy("bucket").agg(of(1).alias("toxic"), of(0).alias("clean")), "classes")
    everything = materialise(_counts(texts).select("bucket", F.col("n").alias("all")), "background")
    own = by_class.agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")).first()
    if not own.toxic or not own.clean:
        return None
    total = everything.agg(F.sum("all").alias("n")).first().n
    prior = PRIOR_WEIGHT * (F.col("all") + 0.5) / (total + 0.5 * (1 << BITS))
    a, b = F.col("toxic") + prior, F.col("clean") + prior
    odds = F.log(a / (own.toxic + PRIOR_WEIGHT - a)) - F.log(b / (own.clean + PRIOR_WEIGHT - b))
    scored = by_class.join(everything, "bucket").select("bucket", odds.alias("odds"), (odds / F.sqrt(1 / a + 1 / b)).alias("z"))
    rows = scored.filter((F.abs("z") >= MIN_Z) & (F.abs("odds") >= MIN_ODDS)).select("bucket", "odds").toPandas()
    out = np.full(1 << BITS, -DRIFT, np.float32)
    out[rows["bucket"].to_numpy()] = rows["odds"].to_numpy() - DRIFT
    return out


def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments (first, end, score), left to right, in linear time.

    Only positive tokens can begin a segment, so the scan visits those; what lies between is in
    the running totals.
    """
    total = np.concatenate([[0.0], np.cumsum(scores)])
    stack: list[list[float]] = []  # begin, end, total before, total after, index of the last smaller one
    for at in np.flatnonzero(scores > 0):
        begin, end, before, after = int(at), int(at) + 1, total[at], total[at + 1]
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][2] >= before:
                j = stack[j][4]
            if j < 0 or stack[j][3] >= after:
                stack.append([begin, end, before, after, j])
                break
            begin, before = stack[j][0], stack[j][2]
            del stack[j:]
    return [(int(s[0]), int(s[1]), float(s[3] - s[2])) for s in stack]


def evidence(segments: list[tuple[int, int, float]], n: int, decay: float, rate: float) -> float:
    """Sum of the significant segments' -log(expected number by chance), corrected for their number."""
    each = [x for _, _, s in segments if (x := decay * s - np.log(max(rate * n, 1e-300))) > 0]
    return max(0.0, float(sum(each)) - lgamma(len(each) + 1)) if each else 0.0


def _scan(texts: pa.Array, token: np.ndarray) -> Iterator[tuple[int, list[tuple[int, int, float]]]]:
    """(number of tokens, segments) of each text."""
    for _, _, buf, offs in chunks(texts):
        w = find_words(buf, offs, "alnum")
        s = token[_tokens(buf, w)].max(axis=0)
        some = np.concatenate([[0], np.cumsum(s > 0)])
        for a, b in zip(w.ptr[:-1], w.ptr[1:], strict=True):
            yield int(b - a), maximal_segments(s[a:b]) if some[b] > some[a] else []


def _best(token):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, all_scores = [], []
            for size, segments in _scan(batch.column("text"), token.value):
                n.append(size)
                all_scores.append([s for _, _, s in segments])
            yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array(n, pa.int64()), pa.array(all_scores, pa.list_(pa.float64()))], names=["y", "n", "scores"])

    return run


def fit_extremes(best: np.ndarray, n: np.ndarray) -> tuple[float, float]:
    """Maximum-likelihood (lambda, K) of the law of the best segment of clean texts."""
    n = np.maximum(n, 1)
    some = best > 0
    floor = best[some].min() / 2 if some.any() else 1.0
    x = np.where(some, best, floor)
    hits = max(some.sum(), 0.5)  # texts without a positive token say only that the best is below the floor

    def fitted(g: float) -> tuple[float, float, float]:
        k = hits / (n * np.exp(-g * x)).sum()
        return float((np.log(g * k * n[some]) - g * x[some]).sum() - hits), g, k

    _, decay, rate = max(map(fitted, np.exp(np.linspace(np.log(0.05), np.log(3.0), 120))))
    return float(decay), float(rate)


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, float]:
    """Slope (not negative) and intercept by damped Newton steps with shrinkage.

    The classes may be separable, where the unpenalised fit has no maximum; the penalty on the
    standardised slope gives one, and a step is halved until the objective grows.
    """
    scale = float(x.std()) or 1.0
    design, beta, ridge = np.stack([x / scale, np.ones_like(x)], 1), np.zeros(2), np.array([0.1, 1e-4])

    def objective(b: np.ndarray) -> float:
        z = design @ b
        return float((weight * (y * z - np.logaddexp(0, z))).sum() - 0.5 * (ridge * b * b).sum())

    now = objective(beta)
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -35, 35)))
        grad = design.T @ (weight * (y - p)) - ridge * beta
        hess = (design * (weight * p * (1 - p))[:, None]).T @ design + np.diag(ridge)
        step, size = np.linalg.solve(hess, grad), 1.0
        while size > 1e-6 and objective(beta + size * step) <= now:
            size /= 2
        if size <= 1e-6:
            break
        beta = beta + size * step
        now = objective(beta)
    return max(float(beta[0] / scale), 0.0), float(beta[1])


def best_cut(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
    """The evidence above which the label is likelier: the cut with the most weight judged rightly.

    A few labelled texts without any toxic passage would pull a logistic fit's own cut far up; they
    do not move this one. Of equally good cuts the middle one is taken.
    """
    order = np.argsort(x, kind="stable")
    xs, gain = x[order], np.where(y[order] == 1, -weight[order], weight[order])
    right = weight[y == 1].sum() + np.cumsum(gain)  # with everything up to here judged clean
    last = np.append(xs[1:] != xs[:-1], True)
    best = np.flatnonzero(last & (right >= right[last].max() - 1e-9))
    k = best[len(best) // 2]
    return float((xs[k] + (xs[k + 1] if k + 1 < len(xs) else xs[k] + 1)) / 2)


def fit(docs: DataFrame, labels: DataFrame, label: str, usable, per_class: int = SAMPLE_PER_CLASS) -> Model:
    frequency = {int(r["y"]): r["n"] for r in labels.filter(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & usable).groupBy(F.col(label).cast("int").alias("y")).agg(F.count("*").alias("n")).collect()}
    # a text that was copied many times over counts once, lest its words look typical of its class
    sample = materialise(labelled_sample(docs, labels, label, usable, per_class).select("text", "y").dropDuplicates(["text"]), "labelled")
    token = token_scores(sample, docs.select("text"))
    if token is None:
        return Model(np.full(1 << BITS, -DRIFT, np.float32), 1.0, 1.0, 0.0, -35.0)
    sent = docs.sparkSession.sparkContext.broadcast(token)
    seen = sample.mapInArrow(_best(sent), "y int, n long, scores array<double>").toPandas()  # bounded by the sample
    y, n = seen["y"].to_numpy(), seen["n"].to_numpy()
    best = np.array([max(s, default=0.0) if len(s) else 0.0 for s in seen["scores"]])
    decay, rate = fit_extremes(best[y == 0], n[y == 0])
    x = np.array([evidence([(0, 0, v) for v in s], size, decay, rate) for s, size in zip(seen["scores"], n, strict=True)])
    weight = np.array([frequency[c] / (y == c).sum() for c in (0, 1)])[y]
    weight = weight * len(y) / weight.sum()
    slope = max(fit_logistic(x, y, weight)[0], 1e-3)
    return Model(token, decay, rate, slope, -slope * best_cut(x, y, weight))


def _score(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for batch in batches:
            found = list(_scan(batch.column("text"), m.token))
            p = m.probability(np.array([evidence(s, n, m.decay, m.rate) for n, s in found]))
            rows = [sorted(((a, b, v) for a, b, v in s if m.decay * v > np.log(max(m.rate * n, 1e-300)))) for n, s in found]
            spans = pa.array([[{"first": a, "end": b, "score": v} for a, b, v in r] for r in rows], pa.list_(pa.struct([("first", pa.int32()), ("end", pa.int32()), ("score", pa.float64())])))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p), pa.array((p >= 0.5).astype(np.int32)), spans], names=["doc_id", "held_out", "score", "predicted", "passages"])

    return run


def score(docs: DataFrame, model: Model, held_out) -> DataFrame:
    """(doc_id, held_out, score, predicted, passages) for every row; passages are token ranges with scores."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(_score(sent), "doc_id long, held_out boolean, score double, predicted int, passages array<struct<first:int,end:int,score:double>>")


def judged(docs: DataFrame, labels: DataFrame) -> DataFrame:
    held = fold_of(5) == 0
    return score(docs, fit(docs, labels, "toxic", ~held), held)


def _reject(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for batch in batches:
            x = np.array([evidence(s, n, m.decay, m.rate) for n, s in _scan(batch.column("text"), m.token)], float)
            yield batch.filter(pa.array(m.probability(x) < 0.5))

    return run


def surviving_rows(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs``, all columns, that are not judged toxic."""
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, "toxic", fold_of(5) != 0))
    return docs.mapInArrow(_reject(model), docs.schema)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("passages")
