"""Training: rounds of parallel shard passes and a merge of the shards' changes into the parent factors.

The loop is the driver's only part; arrays, plans, factors and changes stay DataFrames, and every
round's factors are written to a checkpoint, so that lineage does not grow.
"""

from __future__ import annotations

import hashlib
import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import gp
from ..functions.hashing import keyed, uniform
from ..functions.kernels import Kernel
from ..sources.tables import by_mode
from .arrays import order_of

BROADCAST_BYTES = 64_000_000  # factors that may go to every task
SMALL_BYTES = 1_000_000  # factors that always do
DELTAS = "round int, shard int, mode int, idx long, delta array<double>, bound double, subarrays long, seconds double"


@dataclass(frozen=True)
class TrainParams:
    ranks: tuple[int, ...]
    rounds: int = 5
    rate: float = 0.01
    variance: float = 1.0  # lambda; infinite lets shards drift freely, zero freezes them
    kernel: Kernel = field(default_factory=Kernel)
    likelihood: str = "binary"
    sweeps: int = 10
    merge: str = "mean"  # or "touched", "laplace"
    laplace_scale: float = 0.0
    schedule: str = "all"  # or "slice": a round sees its share of the subarrays
    optimizer: str = "sgd"  # or "lbfgs"
    decay_rate: str = "fixed"  # or "sqrt": the rate falls with the root of the round; "rows": with a row's gradients in a pass
    clip: float = 5.0  # gradient rows longer than this are shortened to it; infinite for none
    offset: float = 0.0  # constant mean of binary cells
    init_scale: float = 0.5
    seed: int = 7


@dataclass
class Model:
    factors: DataFrame
    history: list[dict]
    params: TrainParams
    sizes: tuple[int, ...]


def initial_factors(spark: SparkSession, array_sizes: Sequence[int], p: TrainParams) -> DataFrame:
    """(mode, idx, vec): hash-seeded normal draws, distinct for every row."""
    out = None
    for k, (m, r) in enumerate(zip(array_sizes, p.ranks, strict=True), 1):
        draw = lambda d, k=k: F.sqrt(-2 * F.log(F.greatest(uniform(keyed(p.seed, "r", k, F.col("idx"), d)), F.lit(1e-12)))) * F.cos(2 * np.pi * uniform(keyed(p.seed, "a", k, F.col("idx"), d)))
        own = spark.range(1, m + 1).select(F.lit(k).alias("mode"), F.col("id").alias("idx")).select("mode", "idx", F.array(*[F.lit(p.init_scale) * draw(d) for d in range(r)]).alias("vec"))
        out = own if out is None else out.unionByName(own)
    return out


def densify(lin, y, shape) -> np.ndarray:
    block = np.zeros(int(np.prod(shape)))
    block[np.asarray(lin, np.int64)] = np.asarray(y, float)
    return block.reshape(shape)


def _lbfgs(rows: list[np.ndarray], objective, steps: int = 8, memory: int = 10) -> list[np.ndarray]:
    """Two-loop quasi-Newton ascent on all rows of a subarray, with backtracking."""
    shapes = [r.shape for r in rows]
    cuts = np.cumsum([r.size for r in rows])[:-1]
    split = lambda x: [p.reshape(s) for p, s in zip(np.split(x, cuts), shapes, strict=True)]
    x = np.concatenate([r.ravel() for r in rows])
    f, g = objective(split(x))
    past: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):
        q, stack = g.copy(), []
        for s, d in reversed(past):
            a = (s @ q) / (s @ d)
            stack.append(a)
            q -= a * d
        if past:
            q *= (past[-1][0] @ past[-1][1]) / (past[-1][1] @ past[-1][1])
        else:
            q /= max(np.linalg.norm(q), 1.0)
        for (s, d), a in zip(past, reversed(stack), strict=True):
            q += (a - (d @ q) / (s @ d)) * s
        t = 1.0
        while t > 1e-6:
            f2, g2 = objective(split(x + t * q))
            if f2 >= f + 1e-4 * t * (g @ q):
                break
            t /= 2
        else:
            break
        s, d = t * q, g - g2  # the curvature of the negated objective
        x, f, g = x + s, f2, g2
        if s @ d > 1e-12:
            past = [*past, (s, d)][-memory:]
    return split(x)


def shard_pass(frames: Iterator[pd.DataFrame], parent, p: TrainParams, round_: int, counts: dict[int, int]) -> Iterator[pd.DataFrame]:
    """One pass over a sorted stream of subarrays, shard after shard; one subarray is in memory at a time."""
    state, shard, bound, seen, began = None, None, 0.0, 0, time.time()
    rate = p.rate / np.sqrt(round_) if p.decay_rate == "sqrt" else p.rate

    def finish() -> pd.DataFrame:
        rows = [(round_, shard, k + 1, i, d.tolist(), bound, seen, time.time() - began) for (k, i), d in state.deltas()]
        return pd.DataFrame(rows, columns=["round", "shard", "mode", "idx", "delta", "bound", "subarrays", "seconds"])

    for frame in frames:
        for row in frame.itertuples(index=False):
            if row.shard != shard:
                if state is not None:
                    yield finish()
                shard, bound, seen, began = int(row.shard), 0.0, 0, time.time()
                state = gp.ShardState(parent(row) if callable(parent) and getattr(parent, "per_row", False) else parent, counts.get(shard, 1), rate, p.variance, p.clip, p.decay_rate == "rows")
            if getattr(parent, "per_row", False):
                state.parent = parent(row)
            sets = [np.asarray(s, np.int64) for s in row.sets]
            rows = [state.gather(k, s) for k, s in enumerate(sets)]
            y = densify(row.lin, row.y, [len(s) for s in sets])
            options = {"sweeps": p.sweeps, "offset": p.offset} if p.likelihood == "binary" else {}
            if p.optimizer == "lbfgs":

                def objective(r):
                    post, spec = gp.infer(r, y, p.kernel, p.likelihood, **options)
                    return post.bound[-1], np.concatenate([g.ravel() for g in gp.factor_gradients(r, post, spec, p.kernel)])

                moved = _lbfgs(rows, objective)
                post, _ = gp.infer(moved, y, p.kernel, p.likelihood, **options)
                state.step(sets, [(a - b) / max(rate, 1e-12) for a, b in zip(moved, rows, strict=True)], plain=True)
            else:
                post, spec = gp.infer(rows, y, p.kernel, p.likelihood, **options)
                state.step(sets, gp.factor_gradients(rows, post, spec, p.kernel))
            bound += post.bound[-1] / y.size
            seen += 1
    if state is not None:
        yield finish()


class _Broadcast:
    """Parent rows from one array a mode, sent to all tasks."""

    def __init__(self, sent):
        self.sent = sent

    def __call__(self, mode: int, idx: int) -> np.ndarray:
        return self.sent.value[mode][idx - 1]


class _Joined:
    """Parent rows that came with the subarray."""

    per_row = True

    def __call__(self, row):
        table = {(k, int(i)): np.asarray(v) for k, (s, vs) in enumerate(zip(row.sets, row.rows, strict=True)) for i, v in zip(s, vs, strict=True)}
        return lambda mode, idx: table[mode, idx]


def factor_bytes(array_sizes: Sequence[int], ranks: Sequence[int]) -> int:
    return 8 * sum(m * r for m, r in zip(array_sizes, ranks, strict=True))


def as_arrays(factors: DataFrame, array_sizes: Sequence[int], ranks: Sequence[int]) -> list[np.ndarray]:
    """Factors as one array a mode; only for sizes that were checked."""
    out = [np.zeros((m, r)) for m, r in zip(array_sizes, ranks, strict=True)]
    for k, (idx, vecs) in by_mode(factors, "vec").items():
        out[k - 1][idx - 1] = vecs
    return out


def ships(array_sizes: Sequence[int], ranks: Sequence[int], used: int) -> str:
    """How parent rows reach the tasks: whole factors sent to all where that is no more than the ``used`` rows joined to the subarrays."""
    size = factor_bytes(array_sizes, ranks)
    return "broadcast" if size <= max(SMALL_BYTES, min(BROADCAST_BYTES, 8 * max(ranks) * used)) else "join"


def _with_rows(blocks: DataFrame, factors: DataFrame) -> DataFrame:
    """Subarrays with the parent rows that they use, by a join: for factors too large to send."""
    used = blocks.select("sub_id", F.posexplode("sets").alias("k", "set")).select("sub_id", (F.col("k") + 1).alias("mode"), F.posexplode("set").alias("pos", "idx"))
    rows = used.join(factors, ["mode", "idx"]).groupBy("sub_id", "mode").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "vec"))), lambda x: x["vec"]).alias("vecs"))
    nested = rows.groupBy("sub_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("mode", "vecs"))), lambda x: x["vecs"]).alias("rows"))
    return blocks.join(nested, "sub_id")


def shard_deltas(blocks: DataFrame, factors: DataFrame, p: TrainParams, round_: int, array_sizes: Sequence[int], shards: int, ship: str = "auto") -> DataFrame:
    """Changes of touched rows after one pass of every shard over its subarrays in a fresh random order."""
    spark = blocks.sparkSession
    order = F.md5(keyed(p.seed, round_, F.col("sub_id")).cast("binary"))
    own = blocks.filter(F.pmod(F.xxhash64("sub_id"), F.lit(p.rounds)) == round_ % p.rounds) if p.schedule == "slice" else blocks
    told = own.groupBy("shard").agg(F.count("*").alias("n"), F.sum(F.aggregate("sets", F.lit(0), lambda n, s: n + F.size(s))).alias("used")).collect()  # of the round's own subarrays, one row a shard
    counts = {r.shard: r.n for r in told}
    if (ships(array_sizes, p.ranks, sum(r.used for r in told)) if ship == "auto" else ship) == "broadcast":
        parent = _Broadcast(spark.sparkContext.broadcast(as_arrays(factors, array_sizes, p.ranks)))
    else:
        own, parent = _with_rows(own, factors), _Joined()
    dealt = own.withColumn("ord", order).repartitionById(shards, "shard").sortWithinPartitions("shard", "ord").drop("ord")
    return dealt.mapInPandas(lambda frames: shard_pass(frames, parent, p, round_, counts), DELTAS)


def merge_factors(factors: DataFrame, deltas: DataFrame, shards: int, mode: str = "mean", laplace: float = 0.0) -> DataFrame:
    """Parent rows plus the shards' mean change. Shards that never touched a row count as no change.

    "touched" divides by the shards that did; "laplace" soft-thresholds the mean row.
    """
    parts = deltas.select("shard", "mode", "idx", F.posexplode("delta").alias("d", "v"))
    n = F.count_distinct("shard") if mode == "touched" else F.lit(shards)
    sums = parts.groupBy("mode", "idx", "d").agg((F.sum("v") / n).alias("v"))
    change = sums.groupBy("mode", "idx").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "v"))), lambda x: x["v"]).alias("change"))
    moved = factors.join(change, ["mode", "idx"], "left").withColumn("vec", F.when(F.col("change").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "change", lambda a, b: a + b))).drop("change")
    if mode == "laplace":
        moved = moved.withColumn("vec", F.transform("vec", lambda x: F.signum(x) * F.greatest(F.abs(x) - laplace, F.lit(0.0))))
    return moved.select("mode", "idx", "vec")


def fit(blocks: DataFrame, array_sizes: Sequence[int], p: TrainParams, shards: int, init: DataFrame | None = None, ship: str = "auto") -> Model:
    """Rounds of shard passes and merges, from random or given factors."""
    from ..sources.tables import checkpointed

    spark = blocks.sparkSession
    blocks = checkpointed(blocks, "blocks")
    factors = checkpointed(init if init is not None else initial_factors(spark, array_sizes, p), "factors")
    visited = F.aggregate("sets", F.lit(1.0), lambda n, s: n * F.size(s))
    share = float(blocks.agg(F.sum(visited)).first()[0] or 0.0) / float(np.prod(array_sizes, dtype=float))
    every = blocks.count()
    history = []
    for round_ in range(1, p.rounds + 1):
        began = time.time()
        deltas = checkpointed(shard_deltas(blocks, factors, p, round_, array_sizes, shards, ship), "deltas")
        passed = time.time()
        told = deltas.groupBy("shard").agg(F.first("bound").alias("bound"), F.first("subarrays").alias("subarrays"), F.count("*").alias("rows"), F.sqrt(F.sum(F.aggregate("delta", F.lit(0.0), lambda a, v: a + v * v))).alias("norm")).agg(F.sum("bound").alias("bound"), F.sum("subarrays").alias("subarrays"), F.sum("rows").alias("rows"), F.avg("norm").alias("norm")).first()
        scale = p.laplace_scale * p.variance / shards
        factors = checkpointed(merge_factors(factors, deltas, shards, p.merge, scale), "factors")
        history.append({"round": round_, "bound": float((told.bound or 0.0) / max(told.subarrays or 1, 1)), "rows_touched": int(told.rows or 0), "subarrays": int(told.subarrays or 0), "coverage": share * int(told.subarrays or 0) / max(every, 1), "delta_norm": float(told.norm or 0.0), "seconds": time.time() - began, "pass_s": passed - began, "merge_s": time.time() - passed})
    return Model(factors, history, p, tuple(array_sizes))


def with_params(p: TrainParams, **changes) -> TrainParams:
    return replace(p, **changes)


def digest(model: Model) -> str:
    """A fingerprint of the factors, for reproducibility checks on small models."""
    rows = sorted((r.mode, r.idx, tuple(round(v, 9) for v in r.vec)) for r in model.factors.collect())
    return hashlib.sha256(repr(rows).encode()).hexdigest()


def modes_of(arr: DataFrame) -> int:
    return order_of(arr)
