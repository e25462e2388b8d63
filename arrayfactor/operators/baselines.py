"""The multilinear baselines, the single-process model, and what they share.

CP and its sparse form, nonnegative CP and Tucker run on the nonzeros with joins and sums; only
matrices of the size of a rank (or, for Gram matrices, of a checked mode) come to the driver.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import product

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import gp
from ..functions.hashing import keyed, uniform
from ..functions.kernels import Kernel
from ..sources.tables import checkpointed
from .arrays import attach_rows, order_of
from .products import row_products

GRAM_LIMIT = 5_000
GLOBAL_LIMIT = 4_000_000


def random_factors(spark: SparkSession, sizes: Sequence[int], rank: int | Sequence[int], seed: int) -> DataFrame:
    ranks = [rank] * len(sizes) if isinstance(rank, int) else rank
    out = None
    for k, (m, r) in enumerate(zip(sizes, ranks, strict=True), 1):
        own = spark.range(1, m + 1).select(F.lit(k).alias("mode"), F.col("id").alias("idx")).select("mode", "idx", F.array(*[uniform(keyed(seed, k, F.col("idx"), d)) for d in range(r)]).alias("vec"))
        out = own if out is None else out.unionByName(own)
    return out


def _rows_of(factors: DataFrame, k: int) -> DataFrame:
    return factors.filter(F.col("mode") == k).select(F.col("idx").alias(f"i{k}"), F.col("vec").alias(f"u{k}"))


def mttkrp(arr: DataFrame, factors: DataFrame, k: int, rank: int) -> DataFrame:
    """(i, vec): the mode-k matrix times the Khatri-Rao product of the other modes' factors, on nonzeros."""
    out = arr
    others = [j for j in range(1, order_of(arr) + 1) if j != k]
    for j in others:
        out = out.join(_rows_of(factors, j), f"i{j}")
    terms = [F.sum(reduce(lambda a, b: a * b, [F.col("y"), *[F.get(f"u{j}", F.lit(d)) for j in others]])) for d in range(rank)]
    return out.groupBy(F.col(f"i{k}").alias("i")).agg(F.array(*terms).alias("vec"))


def sparse_mttkrp(arr: DataFrame, factors: DataFrame, k: int, rank: int) -> DataFrame:
    """The same, one factor at a time: nothing wider than nonzeros times rank is ever made."""
    out = arr.withColumn("acc", F.array(*[F.col("y")] * rank))
    for j in (j for j in range(1, order_of(arr) + 1) if j != k):
        out = out.join(_rows_of(factors, j), f"i{j}").withColumn("acc", F.zip_with("acc", f"u{j}", lambda a, b: a * b)).drop(f"u{j}")
    return out.groupBy(F.col(f"i{k}").alias("i")).agg(F.array(*[F.sum(F.get("acc", F.lit(d))) for d in range(rank)]).alias("vec"))


def gram_of(factors: DataFrame, k: int, rank: int) -> np.ndarray:
    """Rank x rank products of one mode's rows."""
    own = factors.filter(F.col("mode") == k)
    pairs = [(a, b) for a in range(rank) for b in range(a, rank)]
    row = own.agg(*[F.sum(F.get("vec", F.lit(a)) * F.get("vec", F.lit(b))).alias(f"g{a}_{b}") for a, b in pairs]).first()
    g = np.zeros((rank, rank))
    for (a, b), v in zip(pairs, row, strict=True):
        g[a, b] = g[b, a] = v or 0.0
    return g


def times(vec: Column, m: np.ndarray) -> Column:
    return F.array(*[reduce(lambda a, b: a + b, [F.get(vec, F.lit(i)) * float(m[i, j]) for i in range(m.shape[0])]) for j in range(m.shape[1])])


def _replace(factors: DataFrame, k: int, rows: DataFrame, rank: int) -> DataFrame:
    """Factors with mode k's rows replaced; indices without nonzeros get zero rows."""
    own = factors.filter(F.col("mode") == k).select("mode", "idx").join(rows.withColumnRenamed("i", "idx"), "idx", "left")
    own = own.select("mode", "idx", F.coalesce("vec", F.array(*[F.lit(0.0)] * rank)).alias("vec"))
    return checkpointed(factors.filter(F.col("mode") != k).unionByName(own), "factors")


def cp_als(arr: DataFrame, sizes: Sequence[int], rank: int, iters: int = 5, seed: int = 11, sparse: bool = False, init: DataFrame | None = None) -> DataFrame:
    """Alternating least squares; with ``sparse`` the product is formed factor by factor."""
    arr = checkpointed(arr, "array")
    factors = checkpointed(init if init is not None else random_factors(arr.sparkSession, sizes, rank, seed), "factors")
    form = sparse_mttkrp if sparse else mttkrp
    for _ in range(iters):
        for k in range(1, len(sizes) + 1):
            grams = [gram_of(factors, j, rank) for j in range(1, len(sizes) + 1) if j != k]
            inverse = np.linalg.pinv(reduce(lambda a, b: a * b, grams))
            rows = form(arr, factors, k, rank)
            factors = _replace(factors, k, rows.select("i", times(F.col("vec"), inverse).alias("vec")), rank)
    return factors


def sparse_cp(arr: DataFrame, sizes: Sequence[int], rank: int, iters: int = 5, seed: int = 11) -> DataFrame:
    """The large-data baseline."""
    return cp_als(arr, sizes, rank, iters, seed, sparse=True)


def cp_nonneg(arr: DataFrame, sizes: Sequence[int], rank: int, iters: int = 10, seed: int = 11) -> DataFrame:
    """Multiplicative updates; factors stay nonnegative."""
    arr = checkpointed(arr, "array")
    factors = checkpointed(random_factors(arr.sparkSession, sizes, rank, seed), "factors")
    for _ in range(iters):
        for k in range(1, len(sizes) + 1):
            v = reduce(lambda a, b: a * b, [gram_of(factors, j, rank) for j in range(1, len(sizes) + 1) if j != k])
            rows = sparse_mttkrp(arr, factors, k, rank).withColumnRenamed("vec", "num").withColumnRenamed("i", "idx")
            old = factors.filter(F.col("mode") == k).join(rows, "idx", "left")
            up = F.zip_with(F.zip_with("vec", F.coalesce("num", F.array(*[F.lit(0.0)] * rank)), lambda a, b: a * b), times(F.col("vec"), v), lambda a, b: a / F.greatest(b, F.lit(1e-12)))
            factors = _replace(factors, k, old.select(F.col("idx").alias("i"), up.alias("vec")), rank)
    return factors


def gram(arr: DataFrame, k: int) -> DataFrame:
    """(a, b, g): products of the mode-k matrix's rows, for rows that share a column."""
    return row_products(arr, k, [f"i{j}" for j in range(1, order_of(arr) + 1) if j != k])


def _as_factors(spark: SparkSession, k: int, u: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(k, i + 1, [float(v) for v in row]) for i, row in enumerate(u)], "mode int, idx long, vec array<double>")


def hosvd(arr: DataFrame, sizes: Sequence[int], ranks: Sequence[int]) -> tuple[DataFrame, dict[tuple[int, ...], float]]:
    """Leading eigenvectors of every mode's Gram matrix, and the core they give; modes up to a limit."""
    factors = None
    for k, (m, r) in enumerate(zip(sizes, ranks, strict=True), 1):
        if m > GRAM_LIMIT:
            raise ValueError(f"mode {k} has {m} indices; use tucker_als, which forms no such matrix")
        g = np.zeros((m, m))
        for row in gram(arr, k).toPandas().itertuples(index=False):
            g[row.a - 1, row.b - 1] = row.g
        own = _as_factors(arr.sparkSession, k, np.linalg.eigh(g)[1][:, ::-1][:, :r])
        factors = own if factors is None else factors.unionByName(own)
    factors = checkpointed(factors, "factors")
    return factors, core_of(arr, factors, ranks)


def core_of(arr: DataFrame, factors: DataFrame, ranks: Sequence[int]) -> dict[tuple[int, ...], float]:
    """The array in the factors' coordinates: one sum over the nonzeros for each core cell."""
    rows = attach_rows(arr, factors, len(ranks))
    at = list(product(*[range(r) for r in ranks]))
    terms = [F.sum(reduce(lambda x, z: x * z, [F.col("y"), *[F.get(f"u{k + 1}", F.lit(a)) for k, a in enumerate(c)]])).alias("c" + "_".join(map(str, c))) for c in at]
    return {c: float(v or 0.0) for c, v in zip(at, rows.agg(*terms).first(), strict=True)}


def tucker_als(arr: DataFrame, sizes: Sequence[int], ranks: Sequence[int], iters: int = 3, seed: int = 11) -> tuple[DataFrame, dict[tuple[int, ...], float]]:
    """Orthogonal iteration: each mode's rows are projected on the others' factors and rotated by a
    small Gram matrix, so that no matrix of a mode's size is formed."""
    arr = checkpointed(arr, "array")
    factors = checkpointed(random_factors(arr.sparkSession, sizes, list(ranks), seed), "factors")
    for _ in range(iters):
        for k in range(1, len(sizes) + 1):
            others = [j for j in range(1, len(sizes) + 1) if j != k]
            out = arr
            for j in others:
                out = out.join(_rows_of(factors, j), f"i{j}")
            at = list(product(*[range(ranks[j - 1]) for j in others]))
            terms = [F.sum(reduce(lambda x, z: x * z, [F.col("y"), *[F.get(f"u{j}", F.lit(a)) for j, a in zip(others, c, strict=True)]])) for c in at]
            projected = checkpointed(out.groupBy(F.col(f"i{k}").alias("i")).agg(F.array(*terms).alias("vec")), "projected")
            g = gram_of(projected.select(F.lit(k).alias("mode"), F.col("i").alias("idx"), "vec"), k, len(at))
            values, vectors = np.linalg.eigh(g)
            top = vectors[:, ::-1][:, : ranks[k - 1]] / np.sqrt(np.maximum(values[::-1][: ranks[k - 1]], 1e-12))
            factors = _replace(factors, k, projected.select("i", times(F.col("vec"), top).alias("vec")), ranks[k - 1])
    return factors, core_of(arr, factors, ranks)


def global_gp(arr: DataFrame, sizes: Sequence[int], ranks: Sequence[int], kernel: Kernel, iters: int = 20, rate: float = 0.05, laplace: float = 0.0, seed: int = 7, likelihood: str = "binary") -> tuple[list[np.ndarray], gp.Posterior, gp.Spectrum]:
    """One process over the whole array, on the driver; refused beyond a memory budget, which is its known limit."""
    cells = int(np.prod(sizes))
    if cells + sum(m * m for m in sizes) > GLOBAL_LIMIT:
        raise ValueError("the array is too large for a single process")
    y = np.zeros(sizes)
    for row in arr.toPandas().itertuples(index=False):
        y[tuple(int(i) - 1 for i in row[:-1])] = row[-1]
    rng = np.random.default_rng(seed)
    rows = [0.5 * rng.normal(size=(m, r)) for m, r in zip(sizes, ranks, strict=True)]
    for _ in range(iters):
        post, spec = gp.infer(rows, y, kernel, likelihood)
        step = [rate * g / max(1.0, float(np.abs(g).max())) for g in gp.factor_gradients(rows, post, spec, kernel)]
        rows = [u + s for u, s in zip(rows, step, strict=True)]
        if laplace:
            rows = [np.sign(u) * np.maximum(np.abs(u) - rate * laplace, 0) for u in rows]
    post, spec = gp.infer(rows, y, kernel, likelihood)
    return rows, post, spec


def degree_score(cells: DataFrame, weights: DataFrame) -> DataFrame:
    """A floor: the product of the weights of a cell's slices."""
    out = cells
    names = [f"i{k}" for k in range(1, order_of(cells) + 1)]
    for k, n in enumerate(names, 1):
        own = weights.filter(F.col("mode") == k).select(F.col("idx").alias(n), F.col("weight").alias(f"w{k}"))
        out = out.join(own, n, "left")
    score = reduce(lambda a, b: a * b, [F.coalesce(F.col(f"w{k}"), F.lit(0)).cast("double") for k in range(1, len(names) + 1)])
    return out.withColumn("score", score).drop(*[f"w{k}" for k in range(1, len(names) + 1)])


def impute(arr: DataFrame, cells: float, how: str = "mean") -> DataFrame:
    """What an absent cell would count as before a multilinear fit: one constant, with the cells it stands for."""
    value = F.sum("y") / F.lit(float(cells)) if how == "mean" else F.lit(0.0)
    return arr.agg(value.alias("value"), (F.lit(int(cells)) - F.count("*")).alias("absent"))


def sgd_cp(blocks: DataFrame, factors: DataFrame, rank: int, rate: float, rounds: int, shards: int, loss: str = "squared") -> DataFrame:
    """The same shards and merges for a CP model: local steps on squared or logistic loss."""
    from .train import merge_factors

    factors = checkpointed(factors, "factors")
    blocks = checkpointed(blocks, "blocks")
    for round_ in range(1, rounds + 1):
        own = {}
        for r in factors.toPandas().itertuples(index=False):  # factors of a checked, broadcastable size
            own[r.mode, r.idx] = np.array(r.vec)
        sent = blocks.sparkSession.sparkContext.broadcast(own)

        def run(frames, sent=sent):
            import pandas as pd

            from .train import densify

            for frame in frames:
                rows, base = [], sent.value
                moved: dict = {}
                for b in frame.itertuples(index=False):
                    u = [np.array([moved.get((b.shard, k + 1, i), base[k + 1, i]) for i in s]) for k, s in enumerate(b.sets)]
                    y = densify(b.lin, b.y, [len(s) for s in b.sets])
                    letters = "abcdefgh"[: len(u)]
                    fit = np.einsum(",".join(f"{c}r" for c in letters) + "->" + letters, *u)
                    err = y - (fit if loss == "squared" else 1 / (1 + np.exp(-fit)))
                    for k, s in enumerate(b.sets):
                        rest = [f"{c}r" for j, c in enumerate(letters) if j != k]
                        grad = np.einsum(",".join([letters, *rest]) + f"->{letters[k]}r", err, *[x for j, x in enumerate(u) if j != k])
                        for i, v in zip(s, u[k] + rate * np.clip(grad, -5, 5), strict=True):
                            moved[b.shard, k + 1, i] = v
                rows = [(s, k, i, (v - base[k, i]).tolist()) for (s, k, i), v in moved.items()]
                yield pd.DataFrame(rows, columns=["shard", "mode", "idx", "delta"])

        deltas = blocks.repartition(shards, "shard").sortWithinPartitions("shard", "sub_id").mapInPandas(run, "shard int, mode int, idx long, delta array<double>")
        factors = checkpointed(merge_factors(factors, deltas, shards, "mean"), "factors")
    return factors
