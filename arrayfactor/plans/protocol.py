"""Splits and test sets."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import keyed, uniform
from ..operators.arrays import order_of


def _at(arr: DataFrame) -> list[str]:
    return [f"i{k}" for k in range(1, order_of(arr) + 1)]


def kfold(arr: DataFrame, folds: int, seed: int, columns: Sequence[str] | None = None) -> DataFrame:
    """``fold`` of each nonzero, from a hash of its coordinates."""
    names = columns or _at(arr)
    return arr.withColumn("fold", F.floor(uniform(keyed(seed, *[F.col(c) for c in names])) * folds).cast("long"))


def split(arr: DataFrame, share: float, seed: int, columns: Sequence[str] | None = None) -> tuple[DataFrame, DataFrame]:
    names = columns or _at(arr)
    marked = arr.withColumn("_u", uniform(keyed(seed, *[F.col(c) for c in names])))
    return marked.filter(F.col("_u") < share).drop("_u"), marked.filter(F.col("_u") >= share).drop("_u")


def zero_candidates(arr: DataFrame, sizes: Sequence[int], count: int, seed: int, sets: int = 1) -> DataFrame:
    """(set_id, i1..iK, y=0): distinct random coordinates that are not nonzeros, by an anti-join."""
    draws = arr.sparkSession.range(count).select(F.col("id").alias("n")).join(F.broadcast(arr.sparkSession.range(sets).select(F.col("id").alias("set_id"))), F.lit(True))
    at = [(F.floor(uniform(keyed(seed, "z", F.col("set_id"), F.col("n"), k)) * m) + 1).cast("long").alias(f"i{k}") for k, m in enumerate(sizes, 1)]
    drawn = draws.select("set_id", *at).distinct()
    return drawn.join(arr.select(*_at(arr)), _at(arr), "left_anti").select("set_id", *_at(arr), F.lit(0.0).alias("y"))


def zeros_by_share(arr: DataFrame, sizes: Sequence[int], share: float, seed: int) -> DataFrame:
    """About ``share`` of the array's zero cells, for the small-data protocol."""
    total = 1
    for m in sizes:
        total *= m
    return zero_candidates(arr, sizes, max(1, round(share * total)), seed).drop("set_id")


def holdout_sets(arr: DataFrame, sizes: Sequence[int], share: float, sets: int, ones: int, zeros: int, seed: int) -> tuple[DataFrame, DataFrame]:
    """(training nonzeros, test sets): each set has ``ones`` held-out nonzeros and ``zeros`` zeros, by hash rank."""
    train, rest = split(arr, share, seed)
    ids = F.broadcast(arr.sparkSession.range(sets).select(F.col("id").alias("set_id")))
    drawn = rest.select(*_at(arr)).join(ids, F.lit(True)).withColumn("_u", uniform(keyed(seed, "o", F.col("set_id"), *[F.col(c) for c in _at(arr)])))
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy("_u", *_at(arr)))
    picked = drawn.withColumn("_r", rank).filter(F.col("_r") <= ones).select("set_id", *_at(arr), F.lit(1.0).alias("y"))
    blank = zero_candidates(arr, sizes, 2 * zeros, seed, sets)
    blank = blank.withColumn("_r", F.row_number().over(Window.partitionBy("set_id").orderBy(uniform(keyed(seed, "b", F.col("set_id"), *[F.col(c) for c in _at(arr)])), *_at(arr)))).filter(F.col("_r") <= zeros).drop("_r")
    return train, picked.unionByName(blank)
