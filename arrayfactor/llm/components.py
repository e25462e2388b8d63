"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .runtime import materialise, release

SALTS = 64
CONTRACT = 1 << 20


def with_group(rows: DataFrame, by: str, spread: str, only: str = "true", **measures: Column) -> DataFrame:
    """``rows`` with aggregates over all rows that are equal in ``by``, for the groups that ``only`` holds for.

    Aggregates are combined before they are shuffled. They come back to a group's rows in up to ``SALTS``
    portions, each with the part of the rows whose ``spread`` hashes to it, so that the rows of any
    group, however frequent, are dealt over many tasks; a bit mask names the portions a group needs.
    """
    salted = rows.withColumn("salt", F.pmod(F.xxhash64(spread), F.lit(SALTS)).cast("int"))
    groups = salted.groupBy(by).agg(*[m.alias(n) for n, m in measures.items()], F.bit_or(F.expr("shiftleft(1L, salt)")).alias("salts")).filter(only)
    portions = groups.withColumn("salt", F.explode(F.expr(f"filter(sequence(0, {SALTS - 1}), i -> getbit(salts, i) = 1)"))).drop("salts")
    return salted.join(portions, [by, "salt"]).select(*rows.columns, *measures)


def _attach_least(pairs: DataFrame) -> DataFrame:
    """Each (u, v) with the least node m among u and all its v."""
    return with_group(pairs, "u", "v", least=F.min("v")).select("u", "v", F.least("u", "least").alias("m"))


def stars(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node reachable) of every node of these edges but the least ones themselves."""
    node, place = np.unique(np.concatenate([u, v]), return_inverse=True)
    x, y = place[: len(u)], place[len(u) :]
    root = np.arange(len(node))
    while (root[x] != root[y]).any():
        a, b = root[x], root[y]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while (root[root] != root).any():
            root = root[root]
    moved = root != np.arange(len(node))
    return node[moved], node[root[moved]]


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stars in place of a partition's edges, ``CONTRACT`` at a time: the same nodes stay connected."""
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def put() -> pa.RecordBatch:
        u, v = stars(*(np.concatenate(side) for side in zip(*held, strict=True)))
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

    for batch in batches:
        held.append((batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)))
        if sum(len(u) for u, _ in held) >= CONTRACT:
            yield put()
    if held:
        yield put()


def _contracted(edges: DataFrame, about: int) -> DataFrame:
    """Distinct edges (u, v), ``about`` so many, contracted within partitions of some ``CONTRACT`` rows each.

    The number only sizes the partitions: in any of them ``CONTRACT`` edges are held at a time.
    """
    return edges.filter("u != v").distinct().coalesce(-(-about // CONTRACT) or 1).mapInArrow(_contract, "u long, v long")


def _forest(now: DataFrame) -> bool:
    """Whether these are stars: no node is both a child and a parent, and a child has one parent."""
    roles = now.select("u", F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(now.select(F.col("v").alias("u"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    sums = roles.groupBy("u").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return not sums.filter("up > 1 or (up > 0 and down > 0)").limit(1).count()


def components(edges: DataFrame, label: str = "components") -> DataFrame:
    """(node, root) for every node of the undirected ``edges`` (a, b); root is the least node reachable.

    The edges of each partition are contracted to stars before every round, which leaves less to shuffle
    and fewer rounds: one task does the work where all edges are one partition of ``CONTRACT`` (16 MB). A round writes what is left to the shared scratch folder. It ends when every
    edge joins a node to a root. No list of neighbours is ever gathered, so a node of any degree is fine.
    """
    now = materialise(_contracted(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")), edges.count()), label)
    while not _forest(now):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _attach_least(both).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.filter("u != v").distinct()
        small = _attach_least(large)  # here every v < u
        merged = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        after = materialise(_contracted(merged, now.count()), label)
        release(edges.sparkSession, now)
        now = after
    roots = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("root"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
