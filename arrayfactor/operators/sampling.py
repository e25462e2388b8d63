"""Which small subarrays to train and predict on, and how to cut them out of the array.

A plan is (sub_id, mode, pos, idx): for each subarray and mode its indices in order. Every draw
depends on the seed, the subarray and the mode only, so a plan is the same for any partitioning.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import keyed, uniform
from ..sources.tables import by_mode
from .arrays import order_of

PLAN = "sub_id long, mode int, pos int, idx long"


def sample_by_hash(slices: DataFrame, count: int, sizes: Sequence[int], seed: int, weighted: bool = False) -> DataFrame:
    """Uniform or weighted plans by ranking hashed keys of every (subarray, index).

    ``slices`` is (mode, idx, weight). Weighted draws rank -log(u)/weight, which picks without
    replacement in proportion to the weights; weightless slices do not occur in it. The cost is the
    number of subarrays times the modes' sizes: a form for checking and for moderate modes.
    """
    subs = slices.sparkSession.range(count).select(F.col("id").alias("sub_id"))
    u = uniform(keyed(seed, F.col("sub_id"), F.col("mode"), F.col("idx")))
    key = -F.log(F.greatest(u, F.lit(1e-300))) / F.col("weight") if weighted else u
    ranked = slices.join(F.broadcast(subs), F.lit(True)).withColumn("pos", F.row_number().over(Window.partitionBy("sub_id", "mode").orderBy(key, "idx")))
    limit = F.element_at(F.lit(list(sizes)), F.col("mode"))
    return ranked.filter(F.col("pos") <= limit).select("sub_id", "mode", "pos", "idx")


def _draw(seed: int, sub: int, mode: int) -> np.random.Generator:
    return np.random.default_rng([seed, sub, mode])


def sample_uniform(spark: SparkSession, array_sizes: Sequence[int], count: int, sizes: Sequence[int], seed: int) -> DataFrame:
    """Uniform plans drawn in the tasks: work in proportion to the indices drawn, whatever the modes' sizes."""
    shape, block = list(array_sizes), list(sizes)

    def draw(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for sub in frame["id"]:
                for k, (m, b) in enumerate(zip(shape, block, strict=True), 1):
                    rng = _draw(seed, int(sub), k)
                    own = rng.permutation(m)[:b] if m <= 4 * b else _distinct(rng, m, b)
                    rows += [(int(sub), k, p, int(i) + 1) for p, i in enumerate(sorted(own), 1)]
            yield pd.DataFrame(rows, columns=["sub_id", "mode", "pos", "idx"])

    return spark.range(count).mapInPandas(draw, PLAN)


def _distinct(rng: np.random.Generator, m: int, b: int) -> list[int]:
    got: dict[int, None] = {}
    while len(got) < b:
        got.update(dict.fromkeys(rng.integers(0, m, b - len(got)).tolist()))
    return list(got)


WEIGHTS_LIMIT = 64_000_000  # bytes of slice weights that may go to every task


def sample_weighted(slices: DataFrame, count: int, sizes: Sequence[int], seed: int) -> DataFrame:
    """Weighted plans: slices drawn in proportion to their nonzeros, without repeats.

    Weights go to the tasks where their checked size allows it; beyond that the hash form is used.
    A mode with fewer nonempty slices than wanted gives all it has.
    """
    n = slices.count()
    if 24 * n > WEIGHTS_LIMIT:
        return sample_by_hash(slices, count, sizes, seed, weighted=True)
    table = {k: (idx, weight.cumsum()) for k, (idx, weight) in by_mode(slices, "weight").items()}
    sent = slices.sparkSession.sparkContext.broadcast(table)
    block = list(sizes)

    def draw(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for sub in frame["id"]:
                for k, b in enumerate(block, 1):
                    idx, cum = sent.value[k]
                    rng, got = _draw(seed, int(sub), k), {}
                    if len(idx) <= b:
                        got = dict.fromkeys(idx.tolist())
                    while len(got) < min(b, len(idx)):
                        got.update(dict.fromkeys(idx[np.minimum(np.searchsorted(cum, rng.random(b - len(got)) * cum[-1], side="right"), len(idx) - 1)].tolist()))
                    out += [(int(sub), k, p, int(i)) for p, i in enumerate(sorted(got), 1)]
            yield pd.DataFrame(out, columns=["sub_id", "mode", "pos", "idx"])

    return slices.sparkSession.range(count).mapInPandas(draw, PLAN)


def grid_segments(slices: DataFrame, sizes: Sequence[int], seed: int) -> DataFrame:
    """(mode, idx, segment): each mode's indices in a random order, cut into segments of equal size."""
    u = F.md5(keyed(seed, F.col("mode"), F.col("idx")).cast("binary"))
    rank = F.row_number().over(Window.partitionBy("mode").orderBy(u, "idx"))
    return slices.select("mode", "idx", F.floor((rank - 1) / F.element_at(F.lit(list(sizes)), F.col("mode"))).cast("long").alias("segment"))


def grid_cubes(arr: DataFrame, segments: DataFrame) -> DataFrame:
    """Nonzeros with the numbers of their cube's segments, s1..sK: lookups only, the array is not multiplied."""
    out = arr
    for k in range(1, order_of(arr) + 1):
        own = segments.filter(F.col("mode") == k).select(F.col("idx").alias(f"i{k}"), F.col("segment").alias(f"s{k}"))
        out = out.join(own, f"i{k}")
    return out


def grid_plan(segments: DataFrame, array_sizes: Sequence[int], sizes: Sequence[int]) -> DataFrame:
    """The plan of all cubes of a grid; the short last segment keeps its own length."""
    parts = [math.ceil(m / b) for m, b in zip(array_sizes, sizes, strict=True)]
    out = None
    total = math.prod(parts)
    place = Window.partitionBy("mode", "segment").orderBy("idx")
    placed = segments.withColumn("pos", F.row_number().over(place))
    for k in range(1, len(parts) + 1):
        inner = math.prod(parts[k:])
        cubes = segments.sparkSession.range(total).select(F.col("id").alias("sub_id"), F.pmod(F.floor(F.col("id") / inner), F.lit(parts[k - 1])).alias("segment"))
        own = placed.filter(F.col("mode") == k).join(cubes, "segment").select("sub_id", "mode", "pos", "idx")
        out = own if out is None else out.unionByName(own)
    return out


def sample_grid(spark: SparkSession, array_sizes: Sequence[int], sizes: Sequence[int], repeats: int, seed: int) -> DataFrame:
    """The plans of ``repeats`` grids over whole modes, each with its own permutation: every cell once a repeat."""
    every, out = None, None
    for k, m in enumerate(array_sizes, 1):
        own = spark.range(1, m + 1).select(F.lit(k).alias("mode"), F.col("id").alias("idx"))
        every = own if every is None else every.unionByName(own)
    total = math.prod(math.ceil(m / b) for m, b in zip(array_sizes, sizes, strict=True))
    for r in range(repeats):
        plan = grid_plan(grid_segments(every, sizes, seed + 1000 * r), array_sizes, sizes).withColumn("sub_id", F.col("sub_id") + r * total)
        out = plan if out is None else out.unionByName(plan)
    return out


def subarrays_for_coverage(sizes: Sequence[int], cells: float | Column, coverage: float = 1.0) -> int | Column:
    """How many subarrays of these sides visit ``coverage`` times as many cells as the array has; of a column of cells, a column."""
    if isinstance(cells, Column):
        return F.ceil(cells * coverage / float(math.prod(sizes)))
    return math.ceil(coverage * cells / math.prod(sizes))


def assign_shards(plan: DataFrame, shards: int, seed: int = 0) -> DataFrame:
    """(sub_id, shard) with equal counts: subarrays in hash order, dealt in turn; ranked inside ranges of the hash."""
    hashed = plan.select("sub_id").distinct().withColumn("h", F.md5(keyed(seed, F.col("sub_id")).cast("binary"))).withColumn("range", F.substring("h", 1, 2))
    sizes = hashed.groupBy("range").agg(F.count("*").alias("n"))  # 256 rows at most
    ahead = sizes.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("ahead"))
    rank = F.col("ahead") + F.row_number().over(Window.partitionBy("range").orderBy("h", "sub_id"))
    return hashed.join(F.broadcast(ahead), "range").select("sub_id", F.pmod(rank - 1, F.lit(shards)).cast("int").alias("shard"))


def extract(arr: DataFrame, plan: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """(sub_id, lin, y): nonzeros inside each subarray with their place in the block, last mode fastest.

    Pairs of indices of the two largest modes meet the cells; the indices of the other modes come with the pair,
    which is no more than the subarray's cells together.
    """
    modes = order_of(arr)
    first, *others = sorted(range(1, modes + 1), key=lambda k: -sizes[k - 1])
    kept = [F.collect_list(F.when(F.col("mode") == k, F.struct("idx", "pos"))).alias(f"m{k}") for k in range(1, modes + 1)]
    pairs = plan.groupBy("sub_id").agg(*kept)
    for k in (first, *others[:1]):
        pairs = pairs.withColumn("x", F.explode(f"m{k}")).withColumn(f"i{k}", F.col("x.idx")).withColumn(f"p{k}", F.col("x.pos")).drop("x", f"m{k}")
    met = [f"i{k}" for k in (first, *others[:1])]
    spark = arr.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    out = arr.join(pairs.repartition(tasks, *met), met)  # the work is in the cells met, not in the pairs' bytes
    for k in others[1:]:
        place = F.array_position(F.col(f"m{k}.idx"), F.col(f"i{k}"))
        out = out.filter(place > 0).withColumn(f"p{k}", F.element_at(F.col(f"m{k}.pos"), place.cast("int")))
    lin = F.lit(0)
    for k in range(1, modes + 1):
        lin = lin * sizes[k - 1] + (F.col(f"p{k}") - 1)
    return out.select("sub_id", lin.cast("int").alias("lin"), "y")


def index_sets(plan: DataFrame) -> DataFrame:
    """(sub_id, sets): the indices of each subarray, a list a mode."""
    own = plan.groupBy("sub_id", "mode").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "idx"))), lambda x: x["idx"]).alias("set"))
    return own.groupBy("sub_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("mode", "set"))), lambda x: x["set"]).alias("sets"))


def blocks(arr: DataFrame, plan: DataFrame, sizes: Sequence[int], shards: int, seed: int = 0) -> DataFrame:
    """(shard, sub_id, sets, lin, y): one row a subarray, dealt to shards in equal numbers; subarrays without nonzeros are there as well."""
    sets = index_sets(plan)
    found = extract(arr, plan, sizes).groupBy("sub_id").agg(F.array_sort(F.collect_list(F.struct("lin", "y"))).alias("cells"))
    joined = sets.join(assign_shards(plan, shards, seed), "sub_id").join(found, "sub_id", "left").withColumn("cells", F.coalesce("cells", F.array().cast("array<struct<lin:int,y:double>>")))

    def place(lin):
        """The cell's place in the subarray's own shape: a grid's last segments are shorter."""
        out = F.lit(0)
        for k, side in enumerate(sizes):
            inner = math.prod(sizes[k + 1 :])
            out = out * F.size(F.get("sets", F.lit(k))) + F.pmod(F.floor(lin / inner), F.lit(side))
        return out.cast("int")

    return joined.select("shard", "sub_id", "sets", F.transform("cells", lambda c: place(c["lin"])).alias("lin"), F.transform("cells", lambda c: c["y"]).alias("y"))


def coverage(arr: DataFrame, plan: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """(sub_id, nnz): nonzeros of each subarray, zero included."""
    found = extract(arr, plan, sizes).groupBy("sub_id").agg(F.count("*").alias("nnz"))
    return plan.select("sub_id").distinct().join(found, "sub_id", "left").select("sub_id", F.coalesce("nnz", F.lit(0)).alias("nnz"))
