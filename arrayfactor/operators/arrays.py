"""Sparse K-way arrays: building, indexing, algebra and statistics.

An array is a DataFrame of its nonzeros: one coordinate column for each mode and ``y``. Absent
coordinates are zeros. A null coordinate is dropped when an array is built.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

DIGITS = 3  # leading hex digits of the hash: 4096 ranges that rank independently


def build_array(df: DataFrame, modes: Sequence[str], value: str = "presence", of: str | None = None) -> DataFrame:
    """Nonzeros of records: presence, count, or sum of a column."""
    y = {"presence": F.lit(1.0), "count": F.count("*").cast("double"), "sum": F.sum(of) if of else None}[value]
    kept = df.dropna(subset=list(modes))
    if value == "presence":
        return kept.select(*modes).distinct().withColumn("y", y)
    return kept.groupBy(*modes).agg(y.alias("y"))


def mode_dictionary(arr: DataFrame, modes: Sequence[str], order: str = "md5") -> DataFrame:
    """(mode, idx, key, weight) for each mode; idx from 1 in the order of the keys' hashes.

    Ranks are taken inside ranges of the hash, whose sizes are added up: no task sees a whole mode.
    ``order`` may also be "key" or "weight" (largest first), for which a mode is ranked as a whole.
    """
    stacked = F.explode(F.array(*[F.struct(F.lit(k + 1).alias("mode"), F.col(m).cast("string").alias("key")) for k, m in enumerate(modes)]))
    keys = arr.select(stacked.alias("x")).select("x.*").groupBy("mode", "key").agg(F.count("*").alias("weight"))
    if order != "md5":
        by = ["key"] if order == "key" else [F.desc("weight"), "key"]
        return keys.select("mode", F.row_number().over(Window.partitionBy("mode").orderBy(*by)).cast("long").alias("idx"), "key", "weight")
    hashed = keys.withColumn("h", F.md5(F.col("key").cast("binary"))).withColumn("range", F.substring("h", 1, DIGITS))
    sizes = hashed.groupBy("mode", "range").agg(F.count("*").alias("n"))
    ahead = sizes.withColumn("ahead", F.sum("n").over(Window.partitionBy("mode").orderBy("range")) - F.col("n")).drop("n")
    place = F.row_number().over(Window.partitionBy("mode", "range").orderBy("h", "key"))
    return hashed.join(F.broadcast(ahead), ["mode", "range"]).select("mode", (F.col("ahead") + place).cast("long").alias("idx"), "key", "weight")


def encode(arr: DataFrame, dictionary: DataFrame, modes: Sequence[str]) -> DataFrame:
    """Coordinates replaced by indices i1..iK. Spark picks each join by the dictionaries' sizes."""
    out = arr
    for k, m in enumerate(modes, 1):
        own = dictionary.filter(F.col("mode") == k).select(F.col("key").alias(f"key{k}"), F.col("idx").alias(f"i{k}"))
        out = out.join(own, out[m].cast("string") == F.col(f"key{k}")).drop(m, f"key{k}")
    return out.select(*[f"i{k}" for k in range(1, len(modes) + 1)], "y")


def decode(arr: DataFrame, dictionary: DataFrame, modes: Sequence[str]) -> DataFrame:
    out = arr
    for k, m in enumerate(modes, 1):
        own = dictionary.filter(F.col("mode") == k).select(F.col("key").alias(m), F.col("idx").alias(f"i{k}"))
        out = out.join(own, f"i{k}").drop(f"i{k}")
    return out.select(*modes, "y")


def order_of(arr: DataFrame) -> int:
    return sum(c[0] == "i" and c[1:].isdigit() for c in arr.columns)


def linear_index(arr: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """``pos``: 1-based place in the stacked array, last mode fastest; a decimal beyond 63 bits."""
    total = reduce(lambda a, b: a * b, sizes, 1)
    kind = "decimal(38,0)" if total >= 1 << 63 else "long"
    pos: Column = F.lit(0).cast(kind)
    for k, m in enumerate(sizes, 1):
        pos = (pos * F.lit(m).cast(kind) + (F.col(f"i{k}") - 1).cast(kind)).cast(kind)
    return arr.withColumn("pos", (pos + 1).cast(kind))


def from_linear(arr: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """i1..iK back from ``pos``."""
    rest, out = F.col("pos") - 1, {}
    for k in range(len(sizes), 0, -1):
        out[f"i{k}"] = (F.pmod(rest, F.lit(sizes[k - 1])) + 1).cast("long")
        rest = F.floor(rest / F.lit(sizes[k - 1])) if sizes else rest
    return arr.select(*[out[f"i{k}"].alias(f"i{k}") for k in range(1, len(sizes) + 1)], *[c for c in arr.columns if c not in out])


def unfold(arr: DataFrame, k: int, sizes: Sequence[int]) -> DataFrame:
    """Mode-k matrix (row, col, y); columns run over the other modes in order, last fastest."""
    col: Column = F.lit(0).cast("long")
    for j, m in enumerate(sizes, 1):
        if j != k:
            col = col * m + (F.col(f"i{j}") - 1)
    return arr.select(F.col(f"i{k}").alias("row"), (col + 1).alias("col"), "y")


def mode_product(arr: DataFrame, matrix: DataFrame, k: int) -> DataFrame:
    """Product along mode k with a matrix of (j, i, u); the new coordinate takes the mode's place."""
    others = [f"i{j}" for j in range(1, order_of(arr) + 1) if j != k]
    joined = arr.join(matrix.select(F.col("i").alias(f"i{k}"), "j", "u"), f"i{k}")
    out = joined.groupBy("j", *others).agg(F.sum(F.col("y") * F.col("u")).alias("y"))
    return out.withColumnRenamed("j", f"i{k}").select(*[f"i{j}" for j in range(1, order_of(arr) + 1)], "y")


def attach_rows(cells: DataFrame, factors: DataFrame, modes: int) -> DataFrame:
    """Each cell with its factor row of every mode, u1..uK; factors are (mode, idx, vec)."""
    out = cells
    for k in range(1, modes + 1):
        own = factors.filter(F.col("mode") == k).select(F.col("idx").alias(f"i{k}"), F.col("vec").alias(f"u{k}"))
        out = out.join(own, f"i{k}")
    return out


def tucker_cells(cells: DataFrame, core: dict[tuple[int, ...], float], factors: DataFrame) -> DataFrame:
    """Values of a Tucker model at given cells; the core is a small literal."""
    modes = order_of(cells)
    terms = [F.lit(float(w)) * reduce(lambda a, b: a * b, [F.get(F.col(f"u{k + 1}"), F.lit(a)) for k, a in enumerate(at)]) for at, w in sorted(core.items())]
    value = reduce(lambda a, b: a + b, terms, F.lit(0.0))
    return attach_rows(cells, factors, modes).select(*[f"i{k}" for k in range(1, modes + 1)], value.alias("value"))


def cp_cells(cells: DataFrame, factors: DataFrame, rank: int, weights: Sequence[float] | None = None) -> DataFrame:
    """Values of a CP model: a Tucker model whose core is diagonal."""
    modes = order_of(cells)
    weights = weights or [1.0] * rank
    return tucker_cells(cells, {(a,) * modes: w for a, w in enumerate(weights)}, factors)


def kron(a: DataFrame, b: DataFrame, rows_b: int, cols_b: int) -> DataFrame:
    """Kronecker product of two small matrices (row, col, v), rows and columns from 1."""
    x, y = a.select(F.col("row").alias("r1"), F.col("col").alias("c1"), F.col("v").alias("v1")), b.select(F.col("row").alias("r2"), F.col("col").alias("c2"), F.col("v").alias("v2"))
    return x.join(F.broadcast(y), F.lit(True)).select(((F.col("r1") - 1) * rows_b + F.col("r2")).alias("row"), ((F.col("c1") - 1) * cols_b + F.col("c2")).alias("col"), (F.col("v1") * F.col("v2")).alias("v"))


def frobenius(arr: DataFrame) -> DataFrame:
    return arr.agg(F.sqrt(F.sum(F.col("y") * F.col("y"))).alias("norm"))


def inner(a: DataFrame, b: DataFrame) -> DataFrame:
    at = [f"i{k}" for k in range(1, order_of(a) + 1)]
    return a.join(b.select(*at, F.col("y").alias("z")), at).agg(F.coalesce(F.sum(F.col("y") * F.col("z")), F.lit(0.0)).alias("inner"))


def array_stats(arr: DataFrame, modes: Sequence[str], name: str) -> DataFrame:
    """Sizes, cells, nonzeros and density of an array with the given coordinate columns."""
    counts = arr.agg(*[F.count_distinct(m).alias(f"m{k}") for k, m in enumerate(modes, 1)], F.count("*").alias("nnz"))
    sizes = [F.col(f"m{k}") for k in range(1, len(modes) + 1)]
    cells = reduce(lambda a, b: a * b, [s.cast("double") for s in sizes])
    return counts.select(F.lit(name).alias("name"), *sizes, *[F.lit(None).cast("long").alias(f"m{k}") for k in range(len(modes) + 1, 5)], cells.alias("cells"), "nnz", F.round(100 * F.col("nnz") / cells, 6).alias("density_pct"))


def slice_weights(arr: DataFrame) -> DataFrame:
    """(mode, idx, weight): nonzeros of every slice, all modes in one pass."""
    modes = order_of(arr)
    at = F.explode(F.array(*[F.struct(F.lit(k).alias("mode"), F.col(f"i{k}").alias("idx")) for k in range(1, modes + 1)]))
    return arr.select(at.alias("x")).select("x.*").groupBy("mode", "idx").agg(F.count("*").alias("weight"))


def slice_weights_by_sets(arr: DataFrame) -> DataFrame:
    """The same by grouping sets."""
    modes = order_of(arr)
    names = [f"i{k}" for k in range(1, modes + 1)]
    sets = arr.groupingSets([[n] for n in names], *names).agg(F.grouping_id().alias("g"), F.count("*").alias("weight"))
    mode = reduce(lambda acc, k: acc.when(F.col("g") == (2**modes - 1) - 2 ** (modes - k), k), range(2, modes + 1), F.when(F.col("g") == (2**modes - 1) - 2 ** (modes - 1), 1))
    return sets.select(mode.alias("mode"), F.coalesce(*names).alias("idx"), "weight")


def restrict_top(arr: DataFrame, mode: str, n: int) -> DataFrame:
    """Only cells whose coordinate is among the n most frequent; ties by the smaller key."""
    top = arr.groupBy(mode).agg(F.count("*").alias("n")).orderBy(F.desc("n"), mode).limit(n).select(mode)
    return arr.join(top, mode, "left_semi").select(*arr.columns)


def filter_confidence(arr: DataFrame, column: str, least: float) -> DataFrame:
    return arr.filter(F.col(column) >= least)


def permute_modes(arr: DataFrame, seed: int) -> DataFrame:
    """Each mode's indices exchanged by a keyed hash order, modes separately."""
    from ..functions.hashing import keyed

    out = arr
    for k in range(1, order_of(arr) + 1):
        own = arr.select(F.col(f"i{k}").alias("old")).distinct().withColumn("h", F.md5(keyed(seed, k, F.col("old")).cast("binary")))
        # the range of the hash stands for the rank's leading part, as in the dictionary
        own = own.withColumn("range", F.substring("h", 1, DIGITS))
        sizes = own.groupBy("range").agg(F.count("*").alias("n")).withColumn("ahead", F.sum("n").over(Window.orderBy("range")) - F.col("n")).drop("n")
        place = F.row_number().over(Window.partitionBy("range").orderBy("h", "old"))
        ranked = own.join(F.broadcast(sizes), "range").select("old", (F.col("ahead") + place).cast("long").alias("new"))
        out = out.join(ranked, out[f"i{k}"] == ranked.old).drop(f"i{k}", "old").withColumnRenamed("new", f"i{k}")
    return out.select(*arr.columns)
