"""Products of the rows of an unfolded array, summed in tasks block by block.

The indices of the mode are cut into blocks of ``SIDE``. A column's nonzeros in a block are one list, and lists of one
column meet, so that a unit (two blocks) gets every list it needs and no pair of cells ever leaves a task: what is
shuffled are the lists, once for each block they meet, and what a task holds is one matrix of ``SIDE`` x ``SIDE``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS = 10
SIDE = 1 << BITS
STRIP = 64  # rows of a unit's matrix that are given out together
SMALL = 2_048  # pairs of two lists up to which many lists are expanded together
CHUNK = SIDE * SIDE  # pairs that are expanded at a time


def row_products(arr: DataFrame, k: int, others: list[str]) -> DataFrame:
    """(a, b, g): sums of products of two mode-k rows over the columns that both have; cells without an index have no row."""
    at = F.col(f"i{k}").cast("long")
    cells = arr.select(*others, F.shiftright(at, BITS).alias("block"), at.bitwiseAND(SIDE - 1).cast("smallint").alias("r"), F.col("y").cast("double").alias("y"))
    packed = cells.groupBy("block", *others).agg(F.collect_list(F.struct("r", "y")).alias("cells"))
    one, two = (packed.select(*others, F.col("block").alias(f"block{s}"), F.col("cells.r").alias(f"r{s}"), F.col("cells.y").alias(f"y{s}")) for s in "ab")
    met = one.join(two, others).filter("blocka <= blockb").select("blocka", "blockb", "ra", "ya", "rb", "yb")
    units = met.repartition("blocka", "blockb").sortWithinPartitions("blocka", "blockb")
    return units.mapInArrow(_sums, "a long, b long, g double")


class _Unit:
    """Sums of one pair of blocks. A sum may be zero: places with products of zero or below are marked."""

    def __init__(self, a: int, b: int):
        self.a, self.b = a, b
        self.g = np.zeros(SIDE * SIDE)
        self.seen = np.zeros(SIDE * SIDE, bool)  # has a product of zero or below
        self.void = np.zeros(SIDE * SIDE, bool)  # has a product with a missing value

    def put(self, at: np.ndarray, value: np.ndarray) -> None:
        np.add.at(self.g, at, value)
        low = ~(value > 0)
        if low.any():
            self.seen[at[low]] = True

    def add(self, one: tuple, two: tuple) -> None:
        """Both sides' (starts of lists, offsets in the block, values, which are missing or None)."""
        (sa, ra, ya, na), (sb, rb, yb, nb) = one, two
        pairs = np.diff(sa) * np.diff(sb)
        large = (pairs > SMALL) & (pairs <= CHUNK) & (na is None and nb is None)
        for n in np.flatnonzero(large):
            i, j = slice(sa[n], sa[n + 1]), slice(sb[n], sb[n + 1])
            self.put((ra[i, None] * SIDE + rb[j]).reshape(-1), (ya[i, None] * yb[j]).reshape(-1))
        rest = np.flatnonzero(~large)
        if not len(rest):
            return
        # the others' pairs, many lists or a part of one at a time
        first = np.concatenate([np.arange(sa[n], sa[n + 1]) for n in rest])
        own = np.repeat(rest, np.diff(sa)[rest])
        width = np.diff(sb)[own]
        upto = np.cumsum(width)
        begin = 0
        while begin < len(first):
            end = max(begin + 1, int(np.searchsorted(upto, (upto[begin - 1] if begin else 0) + CHUNK, "right")))
            w = width[begin:end]
            i = np.repeat(first[begin:end], w)
            j = np.arange(len(i)) - np.repeat(np.cumsum(w) - w, w) + np.repeat(sb[own[begin:end]], w)
            at, value = ra[i] * SIDE + rb[j], ya[i] * yb[j]
            if na is not None or nb is not None:
                gone = (na[i] if na is not None else False) | (nb[j] if nb is not None else False)
                self.void[at[gone]] = True
                at, value = at[~gone], value[~gone]
            self.put(at, value)
            begin = end

    def rows(self) -> Iterator[pa.RecordBatch]:
        own = [x.reshape(SIDE, SIDE) for x in (self.g, self.seen, self.void)]
        yield from _rows(self.a, self.b, *own)
        if self.a != self.b:
            yield from _rows(self.b, self.a, *[x.T for x in own])


def _rows(a: int, b: int, g: np.ndarray, seen: np.ndarray, void: np.ndarray) -> Iterator[pa.RecordBatch]:
    i, j = np.divmod(np.arange(STRIP * SIDE), SIDE)
    j += b * SIDE
    for top in range(0, SIDE, STRIP):
        own, marked, gone = (x[top : top + STRIP].reshape(-1) for x in (g, seen, void))
        held = (own != 0) | marked | gone
        if not held.any():
            continue
        missing = (gone & ~marked & (own == 0))[held] if gone.any() else None
        yield pa.RecordBatch.from_arrays([pa.array(i[held] + (a * SIDE + top)), pa.array(j[held]), pa.array(own[held], mask=missing)], names=["a", "b", "g"])


def _parts(batch: pa.RecordBatch, begin: int, end: int, side: str) -> tuple:
    r, y = (batch.column(f"{c}{side}").slice(begin, end - begin) for c in "ry")
    starts = r.offsets.to_numpy().astype(np.int64)
    values = y.flatten()
    gone = values.is_null().to_numpy(zero_copy_only=False) if values.null_count else None
    return starts - starts[0], r.flatten().to_numpy().astype(np.int64), values.fill_null(0.0).to_numpy(), gone


def _sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    unit = None
    for batch in batches:
        if not batch.num_rows:
            continue
        a, b = (batch.column(c).to_numpy() for c in ("blocka", "blockb"))
        cuts = [0, *(np.flatnonzero((np.diff(a) != 0) | (np.diff(b) != 0)) + 1), len(a)]
        for begin, end in zip(cuts[:-1], cuts[1:], strict=True):
            if unit is None or (unit.a, unit.b) != (int(a[begin]), int(b[begin])):
                if unit is not None:
                    yield from unit.rows()
                unit = _Unit(int(a[begin]), int(b[begin]))
            with np.errstate(all="ignore"):
                unit.add(_parts(batch, begin, end, "a"), _parts(batch, begin, end, "b"))
    if unit is not None:
        yield from unit.rows()
