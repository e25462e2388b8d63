"""Prediction by averaging the predictive means of small processes on randomly drawn bags."""

from __future__ import annotations

import pickle
from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import gp
from ..functions.normal import cdf
from ..sources.tables import checkpointed
from .arrays import attach_rows, order_of
from .sampling import blocks, index_sets
from .train import Model, densify

BAGS_LIMIT = 512_000_000
GROUP = 512  # batches that share a task's nonzeros
PIECE = 4_096  # nonzeros of a slice in one row


def fit_bags(model: Model, arr: DataFrame, plan: DataFrame, sizes: Sequence[int]) -> list[tuple]:
    """(rows, posterior, spectrum) of each bag; there are few, of the size of a subarray each, inferred in one task a bag."""
    from .train import _with_rows

    p = model.params
    options = {"sweeps": p.sweeps, "offset": p.offset} if p.likelihood == "binary" else {}
    bags = plan.select("sub_id").distinct().count()
    size = 24 * bags * int(np.prod(sizes))
    if size > BAGS_LIMIT:
        raise ValueError(f"bags take {size} bytes; draw fewer or smaller ones")

    def infer(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for row in frame.itertuples(index=False):
                rows = [np.array([np.asarray(v) for v in r]) for r in row.rows]
                y = densify(row.lin, row.y, [len(s) for s in row.sets])
                post, spec = gp.infer(rows, y, p.kernel, p.likelihood, **options)
                yield pd.DataFrame({"sub_id": [row.sub_id], "bag": [pickle.dumps((rows, post, spec))]})

    own = _with_rows(blocks(arr, plan, sizes, max(bags, 1)), model.factors).repartitionById(max(bags, 1), "shard")
    return [pickle.loads(r.bag) for r in own.mapInPandas(infer, "sub_id long, bag binary").orderBy("sub_id").collect()]


def predict(model: Model, arr: DataFrame, cells: DataFrame, plan: DataFrame, sizes: Sequence[int], rule: str = "mean") -> DataFrame:
    """Cells with mean, var, prob and votes; rule "mean" weighs bags alike, "variance" by inverse variance.

    Bags go to every task; cells meet their own factor rows by joins and are scored batch by batch.
    """
    modes, kernel, offset = order_of(cells), model.params.kernel, model.params.offset
    bags = cells.sparkSession.sparkContext.broadcast(fit_bags(model, arr, plan, sizes))
    names = [f"i{k}" for k in range(1, modes + 1)]
    kept = [c for c in cells.columns if c not in names]
    found = attach_rows(cells, model.factors, modes)
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in cells.select(*names, *kept).schema)

    def score(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            total = np.zeros((3, len(frame)))
            points = [np.array(frame[f"u{k}"].tolist(), float).reshape(len(frame), -1) for k in range(1, modes + 1)]
            for rows, post, spec in bags.value if len(frame) else ():
                mean, var = gp.predictive(points, rows, post, spec, kernel)
                w = 1 / np.maximum(var, 1e-9) if rule == "variance" else np.ones_like(mean)
                total += np.stack([w * mean, w * var, w])
            mean, var = total[0] / np.maximum(total[2], 1e-300) + offset, total[1] / np.maximum(total[2], 1e-300)
            yield frame[names + kept].assign(mean=mean, var=var, prob=cdf(mean / np.sqrt(1 + var)), votes=len(bags.value))

    found = found.repartition(cells.sparkSession.sparkContext.defaultParallelism)  # the work is in the cells, not in their bytes
    return found.mapInPandas(score, f"{fields}, mean double, var double, prob double, votes int")


def predict_containing(model: Model, arr: DataFrame, cells: DataFrame, plan: DataFrame, sizes: Sequence[int], batch: int = 10) -> DataFrame:
    """The other reading: a batch of cells' indices is added to every bag, the cells themselves are unseen,
    and the posterior mean is read where they stand; averaged over bags.

    Batches are groups of ``batch`` cells. Some hundreds of batches go to a task, once with the bags, the factor rows and
    the nonzeros that they share; the task cuts each enlarged bag out of these and holds one at a time.
    """
    modes, p = order_of(cells), model.params
    names = [f"i{k}" for k in range(1, modes + 1)]
    part = F.pmod(F.xxhash64(*names), F.lit(64))
    numbered = cells.select(*names, (F.floor((F.row_number().over(Window.partitionBy(part).orderBy(*names)) - 1) / batch) * 64 + part).alias("batch"))
    numbered = checkpointed(numbered, "batches")
    batches = numbered.select("batch").distinct().count()
    groups = max(min(batches, cells.sparkSession.sparkContext.defaultParallelism), -(-batches // GROUP), 1)
    numbered = numbered.withColumn("grp", F.pmod("batch", F.lit(groups)).cast("int"))
    spots = lambda frame, k: frame.select("grp", F.lit(k).alias("mode"), F.col(f"i{k}").alias("idx"))
    used = reduce(DataFrame.unionByName, [spots(numbered, k) for k in range(1, modes + 1)])
    everywhere = F.broadcast(numbered.select("grp").distinct())  # a row a group
    used = checkpointed(used.unionByName(plan.select("mode", "idx").join(everywhere, F.lit(True))).distinct(), "used")

    shared = {
        "bag": index_sets(plan).join(everywhere, F.lit(True)).select("grp", F.col("sub_id").alias("n"), F.col("sets").alias("idx"), F.array().cast("array<array<double>>").alias("val")),
        "batch": numbered.groupBy("grp", "batch").agg(F.collect_list(F.struct(*names)).alias("c")).select("grp", F.col("batch").alias("n"), F.array(*[F.col(f"c.{n}") for n in names]).alias("idx"), F.array().cast("array<array<double>>").alias("val")),
        "factors": used.join(model.factors, ["mode", "idx"]).groupBy("grp", "mode").agg(F.array_sort(F.collect_list(F.struct("idx", "vec"))).alias("c")).select("grp", F.col("mode").cast("long").alias("n"), F.array("c.idx").alias("idx"), F.col("c.vec").alias("val")),
        "nonzeros": _pieces(arr, int(np.argmax(model.sizes)) + 1, used),
    }
    rows = reduce(DataFrame.unionByName, [df.withColumn("kind", F.lit(kind)) for kind, df in enumerate(shared.values())])
    rows = rows.repartitionById(groups, "grp").sortWithinPartitions("grp", "kind", "n")

    def infer(group: _Group) -> pd.DataFrame:
        out = []
        for wanted in group.batches:
            spots = [np.searchsorted(own, i) for own, i in zip(group.index, wanted, strict=True)]
            for drawn in group.bags:
                sets = [np.union1d(a, b) for a, b in zip(drawn, spots, strict=True)]
                y = group.block(sets)
                at, mask = tuple(np.searchsorted(s, i) for s, i in zip(sets, spots, strict=True)), np.ones(y.shape, bool)
                mask[at] = False
                post, _ = gp.infer([v[s] for v, s in zip(group.vecs, sets, strict=True)], y, p.kernel, p.likelihood, sweeps=p.sweeps, mask=mask, offset=p.offset)
                out.append(np.stack([*wanted, post.mean[at]]))
        table = np.concatenate(out, axis=1) if out else np.zeros((modes + 1, 0))
        return pd.DataFrame({n: table[k].astype(np.int64) for k, n in enumerate(names)} | {"mean": table[-1]})

    def read(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        group = None
        for frame in frames:
            for row in frame.itertuples(index=False):
                if group is None or row.grp != group.number:
                    if group is not None:
                        yield infer(group)
                    group = _Group(row.grp, modes)
                group.add(row)
        if group is not None:
            yield infer(group)

    got = rows.mapInPandas(read, ", ".join(f"{n} long" for n in names) + ", mean double")
    means = got.groupBy(*names).agg((F.avg("mean") + p.offset).alias("mean"), F.count("*").cast("int").alias("votes"))
    return cells.join(means, names)


def _pieces(arr: DataFrame, mode: int, used: DataFrame) -> DataFrame:
    """(grp, n, idx, val): the slices of a mode that each group uses, in pieces of about ``PIECE`` nonzeros."""
    names, own = [f"i{k}" for k in range(1, order_of(arr) + 1)], f"i{mode}"
    many = arr.groupBy(own).agg(F.ceil(F.count("*") / PIECE).alias("many"))
    packed = arr.join(many, own).groupBy(own, F.pmod(F.xxhash64(*names), F.col("many")).alias("piece")).agg(F.collect_list(F.struct(*names, "y")).alias("c"))
    packed = packed.select(F.col(own).alias("idx"), "piece", F.array(*[F.col(f"c.{n}") for n in names]).alias("at"), F.array("c.y").alias("val"))
    wanted = used.filter(F.col("mode") == mode).select("grp", "idx")
    return packed.join(wanted, "idx").select("grp", F.col("piece").alias("n"), F.col("at").alias("idx"), "val")


class _Group:
    """What the batches of a task share; indices are places among the group's own indices of a mode."""

    def __init__(self, number: int, modes: int):
        self.number, self.modes = number, modes
        self.bags, self.batches, self.pieces = [], [], []
        self.index, self.vecs, self.fibres = [], [], None

    def add(self, row) -> None:
        """Rows come in the order of their kinds: bags, batches, factor rows mode after mode, nonzeros."""
        idx = [np.asarray(i, np.int64) for i in row.idx]
        if row.kind == 0:
            self.bags.append(idx)
        elif row.kind == 1:
            self.batches.append(idx)
        elif row.kind == 2:
            self.index.append(idx[0])
            self.vecs.append(np.array([np.asarray(v, float) for v in row.val]))
            if len(self.index) == self.modes:
                self.bags = [[np.searchsorted(own, i) for own, i in zip(self.index, bag, strict=True)] for bag in self.bags]
        else:
            at = [np.minimum(np.searchsorted(own, i), len(own) - 1) for own, i in zip(self.index, idx, strict=True)]
            inside = np.logical_and.reduce([own[a] == i for own, a, i in zip(self.index, at, idx, strict=True)])
            self.pieces.append([*[a[inside].astype(np.int32) for a in at], np.asarray(row.val[0], float)[inside]])

    def _sorted(self) -> tuple:
        """Nonzeros as fibres of the last mode: (numbers of the fibres, starts, ends, places in the mode, values)."""
        *at, y = [np.concatenate(c) for c in zip(*self.pieces, strict=True)] if self.pieces else [np.zeros(0, np.int32)] * self.modes + [np.zeros(0)]
        self.pieces = []
        number = self._number(at[:-1])
        order = np.argsort(number, kind="stable")
        heads, starts = np.unique(number[order], return_index=True)
        return heads, starts, np.append(starts[1:], len(order)), at[-1][order], y[order]

    def _number(self, at: Sequence[np.ndarray]) -> np.ndarray:
        out = np.zeros(1, np.int64)
        for own, a in zip(self.index, at, strict=False):
            out = out * len(own) + a
        return out

    def block(self, sets: Sequence[np.ndarray]) -> np.ndarray:
        """The dense block of these index sets."""
        if self.fibres is None:
            self.fibres = self._sorted()
        heads, starts, ends, last, values = self.fibres
        y = np.zeros([len(s) for s in sets])
        number = self._number(np.ix_(*sets[:-1])).ravel()
        at = np.searchsorted(heads, number)
        found = np.flatnonzero(heads.take(at, mode="clip") == number) if len(heads) else np.zeros(0, np.int64)
        at = at[found]
        n = ends[at] - starts[at]
        cells = np.repeat(starts[at] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        place = np.full(len(self.index[-1]), -1)
        place[sets[-1]] = np.arange(len(sets[-1]))
        to = place[last[cells]]
        y.reshape(-1, y.shape[-1])[np.repeat(found, n)[to >= 0], to[to >= 0]] = values[cells[to >= 0]]
        return y


def bag_mean(scores: DataFrame, by: Sequence[str], weight: str | None = None) -> DataFrame:
    """Aggregated scores of bags: equal weights, or a column's."""
    mean = F.sum(F.col("mean") * F.col(weight)) / F.sum(weight) if weight else F.avg("mean")
    return scores.groupBy(*by).agg(mean.alias("mean"), F.count("*").alias("votes"))


def top_links(scores: DataFrame, mode: str, k: int, others: Sequence[str]) -> DataFrame:
    """The k highest-scored cells of every index of a mode."""
    rank = F.row_number().over(Window.partitionBy(mode).orderBy(F.desc("mean"), *others))
    return scores.withColumn("rank", rank).filter(F.col("rank") <= k)
