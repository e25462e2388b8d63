"""Queries that train, predict and compare models. They return typed rows; tests hold their invariants."""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as w
from .functions.kernels import Kernel
from .operators import arrays, baselines, measures, predict, sampling, train
from .plans import cost, protocol
from .sources.tables import checkpointed
from .streaming import events as st

QUERIES: dict = {}
SHARDS = 24  # of the passes over a whole array
HISTORY = "method string, round int, bound double, delta_norm double, rows_touched long, subarrays long, coverage double, seconds double"


def query(key: str):
    def add(f):
        QUERIES[key] = f
        return f

    return add


def small_params(**changes) -> train.TrainParams:
    base = dict(ranks=(3, 3, 3), rounds=3, rate=0.05, variance=1.0, kernel=Kernel("rbf", scale=1.0), sweeps=6)
    return train.TrainParams(**(base | changes))


def draw_plan(arr: DataFrame, sizes: list[int], how: str, count: int, sides: list[int], seed: int = 9) -> DataFrame:
    """A training plan by one of the three strategies."""
    sides = [min(s, m) for s, m in zip(sides, sizes, strict=True)]
    if how == "uniform":
        return sampling.sample_uniform(arr.sparkSession, sizes, count, sides, seed)
    if how == "weighted":
        return sampling.sample_weighted(arrays.slice_weights(arr), count, sides, seed)
    cubes = int(np.prod([-(-m // b) for m, b in zip(sizes, sides, strict=True)]))
    return sampling.sample_grid(arr.sparkSession, sizes, sides, max(1, round(count / cubes)), seed)


def covering(sides: list[int], sizes: list[int]) -> int:
    """Subarrays that together have as many cells as the array."""
    return sampling.subarrays_for_coverage(sides, math.prod(sizes))


def fitted(arr: DataFrame, sizes: list[int], how: str, p: train.TrainParams, count: int | None = 24, sides: tuple[int, ...] = (12, 12, 12), shards: int = 3, **options) -> train.Model:
    """A model trained on ``count`` subarrays, or on as many as visit each cell once on average."""
    sides = [min(s, m) for s, m in zip(sides, sizes, strict=True)]
    count = covering(sides, sizes) if count is None else count
    plan = checkpointed(draw_plan(arr, sizes, how, count, list(sides)), "plan")
    return train.fit(sampling.blocks(arr, plan, sides, shards), sizes, p, shards, **options)


def _history(spark: SparkSession, models: dict[str, train.Model]) -> DataFrame:
    rows = [(name, h["round"], h["bound"], h["delta_norm"], h["rows_touched"], h["subarrays"], h["coverage"], h["seconds"]) for name, m in models.items() for h in m.history]
    return spark.createDataFrame(rows, HISTORY)


def _triples(spark: SparkSession, sf: str, top: int = w.TOP) -> tuple[DataFrame, list[int]]:
    arr = checkpointed(w.encoded_triples(spark, sf, top=top), "triples")
    return arr, w.sizes_of(arr)


for _how in ("uniform", "weighted", "grid"):

    @query(f"train_{_how}")
    def train_query(spark: SparkSession, sf: str, how: str = _how) -> DataFrame:
        arr, sizes = _triples(spark, sf)
        return _history(spark, {how: fitted(arr, sizes, how, small_params(), count=None, sides=(20, 20, 20), shards=SHARDS)})


@query("train_lbfgs")
def train_lbfgs(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    return _history(spark, {o: fitted(arr, sizes, "uniform", small_params(optimizer=o, rounds=2), count=None, shards=SHARDS) for o in ("sgd", "lbfgs")})


def _trade(spark: SparkSession, sf: str, value: str) -> tuple[DataFrame, list[int]]:
    modes = ["nation", "brand", "month"]
    arr = arrays.build_array(w.trade_records(spark, sf), modes, value, "l_extendedprice" if value == "sum" else None)
    if value == "sum":
        arr = arr.withColumn("y", F.log1p("y") / 10)
    arr = checkpointed(arrays.encode(arr, arrays.mode_dictionary(arr, modes), modes), "trade")
    return arr, w.sizes_of(arr)


@query("train_gaussian")
def train_gaussian(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _trade(spark, sf, "sum")
    return _history(spark, {"continuous": fitted(arr, sizes, "uniform", small_params(likelihood="continuous", rounds=2), count=None)})


@query("train_count")
def train_count(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _trade(spark, sf, "count")
    return _history(spark, {"count": fitted(arr, sizes, "uniform", small_params(likelihood="count", rounds=2), count=None)})


@query("bound_history")
def bound_history(spark: SparkSession, sf: str) -> DataFrame:
    """The planted array under each schedule and merge."""
    arr = checkpointed(w.planted(spark, 18), "planted")
    models = {f"{s}-{m}": fitted(arr, [18, 18, 18], "grid", small_params(schedule=s, merge=m, rounds=3, laplace_scale=0.01), sides=(9, 9, 9)) for s, m in (("all", "mean"), ("all", "touched"), ("slice", "mean"), ("all", "laplace"))}
    return _history(spark, models)


def _held(arr: DataFrame, sizes: list[int], seed: int = 4, zero_share: float = 0.02, fold: int = 0) -> tuple[DataFrame, DataFrame]:
    """One fold of five held out, with a share of the zeros."""
    folds = protocol.kfold(arr, 5, seed)
    test = folds.filter(F.col("fold") == fold).drop("fold").unionByName(protocol.zeros_by_share(arr, sizes, zero_share, seed))
    return checkpointed(folds.filter(F.col("fold") != fold).drop("fold"), "train"), checkpointed(test, "test")


@query("predict_bagged")
def predict_bagged(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    known, test = _held(arr, sizes)
    model = fitted(known, sizes, "weighted", small_params(), count=None, sides=(20, 20, 20), shards=SHARDS)
    bags = checkpointed(draw_plan(known, sizes, "uniform", 4, [20, 20, 20], seed=77), "bags")
    return predict.predict(model, known, test, bags, [min(20, m) for m in sizes])


@query("predict_containing")
def predict_containing(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    known, test = _held(arr, sizes)
    model = fitted(known, sizes, "weighted", small_params(rounds=2), count=None, shards=SHARDS)
    sides = [min(10, m) for m in sizes]
    bags = checkpointed(draw_plan(known, sizes, "uniform", 2, sides, seed=77), "bags")
    return predict.predict_containing(model, known, test, bags, sides)


def compared(spark: SparkSession, name: str, arr: DataFrame, sizes: list[int], sides: list[int], rank: int = 3, rounds: int = 5, count: int | None = 40, bags: int = 6, multilinear: bool = True, kernel: Kernel | None = None, fold: int = 0, zero_share: float = 0.02) -> list[tuple]:
    """(workload, method, auc, seconds) of every method on one held-out fold."""
    known, test = _held(arr, sizes, zero_share=zero_share, fold=fold)
    sides = [min(s, m) for s, m in zip(sides, sizes, strict=True)]
    kernel = kernel or Kernel("rbf", scale=1.0)
    modes = len(sizes)
    out = []

    def note(method: str, began: float, scored: DataFrame) -> None:
        took = time.time() - began
        value = measures.auc(scored).first()
        out.append((name, method, float(value.auc) if value and value.auc is not None else None, took))

    for how in ("uniform", "weighted", "grid"):
        began = time.time()
        p = train.TrainParams(ranks=(rank,) * modes, rounds=rounds, rate=0.1, kernel=kernel, sweeps=8)
        model = fitted(known, sizes, how, p, count=count, sides=tuple(sides), shards=SHARDS if count is None else 3)
        plan = checkpointed(draw_plan(known, sizes, "uniform", bags, sides, seed=77), "bags")
        note(f"local-gp-{how}", began, checkpointed(predict.predict(model, known, test, plan, sides).withColumnRenamed("mean", "score"), "scored"))
    cells = test.withColumnRenamed("y", "label")
    label = lambda df: checkpointed(df.join(test, [f"i{k}" for k in range(1, modes + 1)]).withColumnRenamed("value", "score"), "scored")
    at = cells.drop("label")
    began = time.time()
    note("sparse-cp", began, label(arrays.cp_cells(at, baselines.sparse_cp(known, sizes, rank, 4), rank)))
    if multilinear:
        began = time.time()
        note("cp", began, label(arrays.cp_cells(at, baselines.cp_als(known, sizes, rank, 4), rank)))
        began = time.time()
        note("cp-nonneg", began, label(arrays.cp_cells(at, baselines.cp_nonneg(known, sizes, rank, 5), rank)))
        began = time.time()
        factors, core = baselines.hosvd(known, sizes, [min(rank, m) for m in sizes])
        note("hosvd", began, label(arrays.tucker_cells(at, core, factors)))
        began = time.time()
        factors, core = baselines.tucker_als(known, sizes, [min(rank, m) for m in sizes], 2)
        note("tucker", began, label(arrays.tucker_cells(at, core, factors)))
    if np.prod(sizes) <= 100_000:
        began = time.time()
        _, post, _ = baselines.global_gp(known, sizes, [rank] * modes, kernel, 15, rate=0.1)
        rows = [(*[int(v) for v in r[:-1]], float(r[-1]), float(post.mean[tuple(int(v) - 1 for v in r[:-1])])) for r in test.collect()]
        note("global-gp", began, spark.createDataFrame(rows, ", ".join(f"i{k} long" for k in range(1, modes + 1)) + ", y double, score double"))
    began = time.time()
    note("degree", began, baselines.degree_score(test, arrays.slice_weights(known)))
    return out


AUCS = "workload string, method string, auc double, seconds double"


@query("aucs_by_method")
def aucs_by_method(spark: SparkSession, sf: str) -> DataFrame:
    """Every method on the planted array: which one wins where the truth is not multilinear."""
    arr = checkpointed(w.planted(spark, 18), "planted")
    return spark.createDataFrame(compared(spark, "planted", arr, [18, 18, 18], [12, 12, 12]), AUCS)


@query("aucs_linear_twin")
def aucs_linear_twin(spark: SparkSession, sf: str) -> DataFrame:
    arr = checkpointed(w.planted(spark, 18, linear=True), "planted")
    return spark.createDataFrame(compared(spark, "linear", arr, [18, 18, 18], [12, 12, 12], count=24, rounds=3), AUCS)


ON_SETS = "workload string, method string, rank int, auc double, sd_auc double, sets long, train_s double, bound double"


def compared_on_sets(spark: SparkSession, name: str, arr: DataFrame, sizes: list[int], rank: int, ones: int, zeros: int, sets: int = 50, side: int = 50, rounds: int = 5, bags: int = 10) -> list[tuple]:
    """The large-data comparison: four fifths of the nonzeros train, test sets come from the rest and the zeros.

    Every method goes ``rounds`` times over as many cells as the array has (subarrays to coverage 1,
    or sweeps over all nonzeros). Binary cells have the base rate's probit as their mean, and a row's
    step is divided by the root of its squared gradients; both are the same for every sampling.
    """
    from statistics import NormalDist

    known, tests = (checkpointed(df, "split") for df in protocol.holdout_sets(arr, sizes, 0.8, sets, ones, zeros, 4))
    sides, modes = [min(side, m) for m in sizes], len(sizes)
    at = [f"i{k}" for k in range(1, modes + 1)]
    cells = checkpointed(tests.select(*at).distinct(), "cells")
    base = NormalDist().inv_cdf(known.count() / math.prod(sizes))
    p = train.TrainParams(ranks=(rank,) * modes, rounds=rounds, rate=0.3, decay_rate="rows", kernel=Kernel("matern32", scale=1.5), sweeps=8, offset=base, init_scale=0.3)
    out = []

    def note(method: str, took: float, scored: DataFrame, bound: float | None = None) -> None:
        value = measures.summarize(measures.auc(tests.join(scored.select(*at, "score"), at), ["set_id"])).first()
        out.append((name, method, rank, value.mean_auc, value.sd_auc, value.runs, took, bound))

    for how in ("uniform", "weighted", "grid"):
        began = time.time()
        model = fitted(known, sizes, how, p, count=None, sides=tuple(sides), shards=8)
        took = time.time() - began
        plan = checkpointed(draw_plan(known, sizes, "uniform", bags, sides, seed=77), "bags")
        note(f"local-gp-{how}", took, checkpointed(predict.predict(model, known, cells, plan, sides).withColumnRenamed("mean", "score"), "scored"), model.history[-1]["bound"])
    began = time.time()
    factors = baselines.sparse_cp(known, sizes, rank, rounds)
    note("sparse-cp", time.time() - began, checkpointed(arrays.cp_cells(cells, factors, rank).withColumnRenamed("value", "score"), "scored"))
    note("degree", 0.0, checkpointed(baselines.degree_score(cells, arrays.slice_weights(known)), "scored"))
    return out


@query("aucs_triples")
def aucs_triples(spark: SparkSession, sf: str) -> DataFrame:
    """The text triples: the method's three samplings against the sparse distributed baseline on 50 test sets."""
    arr, sizes = _triples(spark, sf)
    return spark.createDataFrame(compared_on_sets(spark, "triples", arr, sizes, 5, 200, 2000), ON_SETS)


@query("aucs_log")
def aucs_log(spark: SparkSession, sf: str) -> DataFrame:
    """The access log likewise, with ten factors; its table is uniform random, so 0.5 is the right answer."""
    arr = w.stored_log(spark, sf)
    return spark.createDataFrame(compared_on_sets(spark, "log", arr, w.sizes_of(arr), 10, 200, 2000), ON_SETS)


@query("machine_scaling")
def machine_scaling(spark: SparkSession, sf: str) -> DataFrame:
    """Measured seconds of one pass over the same subarrays of the largest array, dealt to 1, 2 and 4 shards at once."""
    modes = ["o_custkey", "l_partkey", "l_suppkey"]
    arr = arrays.build_array(w.order_lines(spark, sf), modes)
    arr = checkpointed(arrays.encode(arr, arrays.mode_dictionary(arr, modes), modes), "giant")
    sizes = w.sizes_of(arr)
    sides = [min(50, m) for m in sizes]
    p = small_params(ranks=(5, 5, 5), rounds=1, kernel=Kernel("matern32", scale=1.5))
    plan = checkpointed(draw_plan(arr, sizes, "uniform", 48, sides), "plan")
    start = checkpointed(train.initial_factors(spark, sizes, p), "factors")
    times = []
    for n in (1, 2, 4):
        cut = checkpointed(sampling.blocks(arr, plan, sides, n), "blocks")
        began = time.time()
        checkpointed(train.shard_deltas(cut, start, p, 1, sizes, n), "deltas")
        times.append((n, time.time() - began))
    return measures.scaling_curve(spark.createDataFrame(times, "machines int, seconds double"), 1)


def _fit_rows(spark: SparkSession, factors: DataFrame) -> DataFrame:
    return factors.groupBy("mode").agg(F.count("*").alias("rows"), F.round(F.sum(F.aggregate("vec", F.lit(0.0), lambda a, v: a + v * v)), 4).alias("norm2")).orderBy("mode")


@query("cp_sweep")
def cp_sweep(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    return _fit_rows(spark, baselines.cp_als(arr, sizes, 3, 1))


@query("cp_nonneg_sweep")
def cp_nonneg_sweep(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    return _fit_rows(spark, baselines.cp_nonneg(arr, sizes, 3, 1))


@query("hosvd")
def hosvd(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    return _fit_rows(spark, baselines.hosvd(arr, sizes, [3, 3, 3])[0])


@query("tucker_sweep")
def tucker_sweep(spark: SparkSession, sf: str) -> DataFrame:
    arr, sizes = _triples(spark, sf)
    return _fit_rows(spark, baselines.tucker_als(arr, sizes, [3, 3, 3], 1)[0])


@query("global_gp_small")
def global_gp_small(spark: SparkSession, sf: str) -> DataFrame:
    arr = checkpointed(w.planted(spark, 12), "planted")
    rows, post, _ = baselines.global_gp(arr, [12, 12, 12], [3, 3, 3], Kernel(), 5, laplace=0.01)
    return spark.createDataFrame([(k + 1, len(u), float(np.abs(u).sum()), post.bound[-1]) for k, u in enumerate(rows)], "mode int, rows int, l1 double, bound double")


@query("sgd_cp")
def sgd_cp(spark: SparkSession, sf: str) -> DataFrame:
    """The hierarchical shards with a multilinear local model."""
    arr = checkpointed(w.planted(spark, 12, linear=True), "planted")
    plan = draw_plan(arr, [12, 12, 12], "grid", 0, [6, 6, 6])
    return _fit_rows(spark, baselines.sgd_cp(sampling.blocks(arr, plan, [6, 6, 6], 2), baselines.random_factors(spark, [12, 12, 12], 2, 11), 2, 0.02, 2, 2))


@query("tradeoff")
def tradeoff(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds by part and AUC against subarray size, with the trained cells equal."""
    arr, sizes = _triples(spark, sf)
    known, test = _held(arr, sizes, zero_share=0.002)
    p = small_params(rounds=2, rate=0.3, decay_rate="rows", kernel=Kernel("matern32", scale=1.5), offset=-2.5, init_scale=0.3)
    bags = checkpointed(draw_plan(known, sizes, "uniform", 4, [50, 50, 50], seed=77), "bags")
    rows = []
    for side in (20, 40, 60, 80):
        count = cost.same_work([side] * 3, math.prod(sizes))
        sides = [min(side, m) for m in sizes]
        began = time.time()
        plan = checkpointed(draw_plan(known, sizes, "uniform", count, sides), "plan")
        cut = checkpointed(sampling.blocks(known, plan, sides, 8), "blocks")
        taken = time.time()
        model = train.fit(cut, sizes, p, 8)
        scored = predict.predict(model, known, test, bags, [min(50, m) for m in sizes])
        rows.append((side, count, taken - began, sum(h["pass_s"] for h in model.history), sum(h["merge_s"] for h in model.history), float(measures.auc(scored, score="mean").first().auc)))
    return spark.createDataFrame(rows, "side int, subarrays long, extract_s double, train_s double, merge_s double, auc double")


@query("giant_round")
def giant_round(spark: SparkSession, sf: str) -> DataFrame:
    """One round on the largest array (customer, part, supplier) with a budget of subarrays."""
    modes = ["o_custkey", "l_partkey", "l_suppkey"]
    arr = arrays.build_array(w.order_lines(spark, sf), modes)
    arr = checkpointed(arrays.encode(arr, arrays.mode_dictionary(arr, modes), modes), "giant")
    sizes = w.sizes_of(arr)
    p = small_params(ranks=(5, 5, 5), rounds=1, kernel=Kernel("matern32", scale=1.5))
    return _history(spark, {"giant": fitted(arr, sizes, "weighted", p, count=48, sides=(25, 25, 25), shards=8)})


@query("tune")
def tune(spark: SparkSession, sf: str) -> DataFrame:
    """Kernels and rates by held-out bound on a planted array: the whole grid is one Spark job."""
    import pandas as pd

    from .functions import gp

    cells = w.planted(spark, 10).toPandas()
    y = np.zeros((10, 10, 10))
    for r in cells.itertuples(index=False):
        y[r.i1 - 1, r.i2 - 1, r.i3 - 1] = r.y
    sent = spark.sparkContext.broadcast(y)
    grid = spark.createDataFrame([(k, rate, fold) for k in ("rbf", "linear", "poly", "matern32", "matern52") for rate in (0.0005, 0.001, 0.002, 0.005, 0.01) for fold in range(2)], "kernel string, rate double, fold int")

    def score(pdf: pd.DataFrame) -> pd.DataFrame:
        kind, rate, fold = pdf["kernel"][0], pdf["rate"][0], int(pdf["fold"][0])
        block, kernel = sent.value, Kernel(kind, gamma=0.3)
        mask = np.random.default_rng(fold).random(block.shape) > 0.2
        rows = [0.5 * np.random.default_rng(k).normal(size=(10, 3)) for k in range(3)]
        for _ in range(10):
            post, spec = gp.infer(rows, block, kernel, mask=mask)
            rows = [u + rate * g for u, g in zip(rows, gp.factor_gradients(rows, post, spec, kernel), strict=True)]
        from .functions.normal import log_cdf

        post, spec = gp.infer(rows, block, kernel, mask=mask)
        held = log_cdf((2 * block - 1) * post.mean / np.sqrt(1 + spec.variance()))[~mask].mean()
        return pd.DataFrame([(kind, rate, fold, float(held))], columns=["kernel", "rate", "fold", "score"])

    scored = grid.groupBy("kernel", "rate", "fold").applyInPandas(score, "kernel string, rate double, fold int, score double")
    return scored.groupBy("kernel", "rate").agg(F.avg("score").alias("score"), F.count("*").alias("folds"))


@query("st_online_fit")
def st_online_fit(spark: SparkSession, sf: str) -> DataFrame:
    """A model that follows a stream of weeks: one grid over each batch's cells, all of them, refits the factors from the last ones."""
    dictionary = checkpointed(arrays.mode_dictionary(w.log_array(spark, sf), w.LOG), "dictionary")
    sizes = [int(r.n) for r in dictionary.groupBy("mode").agg(F.max("idx").alias("n")).orderBy("mode").collect()]
    seen: dict = {"factors": None, "rows": []}

    def update(arr: DataFrame, batch: int) -> None:
        cells = checkpointed(arrays.encode(arr, dictionary, w.LOG), "batch")
        sides = [min(a, b) for a, b in zip((50, 5, 50), sizes, strict=True)]
        plan = checkpointed(draw_plan(cells, sizes, "grid", 0, sides, seed=batch), "plan")
        model = train.fit(sampling.blocks(cells, plan, sides, 4), sizes, small_params(rounds=1), 4, init=seen["factors"])
        seen["factors"] = model.factors
        seen["rows"].append((batch, cells.count(), model.history[0]["bound"], model.history[0]["rows_touched"], model.history[0]["coverage"]))

    stream = st.event_stream_by_week(spark, sf).select("user_id", "event_type", F.get_json_object("props", "$.k").alias("k"))
    st.fit_stream(stream, list(w.LOG), update)
    return spark.createDataFrame(seen["rows"], "batch int, nonzeros long, bound double, rows_touched long, coverage double")


@query("train_4way")
def train_4way(spark: SparkSession, sf: str) -> DataFrame:
    """Four modes: nations, brands, types, nations."""
    modes = ["c_nationkey", "p_brand", "p_type", "s_nationkey"]
    arr = arrays.build_array(w.nation_records(spark, sf), modes)
    arr = checkpointed(arrays.encode(arr, arrays.mode_dictionary(arr, modes), modes), "trade4")
    return _history(spark, {"4way": fitted(arr, w.sizes_of(arr), "weighted", small_params(ranks=(3, 3, 3, 3), rounds=2), count=None, sides=(6, 6, 6, 6), shards=SHARDS)})


@query("repeated_runs")
def repeated_runs(spark: SparkSession, sf: str) -> DataFrame:
    """Mean and spread of the AUC over splits that differ in their seed."""
    arr = checkpointed(w.planted(spark, 12), "planted")
    rows = []
    for seed in (1, 2, 3):
        known, test = _held(arr, [12, 12, 12], seed, 0.05)
        model = fitted(known, [12, 12, 12], "uniform", small_params(rounds=2, rate=0.1, seed=seed), count=16, sides=(8, 8, 8))
        bags = checkpointed(draw_plan(known, [12, 12, 12], "uniform", 4, [8, 8, 8], seed=77), "bags")
        rows.append((seed, float(measures.auc(predict.predict(model, known, test, bags, [8, 8, 8]), score="mean").first().auc)))
    return measures.summarize(spark.createDataFrame(rows, "seed int, auc double"))


@query("st_score")
def st_score(spark: SparkSession, sf: str) -> DataFrame:
    """A stream of new cells scored with a fixed model; the same plan as in batch."""
    arr = checkpointed(w.planted(spark, 12), "planted")
    model = fitted(arr, [12, 12, 12], "grid", small_params(rounds=1), count=8, sides=(6, 6, 6))
    bags = checkpointed(draw_plan(arr, [12, 12, 12], "uniform", 2, [6, 6, 6], seed=77), "bags")
    cells = spark.readStream.schema(arr.schema).parquet(arr.inputFiles()[0].rsplit("/", 1)[0])
    return st.replayed(predict.predict(model, arr, cells, bags, [6, 6, 6]))


@query("explore_nonzero_boxes")
def explore_nonzero_boxes(spark: SparkSession, sf: str) -> DataFrame:
    """The rejected strategy: boxes around sampled nonzeros; their sizes differ, which is why it is not used."""
    arr, _ = _triples(spark, sf)
    from pyspark.sql import Window

    from .functions.hashing import keyed, uniform

    draw = uniform(keyed(9, F.col("box"), F.col("i1"), F.col("i2"), F.col("i3")))
    picked = arr.join(F.broadcast(spark.range(8).toDF("box")), F.lit(True)).withColumn("n", F.row_number().over(Window.partitionBy("box").orderBy(draw))).filter("n <= 12")
    return picked.groupBy("box").agg(F.count_distinct("i1").alias("m1"), F.count_distinct("i2").alias("m2"), F.count_distinct("i3").alias("m3"))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Triples, weighted subarrays, training, bagged prediction: scored held-out cells."""
    return predict_bagged(spark, sf)
