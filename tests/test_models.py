"""Training, prediction and baselines: reductions, invariants, statistics and the reported orderings."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from arrayfactor import queries_models as q
from arrayfactor import workloads as w
from arrayfactor.functions.kernels import Kernel
from arrayfactor.operators import arrays, baselines, measures, predict, sampling, train
from arrayfactor.sources.tables import checkpointed


@pytest.fixture(scope="module")
def cube(spark):
    return checkpointed(w.planted(spark, 12), "planted")


@pytest.fixture(scope="module")
def cut(spark, cube):
    plan = checkpointed(q.draw_plan(cube, [12, 12, 12], "grid", 0, [6, 6, 6]), "plan")
    return checkpointed(sampling.blocks(cube, plan, [6, 6, 6], 3), "blocks")


def dense(factors):
    return {(r.mode, r.idx): np.array(r.vec) for r in factors.collect()}


def test_grid_covers_every_cell_once(cube):
    plan = q.draw_plan(cube, [12, 12, 12], "grid", 0, [5, 5, 5])
    cells = plan.groupBy("sub_id").pivot("mode", [1, 2, 3]).count().select((F.col("1") * F.col("2") * F.col("3")).alias("n")).agg(F.sum("n")).first()[0]
    assert cells == 12**3
    assert sampling.extract(cube, plan, [5, 5, 5]).count() == cube.count()


def test_uniform_and_weighted_draws(spark):
    plan = sampling.sample_uniform(spark, [40, 30, 20], 200, [10, 10, 10], 3)
    counts = plan.groupBy("mode", "idx").count().collect()
    assert plan.groupBy("sub_id", "mode").agg(F.count_distinct("idx").alias("n")).filter("n <> 10").count() == 0
    ones = [r["count"] for r in counts if r.mode == 1]
    assert abs(np.mean(ones) - 50) < 1 and max(ones) < 90
    slices = spark.createDataFrame([(1, i, 1 + 9 * (i <= 5)) for i in range(1, 31)], "mode int, idx long, weight long")
    for drawn in (sampling.sample_weighted(slices, 300, [3], 3), sampling.sample_by_hash(slices, 300, [3], 3, weighted=True)):
        heavy = drawn.filter("idx <= 5").count() / drawn.count()
        assert 0.5 < heavy < 0.75  # ten times the weight of the others, without replacement


def test_weighted_subarrays_have_no_empty_ones(spark):
    arr = spark.createDataFrame([(i, j, 1, 1.0) for i in range(1, 5) for j in range(1, 5)] + [(60, 60, 1, 1.0)], "i1 long, i2 long, i3 long, y double")
    slices = arrays.slice_weights(arr)
    sides = [4, 4, 1]
    n = lambda plan: [r.nnz for r in sampling.coverage(arr, plan, sides).collect()]
    weighted, uniform = n(sampling.sample_weighted(slices, 40, sides, 1)), n(sampling.sample_uniform(spark, [60, 60, 1], 40, sides, 1))
    assert min(weighted) > 0 and sum(x == 0 for x in uniform) > 5


def test_empty_subarrays_are_there(spark):
    arr = spark.createDataFrame([(1, 1, 1, 1.0)], "i1 long, i2 long, i3 long, y double")
    plan = q.draw_plan(arr, [4, 4, 4], "grid", 0, [2, 2, 2])
    assert sampling.blocks(arr, plan, [2, 2, 2], 2).count() == 8


def test_merge_of_deltas_is_the_dense_mean(spark, cut):
    p = q.small_params(ranks=(2, 2, 2), rounds=1)
    start = checkpointed(train.initial_factors(spark, [12, 12, 12], p), "start")
    deltas = checkpointed(train.shard_deltas(cut, start, p, 1, [12, 12, 12], 3), "deltas")
    base = dense(start)
    copies = [dict(base) for _ in range(3)]
    for r in deltas.collect():
        copies[r.shard][r.mode, r.idx] = base[r.mode, r.idx] + np.array(r.delta)
    for key, v in dense(train.merge_factors(start, deltas, 3)).items():
        assert np.allclose(v, np.mean([c[key] for c in copies], axis=0))


def test_same_model_for_any_partitioning_and_shipping(spark, cut):
    p = q.small_params(ranks=(2, 2, 2), rounds=2)
    a = train.fit(cut, [12, 12, 12], p, 3)
    b = train.fit(cut.repartition(7), [12, 12, 12], p, 3, ship="join")
    assert train.digest(a) == train.digest(b)
    assert [h["subarrays"] for h in a.history] == [8, 8]


def test_variance_limits(spark, cut):
    frozen = train.fit(cut, [12, 12, 12], q.small_params(ranks=(2, 2, 2), rounds=1, variance=1e-12, rate=1e-12), 3)
    start = dense(train.initial_factors(spark, [12, 12, 12], frozen.params))
    assert all(np.allclose(v, start[k], atol=1e-6) for k, v in dense(frozen.factors).items())


def test_training_raises_the_bound(cut):
    for optimizer in ("sgd", "lbfgs"):
        history = train.fit(cut, [12, 12, 12], q.small_params(rounds=5, rate=0.1, merge="touched", optimizer=optimizer), 3).history
        assert history[-1]["bound"] > history[0]["bound"]


def test_one_shard_one_block_is_the_global_model(spark, cube):
    plan = q.draw_plan(cube, [12, 12, 12], "grid", 0, [12, 12, 12])
    p = q.small_params(ranks=(2, 2, 2), rounds=1, variance=float("inf"))
    model = train.fit(sampling.blocks(cube, plan, [12, 12, 12], 1), [12, 12, 12], p, 1)
    from arrayfactor.functions import gp

    start = dense(train.initial_factors(spark, [12, 12, 12], p))
    rows = [np.array([start[k, i] for i in range(1, 13)]) for k in (1, 2, 3)]
    y = np.zeros((12, 12, 12))
    for r in cube.collect():
        y[r.i1 - 1, r.i2 - 1, r.i3 - 1] = r.y
    post, spec = gp.infer(rows, y, p.kernel, sweeps=p.sweeps)
    got = dense(model.factors)
    for k, (u, g) in enumerate(zip(rows, gp.factor_gradients(rows, post, spec, p.kernel)), 1):
        g = g * np.minimum(1, 5 / np.maximum(np.linalg.norm(g, axis=1, keepdims=True), 1e-12))
        assert np.allclose(u + p.rate * g, [got[k, i] for i in range(1, 13)])


def test_bagging_lowers_the_spread(spark, cube):
    model = q.fitted(cube, [12, 12, 12], "grid", q.small_params(rounds=2), sides=(6, 6, 6))
    cells = cube.limit(40)
    one = lambda seed, n: {(r.i1, r.i2, r.i3): r.mean for r in predict.predict(model, cube, checkpointed(cells, "cells"), checkpointed(q.draw_plan(cube, [12] * 3, "uniform", n, [6] * 3, seed), "bags"), [6] * 3).collect()}
    a, b, c, d = one(1, 1), one(2, 1), one(3, 8), one(4, 8)
    gap = lambda x, y: np.mean([(x[k] - y[k]) ** 2 for k in x])
    assert gap(c, d) < gap(a, b)


def test_containing_prediction_is_the_enlarged_bag(spark, cube):
    """A cell's indices join every bag, the cell itself is unseen, and its posterior means are averaged."""
    from arrayfactor.functions import gp

    model = q.fitted(cube, [12] * 3, "grid", q.small_params(rounds=1), sides=(6, 6, 6))
    cells = checkpointed(cube.orderBy("i1", "i2", "i3").limit(3).unionByName(spark.createDataFrame([(12, 12, 12, 0.0)], cube.schema)), "cells")
    plan = checkpointed(q.draw_plan(cube, [12] * 3, "uniform", 2, [4] * 3, 77), "bags")
    got = {(r.i1, r.i2, r.i3): r for r in predict.predict_containing(model, cube, cells, plan, [4] * 3, batch=1).collect()}
    drawn, vecs, p = {}, dense(model.factors), model.params
    for r in plan.collect():
        drawn.setdefault(r.sub_id, {}).setdefault(r.mode, set()).add(r.idx)
    full = np.zeros((12, 12, 12))
    for r in cube.collect():
        full[r.i1 - 1, r.i2 - 1, r.i3 - 1] = r.y
    assert len(got) == 4
    for r in cells.collect():
        at, means = (r.i1, r.i2, r.i3), []
        for own in drawn.values():
            sets = [sorted(own[k] | {i}) for k, i in enumerate(at, 1)]
            y = full[np.ix_(*[np.array(s) - 1 for s in sets])]
            here, mask = tuple(s.index(i) for s, i in zip(sets, at, strict=True)), np.ones(y.shape, bool)
            mask[here] = False
            post, _ = gp.infer([np.array([vecs[k, i] for i in s]) for k, s in enumerate(sets, 1)], y, p.kernel, p.likelihood, sweeps=p.sweeps, mask=mask, offset=p.offset)
            means.append(post.mean[here])
        assert got[at].votes == 2 and got[at].mean == pytest.approx(np.mean(means)) and got[at].y == r.y


def test_sparse_and_plain_products_agree_step_for_step(spark, cube):
    ones = cube.filter("y > 0")
    a, b = dense(baselines.cp_als(ones, [12] * 3, 2, 2)), dense(baselines.sparse_cp(ones, [12] * 3, 2, 2))
    assert all(np.allclose(a[k], b[k]) for k in a)
    assert all((v >= 0).all() for v in dense(baselines.cp_nonneg(ones, [12] * 3, 2, 2)).values())


def test_full_rank_tucker_reproduces_the_array(spark):
    arr = spark.createDataFrame([(i, j, k, float(i + 2 * j + 3 * k)) for i in range(1, 4) for j in range(1, 4) for k in range(1, 3)], "i1 long, i2 long, i3 long, y double")
    arr = checkpointed(arr, "arr")
    for factors, core in (baselines.hosvd(arr, [3, 3, 2], [3, 3, 2]), baselines.tucker_als(arr, [3, 3, 2], [3, 3, 2], 2)):
        got = {(r.i1, r.i2, r.i3): r.value for r in arrays.tucker_cells(arr.select("i1", "i2", "i3"), core, factors).collect()}
        assert all(abs(v - (i + 2 * j + 3 * k)) < 1e-3 for (i, j, k), v in got.items())


def shuffled_records(spark):
    """Records that all stages so far have shuffled."""
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return sum(stages.apply(n).shuffleWriteRecords() for n in range(stages.size()))


def test_row_products_shuffle_lists_not_pairs(spark):
    n = 1_500  # rows that share one column: 2,250,000 pairs
    arr = checkpointed(spark.range(1, n + 1).select(F.col("id").alias("i1"), F.lit(1).cast("long").alias("i2"), F.lit(1).cast("long").alias("i3"), F.lit(2.0).alias("y")), "arr")
    products, before = baselines.gram(arr, 1), shuffled_records(spark)
    products.write.format("noop").mode("overwrite").save()
    assert shuffled_records(spark) - before < 10 * n
    got = products.agg(F.count("*"), F.count_distinct("a", "b"), F.min("g"), F.max("g"), F.max("a"), F.max("b")).first()
    assert tuple(got) == (n * n, n * n, 4.0, 4.0, n, n)


def test_row_products_equal_the_join(spark):
    rng = np.random.default_rng(5)
    # three blocks of rows, short and long lists, values that cancel, cells that repeat, missing values and columns
    cells = [(int(rng.integers(1, 2_600)), int(rng.integers(1, 4)), int(rng.integers(1, 40)), float(rng.integers(-2, 3))) for _ in range(2_000)]
    cells += [(i, 7, 7, float(rng.integers(-1, 2))) for i in range(1, 1_200, 3)] + [(i, 8, 8, -1.0) for i in range(1, 1_200, 3)]
    cells += [(i, 9, 9, None if i % 2 else 3.0) for i in range(2_000, 2_050)] + [(5, 9, 9, None), (5, 9, 10, None), (6, None, 1, 1.0), (7, None, 1, 1.0)]
    arr = checkpointed(spark.createDataFrame(cells, "i1 long, i2 long, i3 long, y double"), "arr")
    for k, others in ((1, ["i2", "i3"]), (2, ["i1", "i3"])):
        left, right = (arr.select(*others, F.col(f"i{k}").alias(s), F.col("y").alias(f"y{s}")) for s in "ab")
        want = left.join(right, others).filter("a is not null and b is not null").groupBy("a", "b").agg(F.sum(F.col("ya") * F.col("yb")).alias("g"))
        got = [sorted(map(repr, map(tuple, df.select("a", "b", F.col("g") + F.lit(0.0)).collect()))) for df in (baselines.gram(arr, k), want)]
        assert got[0] == got[1]


def test_auc_with_ties(spark):
    df = spark.createDataFrame([(1.0, 0.9), (1.0, 0.5), (0.0, 0.5), (0.0, 0.1)], "y double, score double")
    assert measures.auc(df).first().auc == 0.875
    assert measures.auc_binned(df).first().auc == 0.875


def test_nonlinear_truth_favours_the_processes(spark):
    """On a truth that is not multilinear the local processes beat every multilinear baseline."""
    rows = {r.method: r.auc for r in q.aucs_by_method(spark, "").collect()}
    best = max(rows[m] for m in ("local-gp-uniform", "local-gp-weighted", "local-gp-grid"))
    assert best > max(rows[m] for m in ("cp", "cp-nonneg", "sparse-cp", "hosvd", "tucker", "degree"))


def test_position_overflow_is_decimal(spark):
    arr = spark.createDataFrame([(2, 3, 4, 1.0)], "i1 long, i2 long, i3 long, y double")
    out = arrays.linear_index(arr, [10**8, 10**8, 10**8])
    assert out.schema["pos"].dataType.simpleString() == "decimal(38,0)"
    assert int(out.first().pos) == (10**16 + 2 * 10**8 + 4)
    assert arrays.linear_index(spark.createDataFrame([(2, 3, 1, 1.0)], "i1 long, i2 long, i3 long, y double"), [4, 5, 3]).first().pos == 22


def test_kernel_choice_runs(cut):
    for kind in ("linear", "poly", "matern52"):
        assert train.fit(cut, [12, 12, 12], q.small_params(rounds=1, kernel=Kernel(kind, gamma=0.3)), 3).history[0]["bound"] < 0


@pytest.mark.parametrize("key", ["train_uniform", "train_weighted", "train_grid", "train_lbfgs", "predict_bagged", "predict_containing", "aucs_triples", "cp_sweep", "cp_nonneg_sweep", "hosvd", "tucker_sweep", "tradeoff", "explore_nonzero_boxes"])
def test_triple_queries_take_the_whole_workload(spark, monkeypatch, key):
    class Reached(Exception):
        pass

    def encoded(spark, sf, top=200, least=1):
        raise Reached(top, least)

    monkeypatch.setattr(w, "encoded_triples", encoded)
    with pytest.raises(Reached) as got:
        q.QUERIES[key](spark, "/root/testdata/sf0.001")
    assert got.value.args == (200, 1)


def test_triples_are_trained_to_coverage_one(spark, monkeypatch):
    counts = []
    monkeypatch.setattr(q, "draw_plan", lambda arr, sizes, how, count, sides, seed=9: counts.append((count, sizes, sides)) or (_ for _ in ()).throw(StopIteration))
    with pytest.raises(StopIteration):
        q.QUERIES["train_weighted"](spark, "/root/testdata/sf0.001")
    count, sizes, sides = counts[0]
    assert count * np.prod(sides) >= np.prod(sizes)


def test_coverage_is_told(spark, cube):
    model = q.fitted(cube, [12] * 3, "uniform", q.small_params(rounds=1), count=None, sides=(5, 5, 5))
    assert 1 <= model.history[0]["coverage"] < 1.1


def test_shards_are_equal_and_alone_in_their_partition(spark, cube):
    plan = checkpointed(sampling.sample_uniform(spark, [12] * 3, 43, [6] * 3, 3), "plan")
    cut = checkpointed(sampling.blocks(cube, plan, [6] * 3, 8), "blocks")
    counts = [r["count"] for r in cut.groupBy("shard").count().collect()]
    assert len(counts) == 8 and max(counts) - min(counts) <= 1
    placed = cut.repartitionById(8, "shard").withColumn("at", F.spark_partition_id()).groupBy("at").agg(F.count_distinct("shard").alias("n")).collect()
    assert len(placed) == 8 and all(r.n == 1 for r in placed)


def test_contraction_in_steps_is_the_einsum():
    from arrayfactor.functions import gp

    rnd = np.random.default_rng(1)
    block, rows = rnd.normal(size=(3, 4, 5, 2)), [rnd.normal(size=(7, m)) for m in (3, 4, 5, 2)]
    assert np.allclose(gp.contracted(block, rows, 3), np.einsum("abcd,na,nb,nc,nd->n", block, *rows))


def test_kernel_diagonal():
    from arrayfactor.functions.kernels import KINDS, covariance, diagonal

    u = np.random.default_rng(2).normal(size=(6, 3))
    for kind in KINDS:
        k = Kernel(kind, scale=0.7, amplitude=1.3, gamma=0.4)
        assert np.allclose(diagonal(u, k), np.diag(covariance(u, u, k)))


def test_log_comparison_finds_no_signal(spark):
    rows = q.aucs_log(spark, "/root/testdata/sf0.001").collect()
    assert {r.method for r in rows} == {"local-gp-uniform", "local-gp-weighted", "local-gp-grid", "sparse-cp", "degree"} and all(r.sets == 50 for r in rows)
    assert all(abs(r.auc - 0.5) < 0.12 for r in rows)


def test_stream_refits_over_several_batches(spark):
    rows = q.st_online_fit(spark, "/root/testdata/sf0.001").collect()
    assert len(rows) >= 4 and all(r.nonzeros > 0 and r.coverage >= 0.99 for r in rows)


@pytest.mark.parametrize("key", ["st_static_encode", "st_dedup_array", "st_tumbling", "st_session", "st_user_state"])
def test_stream_results_stay_out_of_the_driver(spark, key):
    """Rows of a replayed stream lie in files of the scratch folder, not in a memory sink."""
    from arrayfactor import registry
    from arrayfactor.sources.tables import scratch

    got = registry.QUERIES[key](spark, "/root/testdata/sf0.001")
    assert got.inputFiles() and all(scratch(spark).removeprefix("file://") in f for f in got.inputFiles())


def test_replayed_stream_keeps_all_batches_or_the_last(spark, tmp_path):
    from arrayfactor.streaming import events as st

    for n in range(3):
        spark.createDataFrame([(n, i) for i in range(4)], "a long, b long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("a long, b long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    assert sorted(map(tuple, st.replayed(stream).collect())) == [(n, i) for n in range(3) for i in range(4)]
    assert sorted(map(tuple, st.replayed(stream.groupBy("b").count(), "complete").collect())) == [(i, 3) for i in range(4)]
    (tmp_path / "none").mkdir()
    assert st.replayed(spark.readStream.schema("a long, b long").parquet(str(tmp_path / "none"))).collect() == []


def test_parent_rows_of_few_subarrays_are_joined(spark, cube, cut, monkeypatch):
    """48 subarrays of a giant array use few of its rows: the factors stay out of the driver, and the model is the same."""
    assert train.ships([900_000, 1_200_000, 60_000], (5, 5, 5), 48 * 75) == "join"
    assert train.ships([200, 200, 200], (3, 3, 3), 1000 * 60) == "broadcast"
    p = q.small_params(ranks=(2, 2, 2), rounds=1)
    sent = train.digest(train.fit(cut, [12] * 3, p, 3))
    monkeypatch.setattr(train, "ships", lambda *a: "join")
    monkeypatch.setattr(train, "as_arrays", lambda *a: pytest.fail("factors came to the driver"))
    assert train.digest(train.fit(cut, [12] * 3, p, 3)) == sent


def test_packed_rows_are_the_rows(spark):
    from arrayfactor.sources.tables import by_mode

    rows = [(k, i, [float(i), k / 2]) for k in (1, 2) for i in range(9, 0, -1)]
    got = by_mode(spark.createDataFrame(rows, "mode int, idx long, vec array<double>").repartition(3), "vec")
    assert [(k, int(i), v.tolist()) for k in got for i, v in zip(*got[k], strict=True)] == sorted(rows)


@pytest.fixture
def large(spark):
    """Joins as on tables too large to send."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_containing_prediction_shuffles_slices_not_enlarged_bags(spark, large):
    """Nonzeros go to a task once for all its batches, not once for each enlarged bag that a slice of them meets."""
    side = 30
    arr = checkpointed(spark.range(side**3).selectExpr("id div 900 + 1 as i1", "id div 30 % 30 + 1 as i2", "id % 30 + 1 as i3", "1.0D as y"), "arr")
    p = q.small_params()
    model = train.Model(checkpointed(train.initial_factors(spark, [side] * 3, p), "factors"), [], p, (side,) * 3)
    cells = checkpointed(arr.filter("xxhash64(i1, i2, i3) % 67 = 0"), "cells")
    plan = checkpointed(q.draw_plan(arr, [side] * 3, "uniform", 2, [5] * 3, 77), "bags")
    before = shuffled_records(spark)
    got = predict.predict_containing(model, arr, cells, plan, [5] * 3)
    assert got.filter("votes = 2").count() == cells.count() > 300
    assert shuffled_records(spark) - before < 2 * arr.count()


def test_extraction_equals_brute_force_without_shuffling_slices(spark, large):
    rng = np.random.default_rng(4)
    for sides in ([6, 5], [4, 6, 5], [3, 2, 4, 3]):
        shape = [8] * len(sides)
        full = rng.random(shape) * (rng.random(shape) < 0.6)
        names = ", ".join(f"i{k} long" for k in range(1, len(shape) + 1))
        arr = checkpointed(spark.createDataFrame([(*[int(i) + 1 for i in at], float(full[tuple(at)])) for at in np.argwhere(full)], f"{names}, y double"), "arr")
        plan = checkpointed(sampling.sample_uniform(spark, shape, 40, sides, 3), "plan")
        sets, before = {}, shuffled_records(spark)
        for r in plan.orderBy("pos").collect():
            sets.setdefault(r.sub_id, {}).setdefault(r.mode, []).append(r.idx - 1)
        before = shuffled_records(spark)
        got = {(r.sub_id, r.lin): r.y for r in sampling.extract(arr, plan, sides).collect()}
        blocks = {s: full[np.ix_(*[own[k] for k in sorted(own)])].ravel() for s, own in sets.items()}
        assert got == {(s, n): y for s, b in blocks.items() for n, y in enumerate(b) if y}
        assert shuffled_records(spark) - before < 40 * (np.prod(sides) + sum(sides)) + arr.count()


def test_words_are_split_once_and_rare_runs_stay_in_the_tasks(spark):
    texts = ["a b c a b c", None, "", "Été ŒUVRE été\x01b", "averylongword a averylongword averylongwords", "c", "a"] + [f"w{chr(97 + n % 26)}x{chr(97 + n // 26)} rare{chr(97 + n % 26)}" * 30 for n in range(200)]
    docs = checkpointed(spark.createDataFrame([(t,) for t in texts], "text string"), "docs").repartition(3)
    words = docs.select(w.tokens(F.col("text")).alias("w"))
    for n in (6, 10_000):
        frequent = w.frequent_words(docs, n)
        assert sorted(frequent) == sorted(r.t for r in w.top_tokens(words, n).collect())
        place, want = {t: k for k, t in enumerate(frequent, 1)}, {}
        for r in words.collect():
            for run in zip(r.w or [], (r.w or [])[1:], (r.w or [])[2:], strict=False):
                if all(t in place for t in run):
                    key = tuple(place[t] for t in run)
                    want[key] = want.get(key, 0) + 1
        assert {(r.i1, r.i2, r.i3): r.n for r in w.frequent_runs(docs, frequent).collect()} == want and want


def test_tails_are_the_two_functions():
    from arrayfactor.functions.normal import hazard, log_cdf, tails

    for x in (np.linspace(-36.99, 36.99, 50_001), np.array([-60.0, -37.0, 0.0, 37.0, 80.0]), np.zeros((0, 2))):
        logs, ratio = tails(x)
        assert np.allclose(logs, log_cdf(x), rtol=1e-10, atol=1e-300) or np.allclose(logs, log_cdf(x), atol=1e-11)
        assert np.allclose(ratio, hazard(x), rtol=1e-9, atol=1e-11)
