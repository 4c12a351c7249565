"""The solver on Spark: the same numbers as in one process, plans without needless shuffles, edges."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from kernelblocks import measures
from kernelblocks.admm.engine import Model, _round, objective, predict, solve
from kernelblocks.admm.step import Root, SolverConfig, solve_local
from kernelblocks.baselines.linear import average_ensemble, materialized_linear
from kernelblocks.baselines.ridge import exact_ridge, feature_ridge, linear_ridge, local_rows, predict_dual, rkhs_norm
from kernelblocks.baselines.svm import working_set_smo as working
from kernelblocks.baselines.svm import incomplete_cholesky, interior_point_svm, lowrank_svm, smo, smo_svm
from kernelblocks.functions import kernels
from kernelblocks.functions.featuremaps import FourierMap
from kernelblocks.operators.prep import densified, embedding_task, split, text_task
from kernelblocks.plans.blocks import pack, unpack_batch
from kernelblocks.sources.blobs import KernelBlobs

FMAP = FourierMap(2, 64, 4, 1, sigma=1.0)


@pytest.fixture(scope="module")
def xor(spark, sf):
    return embedding_task(spark.read.parquet(f"{sf}/embeddings.parquet"), "xor01").persist()


def blocks_of(packed):
    rows = sorted(packed.collect(), key=lambda r: r["row_block"])
    return [unpack_batch(bytes(r["x"]), r["d"]) for r in rows], [np.frombuffer(bytes(r["y"])).reshape(r["n"], -1) for r in rows]


@pytest.mark.parametrize("options", [{}, {"layout": "explicit"}, {"block_fraction": 0.5}, {"gram_shortcut": True, "threads": 2}, {"tile_rows": 16, "block_fraction": 0.5}])
def test_equals_one_process(spark, xor, options):
    xs, ys = blocks_of(pack(xor, 3))
    n = sum(map(len, ys))
    kw = {k: v for k, v in options.items() if k != "threads"}
    cfg = SolverConfig(FMAP, "hinge", "ridge", 1e-3, 1.0 / n, n, 1, 3, **kw)
    root, _ = solve_local(xs, ys, cfg, 7)
    run = solve(xor, FMAP, "hinge", "ridge", 1e-3, rows=3, iters=7, checkpoint_every=3, **options)
    assert np.abs(run.model.matrix - np.vstack(root.w_bar)).max() < 1e-10


@pytest.mark.parametrize("options", [{}, {"spread_rows": 40}, {"consensus": "join"}, {"spread_rows": 40, "consensus": "join"}])
def test_the_models_step_is_the_same_everywhere(spark, xor, options):
    xs, ys = blocks_of(pack(xor, 2))
    n = sum(map(len, ys))
    root, _ = solve_local(xs, ys, SolverConfig(FMAP, "hinge", "ridge", 1e-3, 1.0 / n, n, 1, 2, weight_pull=n / 10), 3)
    run = solve(xor, FMAP, "hinge", "ridge", 1e-3, rows=2, iters=3, checkpoint_every=3, weight_pull=n / 10, **options)
    assert np.abs(run.model.matrix - np.vstack(root.w_bar)).max() < 1e-9


def test_keyed_sum_gives_the_same(spark, xor, monkeypatch):
    from kernelblocks.admm import engine

    a = solve(xor, FMAP, rows=18, iters=3).model.matrix
    monkeypatch.setattr(engine, "DIRECT_BYTES", 0)
    b = solve(xor, FMAP, rows=18, iters=3).model.matrix
    assert np.abs(a - b).max() < 1e-12


@pytest.mark.parametrize("options", [{"rows": 3}, {"rows": 18, "block_fraction": 0.5}])
def test_consensus_by_join_gives_the_same(spark, xor, options):
    a = solve(xor, FMAP, "hinge", "lasso", iters=5, checkpoint_every=2, **options).model.matrix
    b = solve(xor, FMAP, "hinge", "lasso", iters=5, checkpoint_every=2, consensus="join", **options).model.matrix
    assert np.abs(a - b).max() < 1e-10


def test_resume_goes_on_where_it_stopped(spark, xor, tmp_path):
    whole = solve(xor, FMAP, rows=2, iters=8).model.matrix
    folder = f"file://{tmp_path}/state"
    solve(xor, FMAP, rows=2, iters=5, save_state=folder)
    assert np.abs(solve(xor, FMAP, rows=2, iters=3, resume=folder).model.matrix - whole).max() < 1e-12


def test_stops_by_tolerance_and_by_patience(spark, xor):
    train, test = split(xor)
    run = solve(train, FMAP, "squared", rows=2, iters=60, tol=0.02)
    assert run.rounds < 60 and run.history[-1]["primal_residual"] < 0.02
    run = solve(train, FMAP, rows=2, iters=40, eval_df=test, eval_every=2, patience=2)
    assert run.rounds < 40


def test_inputs_and_factors_stay_where_they_are(spark, xor):
    packed = pack(xor, 2).select("row_block", "n", "d", "x", "y", F.lit(None).cast("binary").alias("factors")).repartition(2, "row_block").persist()
    packed.count()
    cfg = SolverConfig(FMAP, "hinge", n=100, m=1, rows=2)
    first = _round(packed, None, Root.zero(cfg).w_bar, 1, cfg, True).persist()
    assert first.columns == ["kind", "row_block", "block", "step", "value", "payload"]
    state = first.where("kind = 'state'").select("row_block", "payload")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = _round(packed, state, Root.zero(cfg).w_bar, 2, cfg)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    # what lies in memory is not made again; of the rest one exchange moves the states
    open_, hidden = [], None
    for line in plan.splitlines():
        depth = len(line) - len(line.lstrip(" :+-"))
        if hidden is not None and depth > hidden:
            continue
        hidden = depth if "InMemoryRelation" in line else None
        open_.append(line)
    moves = [k for k, line in enumerate(open_) if "Exchange" in line]
    assert len(moves) == 1 and not any("x#" in line for line in open_[moves[0] :])
    payload = max(len(bytes(r["payload"])) for r in state.collect())
    factors = max(len(bytes(r["payload"])) for r in first.where("kind = 'factor'").collect())
    assert factors > 4 * 16 * 16 * 8 and payload < factors + 30 * xor.count()


@pytest.mark.parametrize("options", [{}, {"loss": "logistic"}, {"block_fraction": 0.5}, {"cache": "cholesky", "reg": "lasso"}])
@pytest.mark.parametrize("direct", [True, False])
def test_a_block_spread_over_tasks_takes_the_same_path(spark, xor, options, direct, monkeypatch):
    from kernelblocks.admm import tiled

    if not direct:
        monkeypatch.setattr(tiled, "DIRECT_BYTES", 0)
        if options:
            return
    kw = {"rows": 3, "iters": 6, "checkpoint_every": 2} | options
    ex = xor if options.get("loss") != "logistic" else xor.withColumn("y", F.array((F.col("label") > 0).cast("double") * 2 - 1, (F.col("label") < 0).cast("double") * 2 - 1))
    a = solve(ex, FMAP, tile_rows=16, **kw)
    b = solve(ex, FMAP, spread_rows=20, keep_trajectory=True, eval_df=xor if not options else None, eval_every=3, **kw)
    assert np.abs(a.model.matrix - b.model.matrix).max() < 1e-10 and len(b.trajectory) == 6
    if not options:
        assert [h["iter"] for h in b.history] == [3, 6]
        assert {r for _, r, step, _ in b.profile if step == "tiles"} == {0, 1, 2}


@pytest.mark.parametrize("options", [{}, {"loss": "absolute", "reg": "lasso"}, {"consensus": "join"}, {"consensus": "join", "block_fraction": 0.5}])
def test_a_large_block_is_spread_by_itself(spark, xor, options, monkeypatch):
    from kernelblocks.admm import engine

    kw = {"rows": 2, "iters": 4, "checkpoint_every": 2} | options
    a = solve(xor, FMAP, **kw).model.matrix
    monkeypatch.setattr(engine, "pack", None)  # a block in one row
    monkeypatch.setattr(engine, "BLOCK_BYTES", 0)
    monkeypatch.setattr(engine, "TILE_BYTES", 8 * 64 * 70)
    run = solve(xor, FMAP, **kw)
    assert np.abs(a - run.model.matrix).max() < 1e-10
    if "consensus" not in options:
        steps = {step for _, r, step, _ in run.profile if r >= 0}
        assert {"transform", "factor", "prox", "projection", "sums", "round"} <= steps
    few = solve(xor, FMAP, "hinge", rows=2, iters=1)
    assert few.config.n == xor.count()


def test_passes_over_tiles_never_fill_the_storage_memory(spark, xor, monkeypatch):
    from kernelblocks.admm import tiled

    kept, levels = tiled.kept_flat, []

    def seen(df, **options):
        before = set(spark.sparkContext._jsc.getPersistentRDDs())
        out = kept(df, **options)
        held = spark.sparkContext._jsc.getPersistentRDDs()
        levels.extend(("tile" in df.columns, held[k].getStorageLevel().useMemory()) for k in held if k not in before)
        return out

    monkeypatch.setattr(tiled, "kept_flat", seen)
    solve(xor, FMAP, rows=1, iters=2, spread_rows=40, block_tasks=1)
    # all tiles of a row block may lie in one task: their states go to disk as they come, the local models are small
    assert sorted(levels) == [(False, True)] * 2 + [(True, False)] * 2


def test_rows_alike_count_as_often_as_they_are(spark, xor, monkeypatch):
    from kernelblocks.admm import engine

    ex = xor.withColumn("x", F.transform("x", lambda v: F.round(v / 8))).unionAll(xor)
    a = solve(ex, FMAP, "absolute", rows=3, iters=5).model.matrix
    monkeypatch.setattr(engine, "BLOCK_BYTES", 0)
    for tasks in (0, 1):
        assert np.abs(a - solve(ex, FMAP, "absolute", rows=3, iters=5, block_tasks=tasks).model.matrix).max() < 1e-10


def test_tiles_hold_every_row_once(spark, xor):
    from kernelblocks.plans.blocks import loosened, pack_tiles

    wide = xor.withColumn("x", F.transform("x", lambda v: F.round(v / 8))).union(xor)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50")
    try:
        tiles = pack_tiles(wide.repartition(3), 2, 16, 2).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert max(t["n"] for t in tiles) <= 16 and len({t["tile"] for t in tiles}) == len(tiles)
    assert {t["slot"] // 2 == t["row_block"] for t in tiles} == {True}
    got = []
    for t in tiles:
        rows = np.hstack((unpack_batch(loosened(bytes(t["x"])), t["d"]), np.frombuffer(loosened(bytes(t["y"]))).reshape(t["n"], -1)))
        counts = np.frombuffer(loosened(bytes(t["counts"]))) if t["counts"] is not None else np.ones(t["n"])
        got.append(np.repeat(rows, counts.astype(int), axis=0))
    got = np.vstack(got)
    assert any(t["counts"] is not None for t in tiles)
    want = np.array([[*r["x"], *r["y"]] for r in wide.collect()])
    assert np.array_equal(got[np.lexsort(got.T)], want[np.lexsort(want.T)])


def test_even_blocks_differ_by_one_row(spark, xor):
    from kernelblocks.plans.blocks import even_blocks

    for rows in (3, 7):
        sizes = sorted(r["count"] for r in even_blocks(xor.union(xor.limit(5)), rows).groupBy("row_block").count().collect())
        assert len(sizes) == rows and sizes[-1] - sizes[0] <= 1 and sum(sizes) == xor.count() + 5
    few = even_blocks(xor.limit(2), 5)
    assert few.select("row_block").distinct().count() == 2
    assert solve(xor, FMAP, rows=3, iters=2, even=True).config.rows == 3


def test_a_block_too_large_for_a_row_is_refused(spark, xor, monkeypatch):
    from kernelblocks.admm import engine

    monkeypatch.setattr(engine, "MAX_ROW_BYTES", 1000)
    with pytest.raises(ValueError, match="spread_rows"):
        solve(xor, FMAP, rows=1, iters=1)


def test_prediction_passes_columns_and_does_not_shuffle(spark, xor):
    model = feature_ridge(xor, FMAP, 1e-3)
    scored = predict(xor.withColumn("extra", F.lit("kept")), model)
    assert scored.columns == ["row_id", "x", "y", "label", "extra", "scores", "pred", "margin"]
    assert "Exchange" not in scored._jdf.queryExecution().executedPlan().toString().split("InMemory")[0]
    assert measures.accuracy(scored) > 0.9
    shares = predict(xor, Model(FMAP, [np.hstack((w, -w)) for w in model.weights]), proba=True).first()["scores"]
    assert abs(sum(shares) - 1) < 1e-12


def test_sparse_and_dense_text_give_one_model(spark, sf):
    ex = text_task(spark.read.parquet(f"{sf}/documents.parquet"), "doc_id", "text", "lang", ["en", "fr", "de", "es"], 64)
    fmap = FourierMap(64, 32, 2, 1, sigma=0.7)
    a = solve(ex, fmap, "logistic", lam=1e-4, rows=2, iters=3)
    b = solve(densified(ex), fmap, "logistic", lam=1e-4, rows=2, iters=3)
    assert np.abs(a.model.matrix - b.model.matrix).max() < 1e-9
    assert measures.accuracy(predict(ex, a.model)) > 0.5


def test_model_is_stored_and_read(spark, xor, tmp_path):
    model = feature_ridge(xor, FMAP, 1e-3)
    model.save(spark, f"file://{tmp_path}/m")
    back = Model.load(spark, f"file://{tmp_path}/m")
    assert np.array_equal(back.matrix, model.matrix) and back.fmap == FMAP


def test_edges(spark, xor):
    with pytest.raises(ValueError):
        solve(xor.limit(0), FMAP, rows=2, iters=1)
    bad = spark.createDataFrame([(1, [1.0, None], [1.0])], "row_id long, x array<double>, y array<double>")
    with pytest.raises(Exception, match="null or not a number"):
        solve(bad, FMAP, rows=1, iters=1)
    three = xor.limit(3)
    run = solve(three, FMAP, rows=8, iters=2)  # more blocks than rows
    assert run.model.matrix.shape == (64, 1)
    with pytest.raises(ValueError):
        solve(xor, FourierMap(2, 40_000, 1, 1), rows=1, iters=1)  # one block's factor would be too large
    twice = xor.union(xor)
    assert solve(twice, FMAP, rows=2, iters=2).config.n == 2 * xor.count()


def test_ridge_baselines_agree(spark, xor):
    _, x, y = local_rows(xor, 5000)
    z = FMAP.features(x)
    model = feature_ridge(xor, FMAP, 1e-3)
    dual = z.T @ np.linalg.solve(z @ z.T + len(x) * 1e-3 * np.eye(len(x)), y)
    assert np.abs(model.matrix - dual).max() < 1e-7
    k = kernels.make("gaussian", sigma=1.0)
    a, b = exact_ridge(xor, k, 1e-2), exact_ridge(xor, k, 1e-2, "cg")
    assert np.abs(a.alpha - b.alpha).max() < 1e-6
    gram = k(x, x)
    assert rkhs_norm(a.alpha, gram) > 0
    assert np.allclose((gram + len(x) * 1e-2 * np.eye(len(x))) @ a.alpha, y)
    assert measures.accuracy(predict_dual(xor, a)) > 0.9
    assert measures.accuracy(predict(xor, linear_ridge(xor, 1e-3, 2))) < 0.65
    with pytest.raises(ValueError):
        local_rows(xor, 10)


def test_support_vector_machines_agree(spark, xor):
    k, lam = kernels.make("gaussian", sigma=1.0), 1e-3
    _, x, y = local_rows(xor, 5000)
    n = len(x)
    cost = 1.0 / (2 * n * lam)
    gram = k(x, x)
    free = smo(x, y[:, 0], k, cost, 1e-6, bias=False)
    f = free.decide(x)[:, 0]

    def worth(f, norm):
        return np.maximum(0, 1 - y[:, 0] * f).mean() + lam * norm

    low = np.linalg.cholesky(gram + 1e-9 * np.eye(n))
    a = interior_point_svm(low, y[:, 0], cost)
    ay = a * y[:, 0]
    assert abs(worth(f, float(free.alpha[:, 0] @ k(free.support, free.support) @ free.alpha[:, 0])) - worth(gram @ ay, ay @ gram @ ay)) < 1e-4
    block = solve(xor, FourierMap(2, 512, 1, 1, sigma=1.0), "hinge", lam=lam, rows=2, iters=40, checkpoint_every=20)
    exact = smo_svm(xor, k, lam)
    assert exact.n_support < n
    acc = [measures.accuracy(predict(xor, block.model)), measures.accuracy(predict_dual(xor, exact)), measures.accuracy(predict_dual(xor, lowrank_svm(xor, k, lam)))]
    assert min(acc) > 0.9 and abs(acc[0] - acc[1]) < 0.03


def test_exact_machines_take_any_number_of_rows(spark, xor, monkeypatch):
    from kernelblocks.baselines import ridge, svm

    k = kernels.make("gaussian", sigma=1.0)
    a = exact_ridge(xor, k, 1e-3)
    monkeypatch.setattr(ridge, "MAX_DIRECT_ROWS", 10)
    monkeypatch.setattr(ridge, "STRIP_CELLS", 5000)
    b = exact_ridge(xor, k, 1e-3)
    assert 0 < b.rounds < 30 and np.abs(a.alpha - b.alpha).max() < 1e-6
    few = smo_svm(xor, k, 1e-3, 1e-5)
    monkeypatch.setattr(svm, "PAIR_ROWS", 10)
    monkeypatch.setattr(svm, "working_set_smo", lambda *v, **kw: working(*v, **kw, size=32))
    many = smo_svm(xor, k, 1e-3, 1e-5)
    x = local_rows(xor, None)[1]
    assert np.abs(few.decide(x) - many.decide(x)).max() < 1e-3 and abs(few.n_support - many.n_support) <= 3


def test_interior_point_where_the_rows_lie(spark, xor, monkeypatch):
    from kernelblocks.baselines import svm

    k = kernels.make("gaussian", sigma=1.0)
    a = svm.lowrank_svm(xor, k, 1e-3, 12)
    monkeypatch.setattr(svm, "DRIVER_FACTOR_BYTES", 0)
    b = svm.lowrank_svm(xor, k, 1e-3, 12)
    assert np.abs(a.alpha - b.alpha).max() < 1e-5 * np.abs(a.alpha).max() and abs(a.n_support - b.n_support) <= 2


def test_runs_share_blocks_and_factors(spark, xor):
    from kernelblocks.admm.engine import shared

    with shared(xor, 3) as blocks:
        for lam, rho in ((1e-3, 0.01), (1e-2, 0.01), (1e-2, 0.002)):
            a = solve(xor, FMAP, "hinge", lam=lam, rho=rho, rows=3, iters=4, blocks=blocks).model.matrix
            assert np.abs(a - solve(xor, FMAP, "hinge", lam=lam, rho=rho, rows=3, iters=4).model.matrix).max() < 1e-12
        assert len(blocks.factors) == 1


def test_incomplete_cholesky_nears_the_kernel(spark, xor):
    k = kernels.make("gaussian", sigma=1.0)
    packed, px, tri = incomplete_cholesky(xor, k, 120, 20, rows=2)
    rows = packed.collect()
    x = np.vstack([unpack_batch(bytes(r["x"]), r["d"]) for r in rows])
    h = np.vstack([np.frombuffer(bytes(r["h"])).reshape(r["n"], -1) for r in rows])
    assert np.abs(h @ h.T - k(x, x)).max() < 0.02
    assert np.allclose(np.linalg.solve(tri, k(px, x)).T, h, atol=1e-6)


def test_linear_solvers_on_stored_features(spark, xor):
    opt = solve(xor, FMAP, "hinge", lam=1e-2, rows=1, iters=150, checkpoint_every=50)
    best = objective(xor, opt.model, "hinge", "ridge", 1e-2)
    model, history = materialized_linear(xor, FMAP, "hinge", 1e-2, "lbfgs", 40)
    assert history[-1] < history[0] and objective(xor, model, "hinge", "ridge", 1e-2) < best + 0.02
    sgd, _ = materialized_linear(xor, FMAP, "hinge", 1e-2, "sgd", 30)
    assert objective(xor, sgd, "hinge", "ridge", 1e-2) < history[0]
    lib, _ = materialized_linear(xor, FMAP, "hinge", 1e-2, "mllib", 30)
    assert measures.accuracy(predict(xor, lib)) > 0.85


def test_stored_features_count_equal_rows_once(spark, xor):
    from kernelblocks.baselines.linear import _gradient, stored_tiles
    from kernelblocks.functions.prox import loss_of

    rows = [(k, [float(k % 7), float(k % 3)], [1.0 if k % 2 else -1.0, 0.0 if k % 2 else 1.0]) for k in range(3000)]
    same = spark.createDataFrame(rows, "row_id long, x array<double>, y array<double>").coalesce(2)
    assert stored_tiles(same, FMAP).agg(F.sum(F.length("z"))).first()[0] <= 2 * 42 * FMAP.s * 8
    w = np.random.default_rng(5).normal(size=(FMAP.s, 2))
    docs = text_task(spark.createDataFrame([(k, f"abc {k}", k % 2) for k in range(200)], "k long, t string, c int"), "k", "t", "c", [0, 1])
    wide = FourierMap(256, 64, 4, 1, sigma=1.0)
    for df, fmap, m in ((same, FMAP, 2), (xor, FMAP, 1), (docs, wide, 1)):
        plain = densified(df) if df is docs else df
        got = plain.select("x", "y").collect()
        z, y = fmap.features(np.array([r["x"] for r in got], float)), np.array([r["y"] for r in got], float)
        stored = stored_tiles(df, fmap).persist()
        assert stored.count() < 20
        for loss in ("hinge", "squared") + (("logistic",) if m > 1 else ()):
            f, v = loss_of(loss), w[:, :m]
            value, g = _gradient(stored, v, loss, 1e-2)
            assert np.isclose(value, f.value(z @ v, y) / len(z) + 1e-2 * (v * v).sum())
            assert np.allclose(g, z.T @ f.slope(z @ v, y) / len(z) + 2e-2 * v)


def test_average_of_parts_is_worse_than_the_whole(spark, xor):
    whole = objective(xor, feature_ridge(xor, FMAP, 1e-3), "squared", "ridge", 1e-3)
    parts = objective(xor, average_ensemble(xor, FMAP, 1e-3, 8), "squared", "ridge", 1e-3)
    assert whole <= parts + 1e-9


def test_generated_examples_do_not_depend_on_partitions(spark):
    spark.dataSource.register(KernelBlobs)
    a, b = (spark.read.format("kernel_blobs").option("rows", 60).option("partitions", p).load() for p in (1, 5))
    assert a.orderBy("row_id").collect() == b.orderBy("row_id").collect()
    assert measures.accuracy(predict(a.withColumn("label", 2.0 * F.col("label") - 1).withColumn("y", F.array("label")), feature_ridge(a.withColumn("y", F.array(2.0 * F.col("label") - 1)), FMAP, 1e-3))) > 0.9


def test_feature_count_raises_accuracy(spark, sf):
    from kernelblocks.workloads.experiments import feature_growth

    got = {r["value"]: r["result"] for r in feature_growth(spark, sf, (4, 256)).collect()}
    assert got[256.0] > got[4.0] and got[256.0] > got[0.0] + 0.2


def test_the_breakdown_is_of_all_rows(spark, sf, monkeypatch):
    from kernelblocks.workloads import experiments

    seen = []

    def solved(train, *args, **kw):
        run = solve(train, *args, **kw)
        seen.append(run.config.n)
        return run

    def scored(run, test):
        seen.append(test.count())
        return 0.0, 1.0

    monkeypatch.setattr(experiments, "solve", solved)
    monkeypatch.setattr(experiments, "_score", scored)
    steps = {r["step"] for r in experiments.big_breakdown(spark, sf, s=16, cols=2, iters=2, rows=2).collect()}
    assert seen == [part.count() for part in experiments.train_test(spark, sf, "cells25")]
    assert {"transform", "projection", "prox", "barrier", "communication", "prediction", "total"} <= steps


def test_kernel_machines_take_all_rows(spark, sf):
    from kernelblocks.workloads import experiments

    rows = {r["solver"]: r["result"] for r in experiments.compare_svm(spark, sf, iters=2, names=("checker",)).collect() if r["metric"] == "rows"}
    assert rows == dict.fromkeys(("block", "sequential", "low_rank"), float(experiments.train_test(spark, sf, "checker")[0].count()))


def test_rows_alike_are_one_variable_of_the_machines(spark, xor, monkeypatch):
    from kernelblocks.baselines import svm

    k = kernels.make("gaussian", sigma=1.0)
    # a third of the rows three times over; the machine of all rows apart is what to match
    third = xor.where("row_id % 3 = 0")
    more = xor.unionByName(third.withColumn("row_id", F.col("row_id") + 10_000)).unionByName(third.withColumn("row_id", F.col("row_id") + 20_000))
    _, x, y = local_rows(more, None)
    cost = 1.0 / (2 * len(y) * 1e-3)
    apart = smo(x, y[:, 0], k, cost, 1e-6)
    for fit in (smo, lambda *v, **kw: svm.working_set_smo(*v, **kw, size=32)):
        monkeypatch.setattr(svm, "smo", fit)
        got = svm.smo_svm(more, k, 1e-3, 1e-6)
        assert np.abs(got.decide(x) - apart.decide(x)).max() < 1e-4 and apart.n_support <= got.n_support <= len(y)
    gram = k(x, x)
    free = gram @ (interior_point_svm(np.linalg.cholesky(gram + 1e-9 * np.eye(len(y))), y[:, 0], cost) * y[:, 0])
    for most in (1 << 30, 0):
        monkeypatch.setattr(svm, "DRIVER_FACTOR_BYTES", most)
        got = svm.lowrank_svm(more, k, 1e-3, 120, 30)
        assert np.abs(got.decide(x)[:, 0] - free).max() < 1e-2 and got.n_support <= len(y)
