"""The experiments on the given tables, as long rows (workload, dataset, solver, param, value, metric, result).

Times are of the session at hand; row and column blocks, rows and features are what varies.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kernelblocks import measures
from kernelblocks.admm.engine import Run, objective, predict, shared, solve
from kernelblocks.baselines.linear import average_ensemble, materialized_linear
from kernelblocks.baselines.ridge import feature_ridge, linear_ridge, predict_dual
from kernelblocks.baselines.svm import lowrank_svm, smo_svm
from kernelblocks.functions import kernels
from kernelblocks.functions.featuremaps import (
    Concatenated,
    FourierMap,
    LaplaceMap,
    ShiftInvariantMap,
    StructuredFourierMap,
    TensorSketchMap,
    identity_map,
)
from kernelblocks.operators.prep import densified, embedding_task, lineitem_task, split, text_task
from kernelblocks.plans.blockplan import memory_model
from kernelblocks.sources.tables import table

SCHEMA = "workload string, dataset string, solver string, param string, value double, metric string, result double"
LANGS = ["en", "fr", "de", "es"]


_kept: list[DataFrame] = []


def release() -> None:
    """Lets go of the examples that the last experiment kept in memory."""
    while _kept:
        _kept.pop().unpersist()


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    release()
    return spark.createDataFrame([(*r[:4], float(r[4]), r[5], float(r[6])) for r in rows], SCHEMA)


def task(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Examples of a named task."""
    if name in ("checker", "ripple", "charge", "cells25"):
        return lineitem_task(table(spark, sf_dir, "lineitem"), name)
    if name == "lang4":
        return text_task(table(spark, sf_dir, "documents"), "doc_id", "text", "lang", LANGS)
    if name in ("quality", "toxic"):
        docs = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
        return text_task(docs, "doc_id", "text", name, [0, 1])
    if name == "role3":
        turns = table(spark, sf_dir, "conversations").withColumn("key", F.col("conv_id") * 1000 + F.col("turn"))
        return text_task(turns, "key", "text", "role", ["user", "assistant", "system"])
    return embedding_task(table(spark, sf_dir, "embeddings"), name)


#: Tasks whose examples are columns of a table, cheaper read again than kept (25 outputs of a row take 200 bytes).
READ_AGAIN = ("checker", "ripple", "charge", "cells25")


def train_test(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Kept in memory where they take work to make: the runs below use both again and again."""
    ex = task(spark, sf_dir, name)
    if name in READ_AGAIN:
        return split(ex)
    if name == "quality" or name == "toxic":
        ex = ex.withColumn("label", F.when(F.col("label") == 1, 1).otherwise(-1))
    pair = tuple(part.persist() for part in split(ex))
    _kept.extend(pair)
    return pair


def _score(run: Run, test: DataFrame) -> tuple[float, float]:
    got, sec = measures.timed(lambda: measures.accuracy(predict(test, run.model)))
    return got, sec


def feature_growth(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (8, 32, 128, 512), name: str = "xor01") -> DataFrame:
    """Held-out accuracy against the number of random features, beside the linear model."""
    train, test = train_test(spark, sf_dir, name)
    rows = [("feature_growth", name, "linear", "s", 0, "accuracy", measures.accuracy(predict(test, linear_ridge(train, 1e-3, 2))))]
    for s in sizes:
        model = feature_ridge(train, FourierMap(2, s, 1, seed=1, sigma=1.0), 1e-3)
        rows.append(("feature_growth", name, "fourier", "s", s, "accuracy", measures.accuracy(predict(test, model))))
    return _rows(spark, rows)


def _seconds(run: Run) -> tuple[float, float]:
    """Median (wall seconds of a round, with reduce and broadcast; seconds of its slowest row block), without the first round.

    The first also makes the factors.
    """
    first = min(it for it, *_ in run.profile)
    wall = [sec for it, r, step, sec in run.profile if step == "wall" and it > first]
    by: dict[int, float] = {}
    for it, _, step, sec in run.profile:
        if step == "round" and it > first:
            by[it] = max(by.get(it, 0.0), sec)
    return tuple(float(np.median(v)) if v else 0.0 for v in (wall, list(by.values())))


def _curve(workload: str, name: str, param: str, value: float, run: Run) -> list[tuple]:
    """The accuracy after each measured round, as rows whose metric names the round."""
    return [(workload, name, "block", param, value, f"accuracy_round_{h['iter']}", h["accuracy"]) for h in run.history if "accuracy" in h]


def _some(df: DataFrame, one_of: int) -> DataFrame:
    """One row of so many, by a hash of the id: curves are measured on a stated part of the held-out rows."""
    return df.where(F.pmod(F.xxhash64("row_id"), F.lit(one_of)) == 0)


#: The data sets of the scaling runs: name, map, loss, outputs, classes.
SCALED = {
    "checker": (2, 1.0, "hinge", 1, None),
    "cells25": (2, 0.5, "hinge", 25, list(range(25))),
}


def _scaled(name: str, s: int, cols: int) -> tuple[FourierMap, str, list | None]:
    d, sigma, loss, _, classes = SCALED[name]
    return FourierMap(d, s, cols, seed=1, sigma=sigma), loss, classes


def _with_tables(spark: SparkSession, workload: str, param: str, runs: list[tuple], make, columns: tuple[str, ...]) -> list[tuple]:
    """Rows of the scaling measures of wall seconds and, beside them, of compute seconds alone."""
    rows = []
    for k, part in ((1, ""), (2, "compute_")):
        frame = spark.createDataFrame([(r[0], float(r[3]), r[k]) for r in runs], "series string, resources double, seconds double")
        rows += [(workload, t["series"], "block", param, t["resources"], part + m, t[m]) for t in make(frame).collect() for m in columns]
    return rows


def strong_scaling(spark: SparkSession, sf_dir: str, parts: tuple[int, ...] = (1, 2, 4, 8), iters: int = 3, s: int = 128, names: tuple[str, ...] = ("checker", "cells25")) -> DataFrame:
    """Fixed tables cut in more and more row blocks, each a task: wall and compute seconds of a round, speedup and
    efficiency of both, accuracy in all and by round."""
    rows, runs = [], []
    for name in names:
        train, test = train_test(spark, sf_dir, name)
        fmap, loss, classes = _scaled(name, s, 4)
        few = _some(test, 20).persist()
        _kept.append(few)
        for r in parts if name == names[0] else (parts[0], parts[-1]):
            run = solve(train, fmap, loss, "ridge", 1e-4, rows=r, iters=iters, checkpoint_every=iters, classes=classes, eval_df=few, eval_every=1, block_tasks=1)
            wall, busy = _seconds(run)
            runs.append((name, wall, busy, r))
            rows += [("strong_scaling", name, "block", "R", r, m, v) for m, v in (("accuracy", _score(run, test)[0]), ("seconds", wall), ("compute_seconds", busy))]
            rows += _curve("strong_scaling", name, "R", r, run)
    rows += _with_tables(spark, "strong_scaling", "R", runs, measures.scaling_table, ("speedup", "efficiency"))
    return _rows(spark, rows)


def weak_scaling(spark: SparkSession, sf_dir: str, parts: tuple[int, ...] = (1, 2, 4), iters: int = 3, s: int = 128, names: tuple[str, ...] = ("checker", "cells25")) -> DataFrame:
    """As many rows for each row block at every count of blocks: a growing share of the table, the whole of it at most blocks."""
    rows, runs = [], []
    for name in names:
        train, test = train_test(spark, sf_dir, name)
        fmap, loss, classes = _scaled(name, s, 4)
        few = _some(test, 20).persist()
        _kept.append(few)
        for r in parts if name == names[0] else (parts[0], parts[-1]):
            own = train.where(F.pmod(F.xxhash64("row_id", F.lit("share")), F.lit(max(parts))) < r)
            run = solve(own, fmap, loss, "ridge", 1e-4, rows=r, iters=iters, checkpoint_every=iters, classes=classes, eval_df=few, eval_every=1, block_tasks=1)
            wall, busy = _seconds(run)
            runs.append((name, wall, busy, r))
            rows += [("weak_scaling", name, "block", "R", r, m, v) for m, v in (("rows", run.config.n), ("accuracy", _score(run, test)[0]), ("seconds", wall), ("compute_seconds", busy))]
            rows += _curve("weak_scaling", name, "R", r, run)
    rows += _with_tables(spark, "weak_scaling", "R", runs, measures.weak_table, ("ratio",))
    return _rows(spark, rows)


def column_sweep(spark: SparkSession, sf_dir: str, cols: tuple[int, ...] = (1, 4, 16, 64), iters: int = 10, s: int = 256) -> DataFrame:
    """Column blocks against time, memory of the factors and progress, by round, on two data sets."""
    rows = []
    for name, fmap_of in (("xor01", lambda c: FourierMap(2, s, c, seed=1, sigma=1.0)), ("argmax10", lambda c: FourierMap(10, s, c, seed=1, sigma=4.0))):
        train, test = train_test(spark, sf_dir, name)
        n = train.count()
        for c in cols if name == "xor01" else (cols[0], cols[-1]):
            fmap = fmap_of(c)
            run = solve(train, fmap, "hinge", "ridge", 1e-3, rho=0.3 / n, rows=4, iters=iters, checkpoint_every=iters, eval_df=test, eval_every=max(1, iters // 5))
            wall, busy = _seconds(run)
            values = {
                "objective": objective(train, run.model, "hinge", "ridge", 1e-3), "accuracy": _score(run, test)[0], "seconds": wall, "compute_seconds": busy,
                "factor_numbers": memory_model(n, run.config.m, fmap.d, s, c, 4, 4, 1)["factors"],
            }
            rows += [("column_sweep", name, "block", "C", c, m, v) for m, v in values.items()]
            rows += _curve("column_sweep", name, "C", c, run)
    return _rows(spark, rows)


def big_breakdown(spark: SparkSession, sf_dir: str, s: int = 4096, cols: int = 16, iters: int = 3, name: str = "cells25", rows: int = 8) -> DataFrame:
    """(step, min_sec, max_sec, avg_sec, share): where the time of a larger model goes, by row block.

    barrier is what a block waits for the slowest of its round, communication the rest of the round's wall time:
    reduce, root step, broadcast and scheduling. Trained on all rows and scored on all that are held out; blocks too
    large for a task are spread over several, whose features (rows x s numbers) are never stored.
    """
    train, test = train_test(spark, sf_dir, name)
    fmap, loss, classes = _scaled(name, s, cols)
    run = solve(train, fmap, loss, "ridge", 1e-4, rows=rows, iters=iters, checkpoint_every=iters, classes=classes)
    _, sec = _score(run, test)
    blocks = sorted({r for _, r, step, _ in run.profile if step == "round"})
    times = [(r, step, t) for _, r, step, t in run.profile if step not in ("wall", "tiles")]  # tiles: the steps of a spread block together
    for it in sorted({it for it, *_ in run.profile}):
        own = {r: t for i, r, step, t in run.profile if i == it and step == "round"}
        wall = sum(t for i, _, step, t in run.profile if i == it and step == "wall")
        slowest = max(own.values())
        for r in blocks:
            times += [(r, "barrier", slowest - own[r]), (r, "communication", max(0.0, wall - slowest)), (r, "total", wall)]
    times += [(r, step, sec) for r in blocks for step in ("prediction", "total")]
    release()
    return measures.step_profile(spark.createDataFrame(times, "row_block int, step string, sec double"), "total")


#: The binary tasks of the comparison: map, kernel's width, loss; quality's inputs are texts.
BINARY = {"xor01": (2, 512, 1.0), "quality": (256, 512, 0.7), "checker": (2, 256, 1.0)}


def compare_svm(spark: SparkSession, sf_dir: str, iters: int = 30, names: tuple[str, ...] = ("xor01", "quality", "checker")) -> DataFrame:
    """The block solver, the sequential exact machine and the low-rank machine on binary tasks.

    All three train on all rows, at the same settings for any number of them, and are scored on all that are held out.
    Rows alike in input and target are one variable of the sequential and the low-rank machine: times are times of that.
    """
    rows = []
    for name in names:
        d, s, sigma = BINARY[name]
        train, test = train_test(spark, sf_dir, name)
        n = train.count()
        lam, kernel = 1e-3, kernels.make("gaussian", sigma=sigma)
        plain, scored = train, test
        if name == "quality":
            plain, scored = densified(train).persist(), densified(test)
            plain.count()
            _kept.append(plain)

        def add(solver: str, fit, score, name=name, lam=lam, n=n) -> None:
            model, train_sec = measures.timed(fit)
            acc, test_sec = measures.timed(lambda: measures.accuracy(score(model)))
            values = {"rows": n, "train_seconds": train_sec, "test_seconds": test_sec, "accuracy": acc}
            if hasattr(model, "n_support"):
                values["n_support"] = model.n_support
            rows.extend(("compare_svm", name, solver, "lam", lam, m, v) for m, v in values.items())

        fmap = FourierMap(d, s, 1 if s <= 512 else 4, seed=1, sigma=sigma)
        add("block", lambda: solve(train, fmap, "hinge", "ridge", lam, rho=0.3 / n, rows=4, iters=iters, checkpoint_every=10).model, lambda m: predict(test, m))
        add("sequential", lambda: smo_svm(plain, kernel, lam), lambda m: predict_dual(scored, m))
        add("low_rank", lambda: lowrank_svm(plain, kernel, lam), lambda m: predict_dual(scored, m))
    return _rows(spark, rows)


def compare_linear(spark: SparkSession, sf_dir: str, s: int = 256, iters: int = 24) -> DataFrame:
    """The block solver against linear solvers on the same features, stored beforehand, on two data sets."""
    rows = []
    for name, fmap, m, classes, turns in (
        ("argmax10", FourierMap(10, s, 4, seed=1, sigma=4.0), 10, None, iters),
        ("cells25", FourierMap(2, s // 2, 4, seed=1, sigma=0.5), 25, list(range(25)), 8),
    ):
        train, test = train_test(spark, sf_dir, name)
        lam = 1e-3 if name == "argmax10" else 1e-5
        run = solve(train, fmap, "hinge", "ridge", lam, rho=0.3 / train.count(), rows=4 if name == "argmax10" else 8, iters=turns, checkpoint_every=10, classes=classes)
        rows += [
            ("compare_linear", name, "block", "s", fmap.s, "train_seconds", run.seconds),
            ("compare_linear", name, "block", "s", fmap.s, "accuracy", _score(run, test)[0]),
            ("compare_linear", name, "block", "s", fmap.s, "objective", objective(train, run.model, "hinge", "ridge", lam)),
        ]
        for opt in ("lbfgs", "sgd"):
            began = time.perf_counter()
            model, history = materialized_linear(train, fmap, "hinge", lam, opt, turns, m=m, classes=classes)
            sec = time.perf_counter() - began
            rows += [
                ("compare_linear", name, opt, "s", fmap.s, "train_seconds", sec),
                ("compare_linear", name, opt, "s", fmap.s, "accuracy", measures.accuracy(predict(test, model))),
                ("compare_linear", name, opt, "s", fmap.s, "objective", history[-1]),
            ]
    return _rows(spark, rows)


def modularity(spark: SparkSession, sf_dir: str, iters: int = 3) -> DataFrame:
    """Every loss with every map and two penalties: held-out accuracy after a few rounds.

    The logistic loss takes two outputs, one for each class; the absolute one fits the signs.
    """
    train, test = train_test(spark, sf_dir, "xor01")
    shifted = F.transform("x", lambda v: F.abs(v) / 8)
    sign = F.element_at("y", 1)
    rows = []
    maps = {
        "fourier": FourierMap(2, 32, 2, seed=1, sigma=1.0),
        "structured": StructuredFourierMap(2, 32, 2, seed=1, sigma=1.0),
        "laplace": LaplaceMap(2, 32, 2, seed=1, beta=1.0),
        "tensor": TensorSketchMap(2, 32, 2, seed=1),
        "identity": identity_map(2, 2),
    }
    for map_name, fmap in maps.items():
        one, two = (t.withColumn("x", shifted) if map_name == "laplace" else t for t in (train, test))
        for loss in ("squared", "absolute", "hinge", "logistic"):
            own = one.withColumn("y", F.array(-sign, sign)) if loss == "logistic" else one
            for reg in ("ridge", "lasso"):
                run = solve(own, fmap, loss, reg, 1e-4, rows=2, iters=iters, checkpoint_every=iters, classes=[-1, 1])
                rows.append(("modularity", "xor01", f"{loss}-{reg}", map_name, fmap.s, "accuracy", _score(run, two)[0]))
    return _rows(spark, rows)


def stochastic_blocks(spark: SparkSession, sf_dir: str, fractions: tuple[float, ...] = (0.25, 0.5, 1.0), iters: int = 20) -> DataFrame:
    """A part of the column blocks in each round: objective after the same number of rounds."""
    train, _ = train_test(spark, sf_dir, "xor01")
    rows = []
    for p in fractions:
        run = solve(train, FourierMap(2, 128, 8, seed=1, sigma=1.0), "hinge", "ridge", 1e-3, rows=2, iters=iters, block_fraction=p, checkpoint_every=10)
        rows.append(("stochastic_blocks", "xor01", "block", "fraction", p, "objective", objective(train, run.model, "hinge", "ridge", 1e-3)))
    return _rows(spark, rows)


def grid_search(
    spark: SparkSession, sf_dir: str, name: str = "xor01", sigmas: tuple[float, ...] = (0.5, 1.0, 4.0), lams: tuple[float, ...] = (1e-4, 1e-2),
    rhos: tuple[float, ...] = (0.3, 1.0), sizes: tuple[int, ...] = (128,), iters: int = 12,
) -> DataFrame:
    """Held-out accuracy of the block solver over widths, features, penalties and steps (rho in parts of 1/n).

    All runs take the same packed row blocks; runs of one width and size take the same factors, which depend on neither
    penalty nor step.
    """
    train, test = train_test(spark, sf_dir, name)
    rows = []
    with shared(train, 2) as packed:
        n = train.count()
        for sigma in sigmas:
            for s in sizes:
                fmap = FourierMap(2, s, 2, seed=1, sigma=sigma)
                for lam in lams:
                    for rho in rhos:
                        run = solve(train, fmap, "hinge", "ridge", lam, rho=rho / n, rows=2, iters=iters, checkpoint_every=iters, blocks=packed)
                        rows.append(("grid_search", name, f"lam={lam:g},rho={rho:g}/n,s={s}", "sigma", sigma, "accuracy", _score(run, test)[0]))
    return _rows(spark, rows)


def ensemble_gap(spark: SparkSession, sf_dir: str, parts: tuple[int, ...] = (1, 4, 16)) -> DataFrame:
    """Averages of models fitted by part, against the fit of all rows together."""
    train, test = train_test(spark, sf_dir, "xor01")
    fmap, rows = FourierMap(2, 128, 1, seed=1, sigma=1.0), []
    for p in parts:
        model = average_ensemble(train, fmap, 1e-3, p)
        rows += [
            ("ensemble_gap", "xor01", "average", "parts", p, "objective", objective(train, model, "squared", "ridge", 1e-3)),
            ("ensemble_gap", "xor01", "average", "parts", p, "accuracy", measures.accuracy(predict(test, model))),
        ]
    return _rows(spark, rows)


def shift_invariant_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, test = train_test(spark, sf_dir, "shell01")
    rows = []
    for name, fmap in {
        "gaussian": FourierMap(2, 256, 1, seed=1, sigma=1.0),
        "laplacian": ShiftInvariantMap(2, 256, 1, seed=1, sigma=4.0),
        "matern": ShiftInvariantMap(2, 256, 1, seed=1, sigma=2.0, family="matern", nu=1.5),
        "concatenated": Concatenated(2, 256, 4, seed=1, inner=FourierMap(2, 1, 1, sigma=1.0)),
    }.items():
        rows.append(("shift_invariant_maps", "shell01", name, "s", 256, "accuracy", measures.accuracy(predict(test, feature_ridge(train, fmap, 1e-4)))))
    return _rows(spark, rows)
