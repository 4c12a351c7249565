"""Runs of the solver, of its variants and baselines, and the experiments: no SQL, tested against closed forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from kernelblocks import measures
from kernelblocks.admm.engine import predict, solve
from kernelblocks.baselines.linear import average_ensemble, materialized_linear
from kernelblocks.baselines.ridge import exact_ridge, feature_ridge, predict_dual
from kernelblocks.baselines.svm import lowrank_svm, smo_svm
from kernelblocks.functions import kernels
from kernelblocks.functions.featuremaps import Concatenated, FourierMap, LaplaceMap, StructuredFourierMap, TensorSketchMap
from kernelblocks.queries.registry import query
from kernelblocks.workloads import experiments
from kernelblocks.workloads.flagship import flagship


@query()
def solver_flagship(spark: SparkSession, d: str) -> DataFrame:
    return flagship(spark, d)


def _accuracy(spark: SparkSession, name: str, scored: DataFrame) -> DataFrame:
    got = measures.accuracy(scored)
    experiments.release()
    return spark.createDataFrame([(name, got)], "run string, accuracy double")


@query()
def solver_hinge_xor(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "xor01")
    run = solve(train, FourierMap(2, 256, 4, seed=1, sigma=1.0), "hinge", "ridge", 1e-3, rows=4, iters=30, checkpoint_every=10, eval_df=test, eval_every=10)
    experiments.release()
    return run.history_frame(spark)


@query()
def solver_logistic_lang(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "lang4")
    run = solve(train, FourierMap(256, 256, 2, seed=1, sigma=0.7), "logistic", "ridge", 1e-4, rows=4, iters=10)
    return _accuracy(spark, "lang4", predict(test, run.model))


@query()
def solver_absolute_ripple(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "ripple")
    run = solve(train, FourierMap(2, 128, 2, seed=1, sigma=0.5), "absolute", "ridge", 1e-5, rows=8, iters=10, coding="regression")
    return spark.createDataFrame([("ripple", measures.r_squared(predict(test, run.model)))], "run string, r2 double")


@query()
def solver_lasso(spark: SparkSession, d: str) -> DataFrame:
    """Features that a weighted absolute penalty keeps in the root's own model grow fewer with the penalty."""
    train, test = experiments.train_test(spark, d, "xor01")
    rows = []
    for lam in (1e-4, 1e-2):
        run = solve(train, FourierMap(2, 128, 2, seed=1, sigma=1.0), "squared", "lasso", lam, rows=2, iters=30, checkpoint_every=10)
        rows.append((lam, float(abs(run.model.matrix).sum()), measures.accuracy(predict(test, run.model))))
    return spark.createDataFrame(rows, "lam double, l1 double, accuracy double")


def _map_query(spark: SparkSession, d: str, name: str, task: str, fmap, lam: float = 1e-4) -> DataFrame:
    train, test = experiments.train_test(spark, d, task)
    return _accuracy(spark, name, predict(test, feature_ridge(train, fmap, lam)))


@query()
def map_structured(spark: SparkSession, d: str) -> DataFrame:
    return _map_query(spark, d, "structured", "argmax10", StructuredFourierMap(10, 512, 2, seed=1, sigma=4.0))


@query()
def map_laplace(spark: SparkSession, d: str) -> DataFrame:
    return _map_query(spark, d, "laplace", "lang4", LaplaceMap(256, 256, 2, seed=1, beta=0.05))


@query()
def map_tensor(spark: SparkSession, d: str) -> DataFrame:
    return _map_query(spark, d, "tensor", "lang4", TensorSketchMap(256, 256, 2, seed=1, degree=2))


@query()
def map_shift_invariant(spark: SparkSession, d: str) -> DataFrame:
    return experiments.shift_invariant_maps(spark, d)


@query()
def baseline_exact_ridge(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "xor01")
    return _accuracy(spark, "exact", predict_dual(test, exact_ridge(train, kernels.make("gaussian", sigma=1.0), 1e-3)))


@query()
def baseline_smo(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "xor01")
    return _accuracy(spark, "smo", predict_dual(test, smo_svm(train, kernels.make("gaussian", sigma=1.0), 1e-3)))


@query()
def baseline_lowrank(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "xor01")
    return _accuracy(spark, "low_rank", predict_dual(test, lowrank_svm(train, kernels.make("gaussian", sigma=1.0), 1e-3)))


@query()
def baseline_ensemble(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "xor01")
    return _accuracy(spark, "average", predict(test, average_ensemble(train, FourierMap(2, 128, 1, seed=1, sigma=1.0), 1e-3, 8)))


@query()
def map_concat(spark: SparkSession, d: str) -> DataFrame:
    inner = FourierMap(10, 1, 1, sigma=4.0)
    return _map_query(spark, d, "concatenated", "argmax10", Concatenated(10, 512, 4, seed=1, inner=inner))


@query()
def solver_joined_consensus(spark: SparkSession, d: str) -> DataFrame:
    """The solver on lineitem with the root's step on the executors, a tile of rows at a time."""
    train, test = experiments.train_test(spark, d, "checker")
    run = solve(train, FourierMap(2, 128, 4, seed=1, sigma=1.0), "hinge", "ridge", 1e-4, rows=4, iters=6, consensus="join", tile_rows=4096)
    return _accuracy(spark, "joined", predict(test, run.model))


@query()
def baseline_materialized(spark: SparkSession, d: str) -> DataFrame:
    train, test = experiments.train_test(spark, d, "quality")
    model, _ = materialized_linear(train, FourierMap(256, 128, 2, seed=1, sigma=0.7), "hinge", 1e-3, "lbfgs", 15)
    return _accuracy(spark, "materialized", predict(test, model))


for _f in (
    experiments.feature_growth,
    experiments.strong_scaling,
    experiments.weak_scaling,
    experiments.column_sweep,
    experiments.big_breakdown,
    experiments.compare_svm,
    experiments.compare_linear,
    experiments.modularity,
    experiments.stochastic_blocks,
    experiments.grid_search,
    experiments.ensemble_gap,
):
    query()(_f)
