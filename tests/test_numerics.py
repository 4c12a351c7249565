"""Maps, kernels, prox operators, projections and generators, without Spark."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from kernelblocks.admm import generic
from kernelblocks.functions import graphproj, kernels, prox, rng
from kernelblocks.functions.featuremaps import (
    Concatenated,
    FourierMap,
    LaplaceMap,
    ShiftInvariantMap,
    Sparse,
    StructuredFourierMap,
    TensorSketchMap,
    identity_map,
    kernel_error,
)
from kernelblocks.plans import blockplan

R = np.random.default_rng(3)

MAPS = {
    "fourier": (FourierMap(8, 2048, 4, 3, sigma=2.0), 0.03),
    "portable": (FourierMap(8, 2048, 4, 3, sigma=2.0, generator="portable"), 0.03),
    "laplacian": (ShiftInvariantMap(8, 2048, 4, 3, sigma=4.0), 0.05),
    "matern": (ShiftInvariantMap(8, 2048, 4, 3, sigma=4.0, family="matern", nu=1.5), 0.05),
    "structured": (StructuredFourierMap(8, 2048, 4, 3, sigma=2.0), 0.04),
    "laplace": (LaplaceMap(8, 2048, 4, 3, beta=0.2), 0.02),
    "concatenated": (Concatenated(8, 2048, 4, 3, inner=FourierMap(8, 1, 1, 0, sigma=2.0)), 0.04),
}


@pytest.mark.parametrize("name", MAPS)
def test_maps_approximate_their_kernel(name):
    fmap, most = MAPS[name]
    x = np.abs(R.standard_normal((40, 8))) / 2
    assert kernel_error(x, fmap)["mean"] < most


@pytest.mark.parametrize("name", MAPS)
def test_sparse_inputs_give_the_same_block(name):
    fmap, _ = MAPS[name]
    x = np.abs(R.standard_normal((10, 8))) * (R.random((10, 8)) < 0.4)
    for j in range(fmap.col_blocks):
        assert np.allclose(fmap.block(Sparse.of(x), j), fmap.block(x, j), atol=1e-12)


def test_tensor_sketch_is_unbiased():
    x = R.standard_normal((12, 6)) / 2
    exact = kernels.polynomial(x, x, 2, 1.0, 1.0)
    mean = np.mean([(z := TensorSketchMap(6, 256, 1, s).features(x)) @ z.T for s in range(60)], axis=0)
    assert np.abs(mean - exact).mean() < 0.06


def test_error_shrinks_with_the_root_of_s():
    x = R.standard_normal((40, 8)) / 2
    few, many = (np.mean([kernel_error(x, FourierMap(8, s, 1, k, sigma=2.0))["mean"] for k in range(5)]) for s in (64, 1024))
    assert 2.5 < few / many < 6.5


def test_half_scale_is_half_the_kernel():
    x = R.standard_normal((5, 3))
    a, b = (FourierMap(3, 64, 2, 1, scale=s).features(x) for s in ("unit", "half"))
    assert np.allclose(a @ a.T, 2 * (b @ b.T))


def test_blocks_do_not_depend_on_order():
    f = FourierMap(4, 30, 4, 9)
    x = R.standard_normal((3, 4))
    late = f.block(x, 3)
    f.block(x, 0)
    assert np.array_equal(late, f.block(x, 3))
    assert f.features(x).shape == (3, 30)


def test_laplace_refuses_negative_inputs():
    with pytest.raises(ValueError):
        LaplaceMap(2, 4, 1).block(np.array([[1.0, -1.0]]), 0)


def test_generator_moments():
    z = rng.portable_normal(7, np.arange(64)[:, None], np.arange(512)[None, :])
    assert abs(z.mean()) < 0.02 and abs(z.var() - 1) < 0.03 and abs((z**4).mean() - 3) < 0.15


@pytest.mark.parametrize("loss", ["squared", "absolute", "hinge"])
@pytest.mark.parametrize("kappa", [0.1, 0.4, 2.0])
def test_prox_against_a_grid(loss, kappa):
    f = prox.loss_of(loss)
    grid = np.linspace(-6, 6, 120_001)
    for v in (-2.0, -0.5, 0.0, 0.3, 0.95, 1.5):
        for y in (-1.0, 1.0):
            if loss == "squared":
                values = (grid - y) ** 2
            elif loss == "absolute":
                values = np.abs(grid - y)
            else:
                values = np.maximum(0, 1 - grid * y)
            best = grid[np.argmin(kappa * values + 0.5 * (grid - v) ** 2)]
            assert abs(f.prox(np.array([[v]]), np.array([[y]]), kappa)[0, 0] - best) < 2e-4


@pytest.mark.parametrize("kappa", [0.1, 1.0, 30.0])
def test_logistic_prox_has_no_gradient(kappa):
    f = prox.Logistic()
    v, y = R.standard_normal((200, 5)), 2.0 * np.eye(5)[R.integers(0, 5, 200)] - 1
    o = f.prox(v, y, kappa)
    assert np.abs(kappa * f.slope(o, y) + o - v).max() < 1e-6


@pytest.mark.parametrize("reg", ["ridge", "lasso", "none", "group", "elastic"])
def test_reg_prox_is_a_minimum(reg):
    r = prox.reg_of(reg)
    v = R.standard_normal((6, 2))
    p = r.prox(v, 0.3)

    def worth(w):
        return 0.3 * r.value(w) + 0.5 * ((w - v) ** 2).sum()

    for _ in range(200):
        assert worth(p) <= worth(p + 0.01 * R.standard_normal(v.shape)) + 1e-12


def test_own_loss_can_be_registered():
    class Half(prox.Squared):
        name = "half"

    prox.register_loss("half", Half)
    assert prox.loss_of("half").name == "half"


def test_projections():
    v = R.standard_normal(6)
    assert np.all(prox.onto_box(v, -0.5, 0.5) <= 0.5) and np.all(prox.onto_nonnegative(v) >= 0)
    assert np.linalg.norm(prox.onto_ball(v * 10, 1.0)) <= 1 + 1e-12
    a, b = R.standard_normal((2, 6)), R.standard_normal(2)
    assert np.allclose(a @ prox.onto_affine(v, a, b), b)
    total, parts = prox.exchange(v, [v * 0.1, v * 0.2])
    assert np.allclose(total, sum(parts))
    assert np.allclose(prox.consensus_mean(v, [3 * v]), 2 * v)


@pytest.mark.parametrize(("n", "s"), [(12, 5), (5, 12)])
@pytest.mark.parametrize("kind", ["inverse", "cholesky"])
def test_graph_projection(n, s, kind):
    z, y, x = R.standard_normal((n, s)), R.standard_normal((n, 2)), R.standard_normal((s, 2))
    v, u = graphproj.factor(z, kind=kind).project(z, y, x)
    assert np.allclose(v, z @ u)
    best = np.linalg.lstsq(np.vstack((np.eye(s), z)), np.vstack((x, y)), rcond=None)[0]
    assert np.allclose(u, best)


def test_generic_method_and_constrained_form():
    goal = np.array([2.0, -3.0, 0.5])
    x, z, _ = generic.admm_constrained(lambda v, t: (v + t * 2 * goal) / (1 + 2 * t), lambda v: np.clip(v, -1, 1), np.zeros(3), 1.0, 200)
    assert np.allclose(z, np.clip(goal, -1, 1), atol=1e-6) and np.allclose(x, z, atol=1e-6)
    eye, zero = np.eye(3), np.zeros(3)
    x, z, _ = generic.admm_generic(
        lambda z, u: (2 * goal + z - u) / 3, lambda x, u: prox.soft(x + u, 0.5), eye, -eye, zero, 300, zero
    )
    assert np.allclose(z, prox.soft(goal, 0.25), atol=1e-6)
    assert generic.augmented_lagrangian(1.0, 2.0, np.ones(2), np.ones(2), 2.0) == 7.0


def test_block_bounds():
    assert np.diff(blockplan.block_bounds(10, 3)).tolist() == [4, 3, 3]
    assert np.diff(blockplan.block_bounds(7, 3)).tolist() == [3, 2, 2]
    assert np.diff(blockplan.block_bounds(2, 4)).tolist() == [1, 1, 0, 0]


def test_memory_model_gives_the_printed_numbers():
    gib = 2.0**30
    assert round(16 * gib / (64 * 100 * 8)) == 335_544
    one = blockplan.memory_model(200_000, 10, 784, 100_000, 200, 1, 1, 6)["total"] * 8 / gib
    many = blockplan.memory_model(250_000, 10, 784, 100_000, 200, 32, 32, 64)["total"] * 8 / gib
    assert abs(one - 6.227) < 0.02 and abs(many - 2.361) < 0.02
    simple = blockplan.memory_model_simple(200_000, 10, 784, 78_400, 20, 1.0, 6)
    assert abs(simple / blockplan.memory_model(200_000, 10, 784, 78_400, 100, 20, 20, 6)["total"] - 1) < 1e-9
    assert abs(blockplan.materialized_bytes(2_200_000, 528_000) / 9.29e12 - 1) < 0.01
    assert abs(blockplan.comm_model(528_000, 147, 256)["buffer"] / 0.621e9 - 1) < 0.01


def test_identity_map_cuts_the_inputs():
    x = R.standard_normal((4, 5))
    assert np.array_equal(identity_map(5, 2).features(x), x)


def test_kernel_work_goes_by_pairs_of_blocks(spark):
    rng = np.random.default_rng(3)
    x = np.round(rng.normal(size=(90, 3)), 1)
    df = spark.createDataFrame([(int(i), [float(v) for v in r]) for i, r in enumerate(x)], "row_id long, x array<double>")
    k, fmap = kernels.make("gaussian", sigma=1.0), FourierMap(3, 16, 2, 1)
    full = k(x, x)
    got = {(r["i"], r["j"]): r["k"] for r in kernels.gram(df, k, 20).collect()}
    assert len(got) == 90 * 91 // 2 and max(abs(v - full[i, j]) for (i, j), v in got.items()) < 1e-12
    gap = np.abs(fmap.features(x) @ fmap.features(x).T - full)[np.triu_indices(90)]
    rows = kernels.gaps(df, k, fmap.features, 20).collect()
    assert sum(r["pairs"] for r in rows) == gap.size and abs(max(r["most"] for r in rows) - gap.max()) < 1e-12
    assert abs(sum(r["total"] for r in rows) - gap.sum()) < 1e-9
    sums = {r["row_id"]: r["score"] for r in kernels.weighted_sums(df, k, lambda ids: ids * 0.5, 20).collect()}
    assert max(abs(v - full[i] @ (np.arange(90) * 0.5)) for i, v in sums.items()) < 1e-9 and len(sums) == 90
    near = {}
    for r in kernels.nearest(df, k, 3, block_rows=20).collect():
        near.setdefault(r["i"], []).append((-r["k"], r["j"]))
    for i in range(90):
        assert sorted(near[i])[:3] == sorted((-round(float(full[i, j]), 6) + 0.0, j) for j in range(90) if j != i)[:3]


def test_pairs_of_blocks_take_no_copies_of_rows(spark, capsys):
    x = np.random.default_rng(4).normal(size=(70, 3))
    df = spark.createDataFrame([(int(i) - 35, [float(v) for v in r]) for i, r in enumerate(x)], "row_id long, x array<double>")
    k = kernels.make("gaussian", sigma=1.0)
    got = kernels.gram(df, k, 10)
    got.explain()
    assert "Exchange" not in capsys.readouterr().out  # blocks are read where they lie, not sent to each pair
    sizes = got.groupBy(F.spark_partition_id().alias("task")).count().collect()
    assert sum(r["count"] for r in sizes) == 70 * 71 // 2 and len(sizes) == 7 * 8 // 2
    full = k(x, x)
    pairs = {(r["i"] + 35, r["j"] + 35): r["k"] for r in got.collect()}
    assert set(pairs) == {(i, j) for i in range(70) for j in range(i, 70)}
    assert max(abs(v - full[i, j]) for (i, j), v in pairs.items()) < 1e-12
    assert kernels.gram(df.limit(0), k).count() == 0


def test_text_examples_do_not_depend_on_slices(spark, sf, monkeypatch):
    """A task holds the examples of TEXT_ROWS texts, not those of a whole batch; the examples are the same."""
    from kernelblocks.operators import prep

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").coalesce(1)
    docs = docs.union(spark.createDataFrame([(-1, None, "en"), (-2, "", "fr"), (-3, "ab", "de")], docs.schema))
    made = {}
    for size in (3, 1 << 20):
        monkeypatch.setattr(prep, "TEXT_ROWS", size)
        made[size] = sorted(map(str, prep.text_task(docs, "doc_id", "text", "lang", ["en", "fr", "de", "es"]).collect()))
    assert made[3] == made[1 << 20] and len(made[3]) == docs.count()
