"""The block solver in one process: variants agree, and all reach the optimum."""

import numpy as np
import pytest

from kernelblocks.admm.step import BlockState, SolverConfig, solve_local
from kernelblocks.functions.featuremaps import FourierMap
from kernelblocks.functions.prox import Hinge

R = np.random.default_rng(0)
N, D, M, S = 120, 5, 3, 24
X, Y = R.standard_normal((N, D)), R.standard_normal((N, M))


def run(rows, cols, iters, loss="squared", y=Y, lam=1e-2, **kw):
    f = FourierMap(D, S, cols, 1, sigma=1.5)
    cfg = SolverConfig(f, loss, kw.pop("reg", "ridge"), lam, kw.pop("rho", 1.0 / N), N, y.shape[1], rows, **kw)
    root, states = solve_local(list(np.array_split(X, rows)), list(np.array_split(y, rows)), cfg, iters)
    return np.vstack(root.w_bar), states, f


def optimum(f, lam=1e-2):
    z = f.features(X)
    return np.linalg.solve(z.T @ z + N * lam * np.eye(S), z.T @ Y)


@pytest.mark.parametrize("variant", [{"layout": "explicit"}, {"gram_shortcut": True}, {"cache": "cholesky"}, {"cache": "none"}, {"threads": 3}, {"tile_rows": 7}, {"tile_rows": 1000, "cache": "cholesky"}])
def test_variants_take_the_same_path(variant):
    a, _, _ = run(3, 4, 20)
    b, _, _ = run(3, 4, 20, **variant)
    assert np.abs(a - b).max() < 1e-9


@pytest.mark.parametrize(("rows", "cols"), [(1, 1), (3, 4), (1, 4), (3, 1), (7, 2)])
def test_any_splitting_reaches_the_closed_form(rows, cols):
    w, _, f = run(rows, cols, 700)
    assert np.linalg.norm(w - optimum(f)) < 1e-5 * np.linalg.norm(optimum(f))


@pytest.mark.parametrize("fraction", [0.25, 0.5, 0.75])
def test_random_blocks_reach_it_too(fraction):
    w, _, f = run(3, 4, 1500, block_fraction=fraction)
    assert np.linalg.norm(w - optimum(f)) < 1e-3 * np.linalg.norm(optimum(f))


def test_the_printed_form_does_not():
    w, _, f = run(3, 4, 500, layout="printed")
    assert np.linalg.norm(w - optimum(f)) > 0.3 * np.linalg.norm(optimum(f))


def test_explicit_duals_equal_the_merged_one():
    _, states, _ = run(2, 3, 10, layout="explicit")
    for st in states:
        for nu in st.own_nu:
            assert np.allclose(nu, -st.nu)


def test_hinge_and_absolute_against_subgradients():
    y = np.sign(X[:, :1] * X[:, 1:2])
    w, _, f = run(3, 2, 600, "hinge", y)
    z = f.features(X)

    def value(w):
        return Hinge().value(z @ w, y) / N + 1e-2 * (w**2).sum()

    best, v = np.inf, np.zeros((S, 1))
    for k in range(1, 20_000):
        g = z.T @ Hinge().slope(z @ v, y) / N + 2e-2 * v
        v = v - g / (2e-2 * (k + 50))
        best = min(best, value(v))
    assert value(w) < best + 2e-3


def test_logistic_gradient_vanishes():
    y = 2.0 * np.eye(3)[R.integers(0, 3, N)] - 1
    w, _, f = run(2, 2, 800, "logistic", y)
    z = f.features(X)
    p = np.exp(z @ w)
    p /= p.sum(1, keepdims=True)
    assert np.abs(z.T @ (p - (y > 0)) / N + 2e-2 * w).max() < 1e-5


def test_lasso_meets_its_conditions():
    w, _, f = run(2, 2, 3000, reg="lasso", lam=0.02)
    z = f.features(X)
    g = 2 * z.T @ (z @ w - Y) / N
    assert np.abs(g).max() < 0.02 + 1e-4


def test_more_column_blocks_learn_more_slowly():
    y = np.sign(X[:, :1] * X[:, 1:2])
    values = []
    for c in (1, 4, 24):
        w, _, f = run(2, c, 10, "hinge", y)
        values.append(Hinge().value(f.features(X) @ w, y) / N + 1e-2 * (w**2).sum())
    assert values[0] <= values[1] + 1e-6 <= values[2] + 2e-6


def test_zero_rounds_and_state_shapes():
    w, states, _ = run(2, 2, 0)
    assert not w.any() and isinstance(states[0], BlockState) and states[0].nu.shape == (60, M)


def test_memory_of_the_state_has_no_output_for_each_column():
    _, states, _ = run(2, 4, 2)
    assert not states[0].own and not states[0].own_bar


@pytest.mark.parametrize("variant", [{}, {"layout": "explicit"}, {"tile_rows": 700}])
def test_the_models_step_keeps_the_rounds_of_many_rows(variant):
    """With the step of the outputs alone 100 times as many rows stand far off after as many rounds."""
    x = np.tile(X[:, :2], (100, 1))
    y = np.sign(x[:, :1] * x[:, 1:])
    f, n = FourierMap(2, 2, 2, 3, sigma=1.0, generator="portable"), len(x)
    z = f.features(x)
    want = np.linalg.solve(z.T @ z + n * 1e-3 * np.eye(2), z.T @ y)

    def far(rho, **kw):
        root, _ = solve_local(list(np.array_split(x, 2)), list(np.array_split(y, 2)), SolverConfig(f, "squared", "ridge", 1e-3, rho / n, n, 1, 2, **kw), 120)
        return np.linalg.norm(np.vstack(root.w_bar) - want) / np.linalg.norm(want)

    assert far(3.0, weight_pull=n / 10, **variant) < 1e-7
    assert min(far(3.0, **variant), far(10.0, **variant)) > 1e-5
