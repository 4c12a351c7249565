"""Two-variable alternating direction method on the driver, for small problems and tests."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

Array = np.ndarray


def admm_generic(
    argmin_x: Callable[[Array, Array], Array],
    argmin_z: Callable[[Array, Array], Array],
    a: Array,
    b: Array,
    c: Array,
    iters: int,
    z0: Array,
    rho: float = 1.0,
) -> tuple[Array, Array, Array]:
    """min f(x) + g(z) with a x + b z = c; the arguments minimize over one variable given (the other, the dual).

    Returns x, z and the unscaled dual.
    """
    z, dual = z0, np.zeros_like(c)
    x = argmin_x(z, dual)
    for _ in range(iters):
        x = argmin_x(z, dual)
        z = argmin_z(x, dual)
        dual = dual + rho * (a @ x + b @ z - c)
    return x, z, dual


def augmented_lagrangian(fx: float, gz: float, residual: Array, dual: Array, rho: float) -> float:
    return float(fx + gz + dual.ravel() @ residual.ravel() + 0.5 * rho * (residual**2).sum())


def admm_constrained(
    prox_f: Callable[[Array, float], Array], project: Callable[[Array], Array], x0: Array, rho: float, iters: int, scaled: bool = True
) -> tuple[Array, Array, Array]:
    """min f(x) with x in a set; prox_f(v, 1/rho), the set's projection, and the dual (scaled by 1/rho or not)."""
    z, u = project(x0), np.zeros_like(x0)
    x = z
    for _ in range(iters):
        x = prox_f(z - u, 1.0 / rho)
        z = project(x + u)
        u = u + x - z
    return x, z, u if scaled else rho * u
