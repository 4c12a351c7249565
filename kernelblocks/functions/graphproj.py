"""Projection on the graph {(U, V): V = Z U}, with a factor that is made once for a block.

argmin k |U - X|^2/2 + |V - Y|^2/2 with V = Z U gives U = (Z'Z + k I)^-1 (k X + Z'Y). Where the block has fewer
rows than columns the inverse of the smaller matrix ZZ' + k I does the same. k, the pull, is 1 unless set.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Factor:
    """form tall holds the inverse (or root) of Z'Z + k I, wide that of ZZ' + k I."""

    form: str
    kind: str
    matrix: np.ndarray
    pull: float = 1.0

    def solve(self, z: np.ndarray, b: np.ndarray) -> np.ndarray:
        """(Z'Z + k I)^-1 b."""
        if self.form == "tall":
            return self._apply(b)
        return (b - z.T @ self._apply(z @ b)) / self.pull

    def _apply(self, b: np.ndarray) -> np.ndarray:
        if self.kind == "inverse":
            return self.matrix @ b
        return np.linalg.solve(self.matrix.T, np.linalg.solve(self.matrix, b))

    def project(self, z: np.ndarray, y: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        u = self.solve(z, self.pull * x + z.T @ y)
        return z @ u, u


def factor(z: np.ndarray, form: str = "auto", kind: str = "inverse", pull: float = 1.0) -> Factor:
    n, s = z.shape
    if form == "auto":
        form = "wide" if n < s else "tall"
    g = z.T @ z if form == "tall" else z @ z.T
    return factor_of_gram(g, form, kind, pull)


def factor_of_gram(g: np.ndarray, form: str = "tall", kind: str = "inverse", pull: float = 1.0) -> Factor:
    g = g + pull * np.eye(len(g))
    if kind == "cholesky":
        return Factor(form, kind, np.linalg.cholesky(g), pull)
    half = np.linalg.inv(np.linalg.cholesky(g))
    return Factor(form, kind, half.T @ half, pull)
