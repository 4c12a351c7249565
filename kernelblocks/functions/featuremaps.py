"""Randomized feature maps: block(X, j) gives the features of one column block, made when needed and dropped.

Every map is a small frozen configuration. Its random parameters come from (seed, block) alone, so a
task on any machine makes the same block. The output is dense for dense and sparse inputs alike.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from kernelblocks.functions import kernels
from kernelblocks.functions.rng import generator, omega_slice, portable_normal, portable_uniform
from kernelblocks.plans.blockplan import block_bounds


@dataclass
class Sparse:
    """Rows in compressed form: row i holds idx[ptr[i]:ptr[i+1]] with val; d columns."""

    ptr: np.ndarray
    idx: np.ndarray
    val: np.ndarray
    d: int

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.ptr) - 1, self.d

    def rows(self, low: int, high: int) -> Sparse:
        a, b = self.ptr[low], self.ptr[high]
        return Sparse(self.ptr[low : high + 1] - a, self.idx[a:b], self.val[a:b], self.d)

    def dot(self, w: np.ndarray, step: int = 1 << 16) -> np.ndarray:
        """Where more than one cell in twenty is filled, tiles of plain rows and one product each; else sums over the filled cells."""
        out = np.zeros((len(self.ptr) - 1, w.shape[1]))
        if 20 * len(self.idx) > len(out) * self.d:
            for k in range(0, len(out), 2048):
                part = self.rows(k, min(k + 2048, len(out)))
                out[k : k + 2048] = part.dense() @ w
            return out
        owner = np.repeat(np.arange(len(self.ptr) - 1), np.diff(self.ptr))
        for k in range(0, len(self.idx), step):
            part = slice(k, k + step)
            who, first = np.unique(owner[part], return_index=True)
            out[who] += np.add.reduceat(self.val[part, None] * w[self.idx[part]], first, axis=0)
        return out

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape)
        np.add.at(out, (np.repeat(np.arange(len(self.ptr) - 1), np.diff(self.ptr)), self.idx), self.val)
        return out

    def map_values(self, f) -> Sparse:
        return Sparse(self.ptr, self.idx, f(self.val), self.d)

    @classmethod
    def of(cls, x: np.ndarray) -> Sparse:
        rows, cols = np.nonzero(x)
        return cls(np.concatenate(([0], np.cumsum(np.bincount(rows, minlength=len(x))))), cols, x[rows, cols], x.shape[1])


Batch = np.ndarray | Sparse


def times(x: Batch, w: np.ndarray) -> np.ndarray:
    return x.dot(w)


def dense(x: Batch) -> np.ndarray:
    return x.dense() if isinstance(x, Sparse) else x


@dataclass(frozen=True)
class FeatureMap:
    """d inputs, s features in col_blocks blocks."""

    d: int
    s: int
    col_blocks: int = 1
    seed: int = 0

    def bounds(self) -> np.ndarray:
        return block_bounds(self.s, self.col_blocks)

    def width(self, j: int) -> int:
        b = self.bounds()
        return int(b[j + 1] - b[j])

    def block(self, x: Batch, j: int) -> np.ndarray:
        raise NotImplementedError

    def features(self, x: Batch) -> np.ndarray:
        return np.hstack([self.block(x, j) for j in range(self.col_blocks)])

    def kernel(self) -> kernels.Kernel:
        """The kernel that inner products of features tend to."""
        raise NotImplementedError

    def cost(self, n: int, nnz: int | None = None) -> float:
        """Multiplications of one transform of n rows."""
        return float(self.s) * (nnz if nnz is not None else n * self.d)


@dataclass(frozen=True)
class FourierMap(FeatureMap):
    """Gaussian kernel: cosines of random directions with a phase below half a turn.

    scale "unit" makes inner products tend to the kernel, "half" to half of it (division by the root of s).
    generator "portable" draws what the SQL twin draws.
    """

    sigma: float = 1.0
    scale: str = "unit"
    generator: str = "philox"

    def directions(self, j: int) -> tuple[np.ndarray, np.ndarray]:
        lo, k = int(self.bounds()[j]), self.width(j)
        if self.generator == "portable":
            place = lo + np.arange(k)
            w = portable_normal(self.seed, np.arange(self.d)[:, None], place[None, :])
            phase = portable_uniform(self.seed, self.d, 2 * place)
        else:
            w = self._spectrum(j, k)
            phase = generator(self.seed, j + (1 << 40)).random(k)
        return w / self.sigma, math.pi * phase

    def _spectrum(self, j: int, k: int) -> np.ndarray:
        return omega_slice(self.seed, j, self.d, k)

    def block(self, x: Batch, j: int) -> np.ndarray:
        w, phase = self.directions(j)
        z = times(x, w)
        z += phase
        np.cos(z, out=z)
        z *= math.sqrt((2.0 if self.scale == "unit" else 1.0) / self.s)
        return z

    def kernel(self) -> kernels.Kernel:
        return kernels.make("gaussian", sigma=self.sigma)


@dataclass(frozen=True)
class ShiftInvariantMap(FourierMap):
    """Laplacian (Cauchy spectrum) and Matern (Student spectrum) kernels; sigma is the width."""

    family: str = "laplacian"
    nu: float = 1.5

    def _spectrum(self, j: int, k: int) -> np.ndarray:
        rng = generator(self.seed, j)
        if self.family == "laplacian":
            return rng.standard_cauchy((self.d, k))
        free = 2.0 * self.nu
        return rng.standard_normal((self.d, k)) / np.sqrt(rng.chisquare(free, k) / free)

    def kernel(self) -> kernels.Kernel:
        if self.family == "laplacian":
            return kernels.make("laplacian", width=self.sigma)
        return kernels.make("matern", width=self.sigma, nu=self.nu)


def hadamard(x: np.ndarray) -> np.ndarray:
    """Walsh-Hadamard transform along the last axis, whose length is a power of two."""
    n, lead, h = x.shape[-1], x.shape[:-1], 1
    while h < n:
        x = x.reshape(*lead, n // (2 * h), 2, h)
        x = np.stack((x[..., 0, :] + x[..., 1, :], x[..., 0, :] - x[..., 1, :]), axis=-2).reshape(*lead, n)
        h *= 2
    return x


@dataclass(frozen=True)
class StructuredFourierMap(FeatureMap):
    """Gaussian kernel by products of Hadamard, sign, permutation and Gaussian diagonal factors: s log d work."""

    sigma: float = 1.0

    def block(self, x: Batch, j: int) -> np.ndarray:
        full = 1 << max(0, (self.d - 1).bit_length())
        k = self.width(j)
        padded = np.zeros((x.shape[0], full))
        padded[:, : self.d] = dense(x)
        rng = generator(self.seed, j)
        parts = []
        for _ in range(-(-k // full)):
            sign = rng.choice((-1.0, 1.0), full)
            order = rng.permutation(full)
            g = rng.standard_normal(full)
            length = np.sqrt(rng.chisquare(full, full)) / np.linalg.norm(g)
            z = hadamard(padded * sign)[:, order] * g
            parts.append(hadamard(z) * (length / math.sqrt(full) / self.sigma))
        phase = math.pi * rng.random(k)
        return np.cos(np.hstack(parts)[:, :k] + phase) * math.sqrt(2.0 / self.s)

    def kernel(self) -> kernels.Kernel:
        return kernels.make("gaussian", sigma=self.sigma)

    def cost(self, n: int, nnz: int | None = None) -> float:
        return float(n) * self.s * max(1, (self.d - 1).bit_length())


@dataclass(frozen=True)
class LaplaceMap(FeatureMap):
    """Semigroup kernel of histograms: decaying exponentials of nonnegative inputs with Levy directions."""

    beta: float = 1.0

    def block(self, x: Batch, j: int) -> np.ndarray:
        values = x.val if isinstance(x, Sparse) else x
        if (values < 0).any():
            raise ValueError("inputs must not be negative")
        k = self.width(j)
        w = (self.beta**2 / 2.0) / omega_slice(self.seed, j, self.d, k) ** 2
        return np.exp(-times(x, w)) / math.sqrt(self.s)

    def kernel(self) -> kernels.Kernel:
        return kernels.make("semigroup", beta=self.beta)


@dataclass(frozen=True)
class TensorSketchMap(FeatureMap):
    """Polynomial kernel by count sketches multiplied in the frequency domain; each block has a sketch of its own."""

    degree: int = 2
    gamma: float = 1.0
    offset: float = 1.0

    def block(self, x: Batch, j: int) -> np.ndarray:
        k = self.width(j)
        rng = generator(self.seed, j)
        product = np.ones((x.shape[0], k // 2 + 1), complex)
        for _ in range(self.degree):
            bucket, sign = rng.integers(0, k, self.d + 1), rng.choice((-1.0, 1.0), self.d + 1)
            sketch = np.zeros((self.d, k))
            sketch[np.arange(self.d), bucket[: self.d]] = sign[: self.d] * math.sqrt(self.gamma)
            z = times(x, sketch)
            z[:, bucket[-1]] += sign[-1] * math.sqrt(self.offset)
            product *= np.fft.rfft(z, axis=1)
        return np.fft.irfft(product, k, axis=1) * math.sqrt(k / self.s)

    def kernel(self) -> kernels.Kernel:
        return kernels.make("polynomial", degree=self.degree, gamma=self.gamma, offset=self.offset)

    def cost(self, n: int, nnz: int | None = None) -> float:
        k = max(self.width(0), 2)
        return self.degree * self.col_blocks * ((nnz if nnz is not None else n * self.d) + n * k * math.log2(k))


@dataclass(frozen=True)
class IdentityMap(FeatureMap):
    """The inputs themselves, cut in slices: a linear model through the same solver."""

    def block(self, x: Batch, j: int) -> np.ndarray:
        b = self.bounds()
        return np.array(dense(x)[:, b[j] : b[j + 1]], float)

    def kernel(self) -> kernels.Kernel:
        return kernels.make("linear")


def identity_map(d: int, col_blocks: int = 1) -> IdentityMap:
    return IdentityMap(d, d, col_blocks)


@dataclass(frozen=True)
class Concatenated(FeatureMap):
    """Independent maps side by side, each weighted by the root of its share of the features.

    inner is a map of the same kind; block j is inner with s_j features, one block and a seed of its own.
    """

    inner: FeatureMap | None = None

    def part(self, j: int) -> FeatureMap:
        values = {k: getattr(self.inner, k) for k in self.inner.__dataclass_fields__}
        return type(self.inner)(**values | {"s": self.width(j), "col_blocks": 1, "seed": self.seed * 1_000_003 + j})

    def block(self, x: Batch, j: int) -> np.ndarray:
        return self.part(j).block(x, 0) * math.sqrt(self.width(j) / self.s)

    def kernel(self) -> kernels.Kernel:
        return self.inner.kernel()


def kernel_error(x: np.ndarray, fmap: FeatureMap) -> dict[str, float]:
    """How far inner products of features lie from the kernel, over all pairs of the sample's rows."""
    z = fmap.features(x)
    gap = np.abs(z @ z.T - fmap.kernel()(dense(x), dense(x)))
    return {"max": float(gap.max()), "mean": float(gap.mean()), "frobenius": float(np.sqrt((gap**2).sum()))}
