"""Squared-loss baselines with closed forms: exact kernel ridge, linear ridge, ridge on random features."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.admm.engine import Model
from kernelblocks.functions.featuremaps import FeatureMap, IdentityMap, dense, identity_map
from kernelblocks.functions.kernels import Kernel
from kernelblocks.plans.blocks import unpack_rows

#: Exact solves by Cholesky take so many rows; beyond, the same system goes to conjugate gradients over rows of K.
MAX_DIRECT_ROWS = 5_000
#: Kernel values that a task holds at once.
STRIP_CELLS = 1 << 21
MAX_NORMAL_COLUMNS = 8_192


@dataclass
class DualModel:
    """f(x) = sum_i alpha_i k(x_i, x)."""

    support: np.ndarray
    alpha: np.ndarray
    kernel: Kernel
    n_support: int = 0
    bias: float = 0.0
    coding: str = "ovr"
    rounds: int = 0

    def decide(self, x: np.ndarray) -> np.ndarray:
        strip = max(1, STRIP_CELLS // max(1, len(self.support)))
        parts = [self.kernel(x[at : at + strip], self.support) @ self.alpha for at in range(0, len(x), strip)]
        return (np.vstack(parts) if parts else np.zeros((0, self.alpha.shape[1]))) + self.bias


def local_rows(df: DataFrame, limit: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, x, y) of a table whose rows the driver holds, in the order of row_id; more rows than a limit are an error."""
    n = df.count() if limit is not None else 0
    if limit is not None and n > limit:
        raise ValueError(f"{n} rows; this exact method takes {limit} at most")
    rows = df.select("row_id", F.col("x").cast("array<double>").alias("x"), F.col("y").cast("array<double>").alias("y")).toArrow()
    ids = rows.column("row_id").to_numpy()
    order = np.argsort(ids, kind="stable")
    x, y = (rows.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) for c in ("x", "y"))
    return ids[order], x[order], y[order]


def _pivots(x: np.ndarray, kernel: Kernel, rank: int, tol: float) -> np.ndarray:
    """H with K ~ H H' by pivots of the largest residual, until the residuals' sum is below tol."""
    left = np.array([kernel(x[i : i + 1], x[i : i + 1])[0, 0] for i in range(len(x))])
    h = np.zeros((len(x), min(rank, len(x))))
    for k in range(h.shape[1]):
        i = int(np.argmax(left))
        if left.sum() < tol or left[i] <= 0:
            return h[:, :k]
        h[:, k] = (kernel(x, x[i : i + 1])[:, 0] - h[:, :k] @ h[i, :k]) / np.sqrt(left[i])
        left = np.maximum(left - h[:, k] ** 2, 0.0)
        left[i] = 0.0
    return h


def exact_ridge(df: DataFrame, kernel: Kernel, lam: float, method: str = "cholesky", tol: float = 1e-10, max_iters: int = 500) -> DualModel:
    """(K + n lam I) alpha = Y, by Cholesky on the driver or by conjugate gradients over distributed rows of K.

    Above MAX_DIRECT_ROWS rows it is conjugate gradients in any case. They are preconditioned by a low-rank part of K,
    so that few products with the whole of K are left; each is over all rows.
    """
    _, x, y = local_rows(df, None)
    n = len(x)
    if method == "cholesky" and n <= MAX_DIRECT_ROWS:
        low = np.linalg.cholesky(kernel(x, x) + n * lam * np.eye(n))
        alpha = np.linalg.solve(low.T, np.linalg.solve(low, y))
        return DualModel(x, alpha, kernel, n)
    spark = df.sparkSession
    all_rows = spark.sparkContext.broadcast(x)
    places = spark.range(0, n, 1, min(n, max(1, spark.sparkContext.defaultParallelism)))

    def times(p: np.ndarray) -> np.ndarray:
        sent = spark.sparkContext.broadcast(p)

        def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                i = b.column(0).to_numpy()
                strip = max(1, STRIP_CELLS // n)
                got = np.vstack([kernel(all_rows.value[i[at : at + strip]], all_rows.value) @ sent.value for at in range(0, len(i), strip)])
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in got], pa.binary())], names=["i", "v"])

        rows = places.mapInArrow(part, "i long, v binary").collect()
        out = np.empty_like(p)
        for r in rows:
            out[r["i"]] = np.frombuffer(bytes(r["v"]))
        return out + n * lam * p

    h = _pivots(x, kernel, min(256, n), 1e-2 * n * lam)
    core = np.linalg.inv(n * lam * np.eye(h.shape[1]) + h.T @ h)

    def eased(r: np.ndarray) -> np.ndarray:
        """(H H' + n lam I)^-1 r."""
        return (r - h @ (core @ (h.T @ r))) / (n * lam)

    alpha, residual = np.zeros_like(y), y.copy()
    p = eased(residual)
    size = (residual * p).sum(axis=0)
    rounds = 0
    for rounds in range(1, max_iters + 1):  # noqa: B007
        if np.sqrt((residual**2).sum(axis=0).max()) < tol:
            break
        q = times(p)
        step = size / np.maximum((p * q).sum(axis=0), 1e-300)
        alpha += step * p
        residual -= step * q
        better = eased(residual)
        new = (residual * better).sum(axis=0)
        p = better + (new / np.maximum(size, 1e-300)) * p
        size = new
    return DualModel(x, alpha, kernel, n, rounds=rounds)


def rkhs_norm(alpha: np.ndarray, k: np.ndarray) -> float:
    """Squared norm of the function with these coefficients."""
    return float(np.trace(alpha.T @ k @ alpha))


def predict_dual(df: DataFrame, model: DualModel) -> DataFrame:
    """df with scores, pred and margin; each row meets every support vector (the slow way to predict)."""
    held = df.sparkSession.sparkContext.broadcast(model)
    at = df.columns.index("x")
    names = [*df.columns, "scores", "pred", "margin"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + ", scores array<double>, pred double, margin double"

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for b in batches:
            out = m.decide(dense(unpack_rows(b.column(at)))) if b.num_rows else np.zeros((0, m.alpha.shape[1]))
            if m.coding == "regression":
                pred = margin = out[:, 0]
            elif out.shape[1] == 1:
                pred, margin = np.where(out[:, 0] >= 0, 1.0, -1.0), out[:, 0]
            else:
                pred, margin = np.argmax(out, axis=1).astype(float), out.max(axis=1)
            offsets = np.arange(0, out.size + 1, out.shape[1]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.ListArray.from_arrays(offsets, out.ravel()), pa.array(pred), pa.array(margin)], names=names)

    return df.mapInArrow(score, schema)


def normal_equations(df: DataFrame, fmap: FeatureMap) -> tuple[np.ndarray, np.ndarray, int]:
    """(Z'Z, Z'Y, n): partial sums in each partition, one matrix for each task to add up."""
    if fmap.s > MAX_NORMAL_COLUMNS:
        raise ValueError(f"{fmap.s} features; the normal equations take {MAX_NORMAL_COLUMNS} at most")

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, b, n = np.zeros((fmap.s, fmap.s)), None, 0
        for batch in batches:
            for k in range(0, batch.num_rows, 4096):
                piece = batch.slice(k, 4096)
                z = fmap.features(unpack_rows(piece.column(0)))
                y = piece.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(z), -1)
                g += z.T @ z
                b = z.T @ y if b is None else b + z.T @ y
                n += len(z)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([g.tobytes()], pa.binary()), pa.array([b.tobytes()], pa.binary())], names=["n", "g", "b"])

    parts = df.select("x", "y").mapInArrow(part, "n long, g binary, b binary")
    width = max(1, int(np.sqrt(parts.sparkSession.sparkContext.defaultParallelism)))

    def add(table: pa.Table) -> pa.Table:
        total = {"n": pa.array([sum(table.column("n").to_pylist())])}
        for k in ("g", "b"):
            total[k] = pa.array([sum(np.frombuffer(v, "<f8") for v in table.column(k).to_pylist()).tobytes()], pa.binary())
        return pa.table(total)

    got = parts.withColumn("k", F.spark_partition_id() % width).groupBy("k").applyInArrow(add, "n long, g binary, b binary").collect()
    if not got:
        raise ValueError("there are no examples")
    g = sum(np.frombuffer(bytes(r["g"]), "<f8") for r in got).reshape(fmap.s, fmap.s)
    b = sum(np.frombuffer(bytes(r["b"]), "<f8") for r in got).reshape(fmap.s, -1)
    return g, b, sum(r["n"] for r in got)


def feature_ridge(df: DataFrame, fmap: FeatureMap, lam: float, coding: str = "ovr", classes: list | None = None) -> Model:
    """Ridge on random features: the exact optimum of the block solver with squared loss."""
    g, b, n = normal_equations(df, fmap)
    w = np.linalg.solve(g + n * lam * np.eye(fmap.s), b)
    bounds = fmap.bounds()
    return Model(fmap, [w[lo:hi] for lo, hi in zip(bounds, bounds[1:], strict=False)], coding, classes)


def linear_ridge(df: DataFrame, lam: float, d: int, coding: str = "ovr", classes: list | None = None) -> Model:
    fmap: IdentityMap = identity_map(d)
    return feature_ridge(df, fmap, lam, coding, classes)
