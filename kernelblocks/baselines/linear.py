"""Linear solvers on stored features, and averaging of models fitted by partition."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.admm.engine import Model
from kernelblocks.admm.tiled import _at_most
from kernelblocks.functions.featuremaps import FeatureMap
from kernelblocks.functions.prox import loss_of
from kernelblocks.plans.blocks import _binaries, is_sparse, pack, unpack_batch, unpack_rows

#: What the features of one stored tile may take, and how many tiles a task has at once.
TILE_BYTES, TILES_AT_ONCE = 4 << 20, 4


def materialize(df: DataFrame, fmap: FeatureMap) -> DataFrame:
    """(row_id, z, y): the features stored as rows, which the block solver never does."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            z = fmap.features(unpack_rows(b.column(1))) if b.num_rows else np.zeros((0, fmap.s))
            offsets = np.arange(0, z.size + 1, fmap.s).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, z.ravel()), b.column(2)], names=["row_id", "z", "y"])

    src = df.select(F.col("row_id").cast("long"), "x", F.col("y").cast("array<double>").alias("y"))
    return src.mapInArrow(run, "row_id long, z array<double>, y array<double>")


def stored_tiles(df: DataFrame, fmap: FeatureMap) -> DataFrame:
    """(z, y, counts): the features stored as packed tiles of rows. Plain rows of a batch that are alike in x and y are one with a count."""
    rows, sparse = max(64, TILE_BYTES // (8 * fmap.s)), is_sparse(df)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            step = rows if sparse else max(1, b.num_rows)
            for k in range(0, b.num_rows, step):
                n, d, raw, y, counts = _binaries(pa.Table.from_batches([b.slice(k, step)]))
                x, y = unpack_batch(raw, d), np.frombuffer(y, "<f8").reshape(n, -1)
                many = np.frombuffer(counts, "<f8") if counts is not None else None
                for at in range(0, n, rows):
                    z = fmap.features(x if sparse else x[at : at + rows])
                    own = many[at : at + rows].tobytes() if many is not None else None
                    cols = [z.astype("<f8").tobytes()], [y[at : at + rows].tobytes()], [own]
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in cols], names=["z", "y", "counts"])

    return df.select("x", F.col("y").cast("array<double>").alias("y")).mapInArrow(run, "z binary, y binary, counts binary")


def _gradient(stored: DataFrame, w: np.ndarray, loss: str, lam: float) -> tuple[float, np.ndarray]:
    sent = stored.sparkSession.sparkContext.broadcast(w)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, f, value, g, n = sent.value, loss_of(loss), 0.0, np.zeros_like(sent.value), 0.0
        for b in batches:
            for r in range(b.num_rows):
                z = np.frombuffer(b.column(0)[r].as_py(), "<f8").reshape(-1, len(w))
                y = np.frombuffer(b.column(1)[r].as_py(), "<f8").reshape(len(z), -1)
                raw, o = b.column(2)[r].as_py(), z @ w
                slope = f.slope(o, y)
                if raw is None:
                    value, n = value + f.value(o, y), n + len(z)
                else:
                    many = np.frombuffer(raw, "<f8")
                    value += sum(c * f.value(o[many == c], y[many == c]) for c in np.unique(many))
                    slope, n = slope * many[:, None], n + many.sum()
                g += z.T @ slope
        yield pa.RecordBatch.from_arrays([pa.array([float(value)]), pa.array([int(n)]), pa.array([g.tobytes()], pa.binary())], names=["value", "n", "g"])

    with _at_most(stored.sparkSession, TILES_AT_ONCE):
        got = stored.mapInArrow(part, "value double, n long, g binary").collect()
    n = max(1, sum(r["n"] for r in got))
    g = sum(np.frombuffer(bytes(r["g"]), "<f8") for r in got).reshape(w.shape)
    return sum(r["value"] for r in got) / n + lam * float((w * w).sum()), g / n + 2 * lam * w


def materialized_linear(df: DataFrame, fmap: FeatureMap, loss: str = "hinge", lam: float = 1e-3, optimizer: str = "lbfgs", iters: int = 60, m: int = 1, classes: list | None = None) -> tuple[Model, list[float]]:
    """A linear model on features that are stored first; returns it with the objective of each round.

    optimizer: "sgd" averages decreasing subgradient steps, "lbfgs" keeps the best of quasi-Newton steps,
    "mllib" is the library's own linear support vector classifier (two classes).
    """
    stored = (materialize if optimizer == "mllib" else stored_tiles)(df, fmap).persist()
    stored.count()  # made here: the rounds' plans give Python few rows at once
    bounds = fmap.bounds()

    def model(w: np.ndarray) -> Model:
        return Model(fmap, [w[a:b] for a, b in zip(bounds, bounds[1:], strict=False)], "ovr", classes)

    try:
        if optimizer == "mllib":
            from pyspark.ml.classification import LinearSVC
            from pyspark.ml.functions import array_to_vector

            rows = stored.select(array_to_vector("z").alias("features"), (F.element_at("y", 1) > 0).cast("double").alias("label"))
            fit = LinearSVC(maxIter=iters, regParam=2 * lam, fitIntercept=False, standardization=False).fit(rows)
            return model(np.array(fit.coefficients)[:, None]), list(fit.summary().objectiveHistory)
        w, history = np.zeros((fmap.s, m)), []
        if optimizer == "sgd":
            mean = w
            for k in range(1, iters + 1):
                value, g = _gradient(stored, w, loss, lam)
                history.append(value)
                w = w - g / (2 * lam * (k + 10))
                mean = mean + (w - mean) * 2.0 / (k + 1)
            return model(mean), history
        value, g = _gradient(stored, w, loss, lam)
        best, pairs = (value, w), []
        for _ in range(iters):
            history.append(value)
            q, seen = g.copy(), []
            for s, t in reversed(pairs):
                a = (s * q).sum() / (s * t).sum()
                q -= a * t
                seen.append(a)
            if pairs:
                q *= (pairs[-1][0] * pairs[-1][1]).sum() / (pairs[-1][1] ** 2).sum()
            for (s, t), a in zip(pairs, reversed(seen), strict=True):
                q += (a - (t * q).sum() / (s * t).sum()) * s
            size = 1.0 if pairs else min(1.0, 1.0 / max(np.linalg.norm(g), 1e-12))
            for _ in range(12):
                v2, g2 = _gradient(stored, w - size * q, loss, lam)
                if v2 <= value - 1e-4 * size * float((g * q).sum()):
                    break
                size /= 2
            s, t = -size * q, g2 - g
            if (s * t).sum() > 1e-12:
                pairs = [*pairs, (s, t)][-10:]
            stalled = value - v2 < 1e-7 * abs(value)
            w, value, g = w + s, v2, g2
            if value < best[0]:
                best = (value, w)
            if stalled:
                break
        return model(best[1]), [*history, best[0]]
    finally:
        stored.unpersist()


def average_ensemble(df: DataFrame, fmap: FeatureMap, lam: float, parts: int, coding: str = "ovr", classes: list | None = None) -> Model:
    """Ridge on the features of each part by itself, and the mean of the parts' models."""

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                n, d = b.column(0)[r].as_py(), b.column(1)[r].as_py()
                z = fmap.features(unpack_batch(b.column(2)[r].as_py(), d))
                y = np.frombuffer(b.column(3)[r].as_py(), "<f8").reshape(n, -1)
                w = np.linalg.solve(z.T @ z + n * lam * np.eye(fmap.s), z.T @ y)
                yield pa.RecordBatch.from_arrays([pa.array([w.shape[1]]), pa.array([w.tobytes()], pa.binary())], names=["m", "w"])

    got = pack(df, parts).select("n", "d", "x", "y").mapInArrow(fit, "m long, w binary").collect()
    w = sum(np.frombuffer(bytes(r["w"]), "<f8").reshape(fmap.s, -1) for r in got) / len(got)
    bounds = fmap.bounds()
    return Model(fmap, [w[a:b] for a, b in zip(bounds, bounds[1:], strict=False)], coding, classes)
