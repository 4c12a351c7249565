"""Kernel functions on batches of rows, and their Gram matrix over a DataFrame."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kernelblocks.storage import ensure_checkpoint_dir


def squared_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None, :] - 2.0 * x @ y.T, 0.0)


def gaussian(x: np.ndarray, y: np.ndarray, sigma: float) -> np.ndarray:
    return np.exp(-squared_distances(x, y) / (2.0 * sigma * sigma))


def laplacian(x: np.ndarray, y: np.ndarray, width: float) -> np.ndarray:
    return np.exp(-np.abs(x[:, None, :] - y[None, :, :]).sum(2) / width)


def matern(x: np.ndarray, y: np.ndarray, width: float, nu: float) -> np.ndarray:
    """Smoothness 1/2, 3/2 or 5/2."""
    r = np.sqrt(squared_distances(x, y)) * math.sqrt(2 * nu) / width
    poly = {0.5: 1.0, 1.5: 1.0 + r, 2.5: 1.0 + r + r * r / 3.0}
    if nu not in poly:
        raise ValueError("nu must be 0.5, 1.5 or 2.5")
    return poly[nu] * np.exp(-r)


def semigroup(x: np.ndarray, y: np.ndarray, beta: float) -> np.ndarray:
    if (x < 0).any() or (y < 0).any():
        raise ValueError("inputs must not be negative")
    return np.exp(-beta * np.sqrt(x[:, None, :] + y[None, :, :]).sum(2))


def polynomial(x: np.ndarray, y: np.ndarray, degree: int, gamma: float, offset: float) -> np.ndarray:
    return (gamma * (x @ y.T) + offset) ** degree


def linear(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return x @ y.T


@dataclass(frozen=True)
class Kernel:
    """A kernel with its parameters, picklable for tasks."""

    name: str
    params: tuple[tuple[str, float], ...] = ()

    def __call__(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return KERNELS[self.name](x, y, **dict(self.params))


KERNELS: dict[str, Callable[..., np.ndarray]] = {
    f.__name__: f for f in (gaussian, laplacian, matern, semigroup, polynomial, linear)
}


def make(name: str, **params: float) -> Kernel:
    return Kernel(name, tuple(sorted(params.items())))


def squared_distance_col(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v)


def dot_col(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)


def gaussian_col(a: Column, b: Column, sigma: float) -> Column:
    return F.exp(-squared_distance_col(a, b) / (2.0 * sigma * sigma))


#: Rows of one side whose kernel values with a block are made at once.
STRIP_ROWS = 512


def _pairs_of(df: DataFrame, block_rows: int, work, schema: str) -> DataFrame:
    """The tables of work(ids, x, ids, x, alone) on every pair of blocks of rows, once, and on every block with itself (alone).

    A block is packed once, squeezed, in a partition of its own, and kept in the checkpoint folder; the task of a pair
    reads its two blocks there, so that the disk holds each row once, however many pairs there are. A task holds two
    blocks and what work gives at once.
    """
    from kernelblocks.plans.blocks import loosened, squeezed

    ensure_checkpoint_dir(df.sparkSession)
    blocks = max(1, -(-df.count() // block_rows))
    rows = df.select("row_id", F.col("x").cast("array<double>").alias("x")).withColumn("b", F.pmod(F.xxhash64("row_id"), F.lit(blocks)).cast("int"))

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [b for b in batches if b.num_rows]
        if own:
            table = pa.Table.from_batches(own)
            table = table.take(pa.array(np.argsort(table.column("row_id").to_numpy(), kind="stable")))
            x = table.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False)
            ids = table.column("row_id").to_numpy().astype("<i8")
            yield pa.RecordBatch.from_arrays(
                [own[0].column("b").slice(0, 1), pa.array([ids.tobytes()], pa.binary()), pa.array([squeezed(x.astype("<f8").tobytes())], pa.binary())], names=["b", "ids", "x"]
            )

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                lo, hi, *raw = (column[r].as_py() for column in batch.columns)
                i, j = (np.frombuffer(v, "<i8") for v in raw[:2])
                xi, xj = (np.frombuffer(loosened(v), "<f8").reshape(len(ids), -1) for v, ids in zip(raw[2:], (i, j), strict=True))
                for made in work(i, xi, j, xj, lo == hi):
                    yield from made.to_batches()

    each = rows.repartitionById(blocks, "b").mapInArrow(packed, "b int, ids binary, x binary").checkpoint()
    lo, hi = each.alias("lo"), each.alias("hi").hint("shuffle_replicate_nl")
    pairs = lo.join(hi, F.col("lo.b") <= F.col("hi.b"))
    return pairs.select("lo.b", "hi.b", "lo.ids", "hi.ids", "lo.x", "hi.x").toDF("lo", "hi", "i", "j", "xi", "xj").mapInArrow(pair, schema)


def gram(df: DataFrame, kernel: Kernel, block_rows: int = 2048) -> DataFrame:
    """(i, j, k) for all pairs i <= j of row_id, strip by strip: a baseline whose rows grow with the square of the table."""

    def work(i, xi, j, xj, alone):
        for at in range(0, len(i), STRIP_ROWS):
            part = slice(at, at + STRIP_ROWS)
            k = kernel(xi[part], xj)
            a, b = np.broadcast_to(i[part, None], k.shape), np.broadcast_to(j[None, :], k.shape)
            use = a <= b if alone else np.ones_like(k, bool)
            a, b = a[use], b[use]
            yield pa.table({"i": np.minimum(a, b), "j": np.maximum(a, b), "k": k[use]})

    return _pairs_of(df, block_rows, work, "i long, j long, k double")


def gaps(df: DataFrame, kernel: Kernel, features, block_rows: int = 4096) -> DataFrame:
    """(pairs, most, total) by pair of blocks: |inner product of features - kernel| over all pairs i <= j, none of them kept."""

    def work(i, xi, j, xj, alone):
        zi, zj = features(xi), features(xj)
        pairs, most, total = 0, 0.0, 0.0
        for at in range(0, len(i), STRIP_ROWS):
            part = slice(at, at + STRIP_ROWS)
            gap = np.abs(zi[part] @ zj.T - kernel(xi[part], xj))
            gap = gap[i[part, None] <= j[None, :]] if alone else gap.ravel()
            pairs, most, total = pairs + gap.size, max(most, float(gap.max(initial=0.0))), total + float(gap.sum())
        yield pa.table({"pairs": [pairs], "most": [most], "total": [total]})

    return _pairs_of(df, block_rows, work, "pairs long, most double, total double")


def weighted_sums(df: DataFrame, kernel: Kernel, weight, block_rows: int = 4096) -> DataFrame:
    """(row_id, score): for each row the sum over all rows of weight(row_id) times the kernel with them."""

    def work(i, xi, j, xj, alone):
        to_i, to_j = np.zeros(len(i)), np.zeros(len(j))
        for at in range(0, len(i), STRIP_ROWS):
            part = slice(at, at + STRIP_ROWS)
            k = kernel(xi[part], xj)
            to_i[part] = k @ weight(j)
            if not alone:
                to_j += weight(i[part]) @ k
        yield pa.table({"row_id": i if alone else np.concatenate((i, j)), "score": to_i if alone else np.concatenate((to_i, to_j))})

    return _pairs_of(df, block_rows, work, "row_id long, score double").groupBy("row_id").agg(F.sum("score").alias("score"))


def nearest(df: DataFrame, kernel: Kernel, count: int, digits: int = 6, block_rows: int = 4096) -> DataFrame:
    """(i, j, k): candidates for the count largest kernel values of each row with another, k rounded, ties by j.

    A pair of blocks gives its own best for each row alone, so rows x blocks x count candidates are left of rows squared.
    """

    def best(ids, x, others, y):
        out = []
        for at in range(0, len(ids), STRIP_ROWS):
            own = ids[at : at + STRIP_ROWS]
            shown = np.round(kernel(x[at : at + STRIP_ROWS], y), digits)
            shown[own[:, None] == others[None, :]] = -np.inf
            if len(others) > count:
                least = np.partition(shown, len(others) - count, axis=1)[:, len(others) - count, None]
            else:
                least = np.full((len(own), 1), -np.inf)
            r, c = np.nonzero((shown >= least) & np.isfinite(shown))
            k = shown[r, c]
            order = np.lexsort((others[c], -k, r))
            r, c, k = r[order], c[order], k[order]
            place = np.arange(len(r)) - np.searchsorted(r, r)
            use = place < count
            out.append((own[r[use]], others[c[use]], k[use]))
        return out

    def work(i, xi, j, xj, alone):
        out = best(i, xi, j, xj) + ([] if alone else best(j, xj, i, xi))
        yield pa.table({name: np.concatenate([o[at] for o in out]) for at, name in enumerate("ijk")})

    return _pairs_of(df, block_rows, work, "i long, j long, k double")
