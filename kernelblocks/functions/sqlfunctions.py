"""Functions for SQL: a model's margin, and tables of blocks and features."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


@udtf(returnType="block int, low bigint, size bigint")
class BlockBounds:
    """kb_block_bounds(n, parts): a row for each block."""

    def eval(self, n: int, parts: int) -> Iterator[tuple[int, int, int]]:
        from kernelblocks.plans.blockplan import block_bounds

        b = block_bounds(n, parts)
        for k in range(parts):
            yield k, int(b[k]), int(b[k + 1] - b[k])


@udtf(returnType="feature int, value double")
class FeatureBlock:
    """kb_feature_block(x, s, sigma, seed, block, blocks): the Fourier features of one row."""

    def eval(self, x: list, s: int, sigma: float, seed: int, block: int, blocks: int) -> Iterator[tuple[int, float]]:
        from kernelblocks.functions.featuremaps import FourierMap

        f = FourierMap(len(x), s, blocks, seed, sigma=float(sigma), generator="portable")
        low = int(f.bounds()[block])
        for k, v in enumerate(f.block(np.array([x], float), block)[0]):
            yield low + k, float(v)


@pandas_udf("array<double>")
def vector_sum(v: pd.Series) -> list:
    """Sum of arrays of equal length, as an aggregate."""
    rows = [np.asarray(x, float) for x in v if x is not None]
    return np.sum(rows, axis=0).tolist() if rows else []


def register(spark: SparkSession) -> None:
    spark.udtf.register("kb_block_bounds", BlockBounds)
    spark.udtf.register("kb_feature_block", FeatureBlock)


def register_model(spark: SparkSession, model, name: str = "predict_margin") -> None:
    """SELECT predict_margin(x): the margin of the model for each row of inputs."""
    held = spark.sparkContext.broadcast(model)

    @pandas_udf("double")
    def margin(x: pd.Series) -> pd.Series:
        from kernelblocks.admm.engine import _decide

        m = held.value
        if not len(x):
            return pd.Series([], dtype=float)
        rows = np.stack([np.asarray(v, float) for v in x])
        scores = sum(m.fmap.block(rows, j) @ w for j, w in enumerate(m.weights))
        return pd.Series(_decide(scores, m.coding, m.classes)[1])

    spark.udf.register(name, margin)


__all__ = ["register", "register_model", "vector_sum"]
