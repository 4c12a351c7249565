"""The smallest whole run: planted exclusive-or on embeddings, hinge loss, Fourier features, two by two blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from kernelblocks.admm.engine import predict, solve
from kernelblocks.functions.featuremaps import FourierMap
from kernelblocks.operators.prep import embedding_task, split
from kernelblocks.sources.tables import table


def flagship(spark: SparkSession, sf_dir: str, iters: int = 30) -> DataFrame:
    """(vec_id, label, pred, margin) of every row, after training on the rows that aren't held out."""
    ex = embedding_task(table(spark, sf_dir, "embeddings"), "xor01")
    train, _ = split(ex)
    run = solve(train, FourierMap(2, 128, 2, seed=1, sigma=1.0), "hinge", "ridge", 1e-3, rows=2, iters=iters, checkpoint_every=10)
    scored = predict(ex.select("row_id", "x", "label"), run.model)
    return scored.selectExpr("row_id AS vec_id", "label", "pred", "margin")
