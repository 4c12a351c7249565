"""Measures of runs, predictions and plans."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def accuracy(scored: DataFrame, label: str = "label", pred: str = "pred") -> float:
    return scored.agg(F.avg((F.col(pred) == F.col(label)).cast("double"))).first()[0] or 0.0


def rmse(scored: DataFrame, label: str = "label", pred: str = "pred") -> float:
    return scored.agg(F.sqrt(F.avg((F.col(pred) - F.col(label)) ** 2))).first()[0]


def r_squared(scored: DataFrame, label: str = "label", pred: str = "pred") -> float:
    row = scored.agg(F.avg((F.col(pred) - F.col(label)) ** 2), F.var_pop(label)).first()
    return 1.0 - row[0] / row[1]


def confusion(scored: DataFrame, classes: list, label: str = "label", pred: str = "pred") -> DataFrame:
    """A row for each label, a column for each prediction."""
    return scored.groupBy(label).pivot(pred, classes).count().na.fill(0)


def recall_by_class(scored: DataFrame, label: str = "label", pred: str = "pred") -> DataFrame:
    return scored.groupBy(label).agg(F.avg((F.col(pred) == F.col(label)).cast("double")).alias("recall"), F.count("*").alias("n"))


def objective_gap(value: float, optimum: float) -> float:
    return value - optimum


def timed(run: Callable[[], Any]) -> tuple[Any, float]:
    began = time.perf_counter()
    return run(), time.perf_counter() - began


def scaling_table(runs: DataFrame) -> DataFrame:
    """(series, resources, seconds) with speedup over the least resources and the efficiency of it."""
    w = Window.partitionBy("series").orderBy("resources").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    base, first = F.first("seconds").over(w), F.first("resources").over(w)
    return runs.withColumn("speedup", base / F.col("seconds")).withColumn("efficiency", F.col("speedup") / (F.col("resources") / first))


def weak_table(runs: DataFrame) -> DataFrame:
    """(series, resources, seconds) with the time over that of the least resources; 1 is ideal."""
    w = Window.partitionBy("series").orderBy("resources").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return runs.withColumn("ratio", F.col("seconds") / F.first("seconds").over(w))


def step_profile(times: DataFrame, whole: str = "round") -> DataFrame:
    """(row_block, step, sec) by step: seconds of a process in sum, least, most and on average, and the share of the whole.

    Steps of threads overlap, so shares can add up to more than 100.
    """
    each = times.groupBy("step", "row_block").agg(F.sum("sec").alias("sec"))
    steps = each.groupBy("step").agg(F.min("sec").alias("min_sec"), F.max("sec").alias("max_sec"), F.avg("sec").alias("avg_sec"))
    total = steps.where(F.col("step") == whole).select(F.col("max_sec").alias("whole_sec"))
    return steps.join(F.broadcast(total), how="left").withColumn("share", 100.0 * F.col("max_sec") / F.col("whole_sec")).drop("whole_sec")
