"""Models over streams: scoring, late labels, running standardization, replays, refresh."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from kernelblocks.admm.engine import Model, Run, predict, solve
from kernelblocks.functions.featuremaps import FeatureMap


def score_stream(stream: DataFrame, model: Model) -> DataFrame:
    """The same narrow pass as for a table; every column goes through."""
    return predict(stream, model)


def without_replays(stream: DataFrame, keys: list[str], late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys) if stream.isStreaming else stream.dropDuplicates(keys)


def with_customer(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream and table: an event with the market segment of its user, where there is one."""
    side = customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return events.join(side, "user_id", "left")


def with_labels(predictions: DataFrame, labels: DataFrame, wait: str = "1 hour") -> DataFrame:
    """Stream and stream: a prediction with the label that arrives within the wait; state older than that is dropped."""
    p = predictions.withWatermark("ts", wait).alias("p")
    q = labels.withColumnRenamed("ts", "label_ts").withColumnRenamed("row_id", "label_row_id").withWatermark("label_ts", wait).alias("q")
    near = F.expr(f"row_id = label_row_id AND label_ts >= ts AND label_ts <= ts + interval {wait}")
    return p.join(q, near).drop("label_row_id")


class _Running(StatefulProcessor):
    """Count, mean and sum of squared gaps of each user's values so far."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("moments", "n long, mean double, m2 double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, mean, m2 = self.state.get() if self.state.exists() else (0, 0.0, 0.0)
        got = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        out = []
        for event_id, v in zip(got["event_id"], got["value"], strict=True):
            n += 1
            gap = v - mean
            mean += gap / n
            m2 += gap * (v - mean)
            out.append((event_id, key[0], (v - mean) / (m2 / n) ** 0.5 if m2 > 0 else 0.0))
        self.state.update((n, mean, m2))
        yield pd.DataFrame(out, columns=["event_id", "user_id", "z"])

    def close(self) -> None:
        pass


def running_standardize(events: DataFrame) -> DataFrame:
    """(event_id, user_id, z): each value against the user's mean and deviation up to it."""
    return events.groupBy("user_id").transformWithStateInPandas(
        _Running(), outputStructType="event_id long, user_id long, z double", outputMode="Append", timeMode="None"
    )


def refresh(stream: DataFrame, fmap: FeatureMap, folder: str, rounds: int = 5, **options) -> DataStreamWriter:
    """For every batch of examples: the solver goes on from the stored state's consensus over all rows seen so far.

    The rows are kept in the folder; the state's row blocks are made again when rows have come in.
    """

    def on_batch(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={batch_id}")
        run: Run = solve(spark.read.parquet(f"{folder}/rows").drop("batch"), fmap, iters=rounds, **options)
        run.model.save(spark, f"{folder}/model")

    return stream.writeStream.foreachBatch(on_batch)
