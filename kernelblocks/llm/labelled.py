"""A bounded sample of labelled documents, as sparse rows on the driver."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.llm.runtime import id_and_text

#: At most so many labelled documents train a classifier; they are those of the least hash of their id.
SAMPLE_ROWS = 6000


def labelled_rows(
    docs: DataFrame,
    labels: DataFrame,
    grade: F.Column,
    sparse: Callable[[list[str]], list[tuple[np.ndarray, np.ndarray]]],
    sample_rows: int = SAMPLE_ROWS,
) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """(sparse rows, grades) of a bounded sample, in an order that depends on ids alone.

    labels without an id or a grade don't count; of several labels of one id the least grade does, of several texts of
    one id the least, so that never more than sample_rows rows come to the driver.
    """
    chosen = (
        labels.select("doc_id", grade.cast("int").alias("grade"))
        .where("doc_id is not null and grade is not null")
        .groupBy("doc_id")
        .agg(F.min("grade").alias("grade"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(sample_rows)
    )
    picked = id_and_text(docs).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "grade").agg(F.min("text").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = sparse(b.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0).cast(pa.int64()),
                    b.column(1).cast(pa.int32()),
                    pa.array([i.astype(np.int32).tobytes() for i, _ in rows], pa.binary()),
                    pa.array([v.astype(np.float32).tobytes() for _, v in rows], pa.binary()),
                ],
                names=["doc_id", "grade", "idx", "val"],
            )

    got = picked.mapInArrow(run, "doc_id long, grade int, idx binary, val binary").toPandas()
    got = got.sort_values(["doc_id", "grade", "idx"], kind="stable").iloc[:sample_rows]
    rows = [
        (np.frombuffer(i, np.int32), np.frombuffer(v, np.float32)) for i, v in zip(got["idx"], got["val"], strict=True)
    ]
    return rows, got["grade"].to_numpy(np.int64)
