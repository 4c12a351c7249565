"""Where intermediate results are kept."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The cluster's shared folder; a temporary one only where none is set and all runs on one machine, as in tests."""
    context = spark.sparkContext
    if context.getCheckpointDir() is not None:
        return
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder is None and not context.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="kb-checkpoint-"))


def kept_flat(df: DataFrame, on_disk: bool = False) -> tuple[DataFrame, Callable[[], None]]:
    """(df kept in memory or on disk, a call that lets it go), with a plan that doesn't hold the plan of df.

    Frames that are persisted one upon the other carry the plans of all before them, each printed again for
    every query; in a loop that grows without bound. Here the rows are kept as the JVM has them, and the new
    plan scans them. Lineage for lost executors stays, as with persist().

    on_disk is for partitions that may outgrow the memory of a task: Spark fills its storage with such a partition
    before it turns to the disk, in chunks that take twice their bytes of the heap, and holds them while it writes.
    """
    spark = df.sparkSession
    rows = df._jdf.toJavaRDD()
    rows.persist(spark.sparkContext._getJavaStorageLevel(StorageLevel.DISK_ONLY if on_disk else StorageLevel.MEMORY_AND_DISK))
    flat = DataFrame(spark._jsparkSession.createDataFrame(rows, df._jdf.schema()), spark)
    return flat, lambda: rows.unpersist(False) and None
