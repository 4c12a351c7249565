"""Keys that hold too many rows for one task, dealt in blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.llm.runtime import cut

#: Split keys are few; beyond so many their list is joined by a shuffle and not broadcast.
BROADCAST_ROWS = 200_000


def in_blocks(rows: DataFrame, sizes: DataFrame, keys: list[str], member: str, block_rows: int) -> DataFrame:
    """rows with (lo, hi, block): keys of more than block_rows rows (n_rows of sizes) are dealt in blocks by member.

    Rows of such a key meet in one task for each pair of blocks, so all pairs of rows still meet.
    """
    large = sizes.where(F.col("n_rows") > block_rows).select(
        *keys, F.ceil(F.col("n_rows") / block_rows).cast("int").alias("_kb_blocks")
    )
    large = cut(large)
    if large.count() <= BROADCAST_ROWS:
        large = F.broadcast(large)
    dealt = rows.join(large, keys, "left").withColumn(
        "block",
        F.when(F.col("_kb_blocks").isNull(), 0).otherwise(F.pmod(F.xxhash64(member), F.col("_kb_blocks")).cast("int")),
    )
    others = F.when(F.col("_kb_blocks").isNull(), F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("_kb_blocks") - 1))
    return dealt.withColumn("_kb_other", F.explode(others)).select(
        *rows.columns,
        "block",
        F.least("block", "_kb_other").alias("lo"),
        F.greatest("block", "_kb_other").alias("hi"),
    )
