"""As-of and range joins without a nested loop."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def last_before(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with the value of the latest row of right of the same key at or before its time; of a tie the largest value.

    Both sides go through one window over the key, so no pair of rows is formed.
    """
    names = left.columns
    one = left.select(*names, F.lit(1).alias("_kb_side"), F.lit(None).cast(right.schema[value].dataType).alias("_kb_value"))
    two = right.select(
        *(F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names), F.lit(0).alias("_kb_side"), F.col(value).alias("_kb_value")
    )
    w = Window.partitionBy(key).orderBy(at, "_kb_side", "_kb_value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = one.unionByName(two).withColumn(value, F.last("_kb_value", ignorenulls=True).over(w))
    return seen.where("_kb_side = 1").select(*names, value)


def range_join(left: DataFrame, right: DataFrame, key: str, at: str, low: str, high: str, bin_seconds: int) -> DataFrame:
    """Pairs of equal key with low <= at < high; both sides are dealt by time bin, intervals once to each bin they touch."""
    def bin_of(c: str):
        return F.floor(F.unix_timestamp(c) / bin_seconds)

    a = left.withColumn("_kb_bin", bin_of(at))
    b = right.withColumn("_kb_bin", F.explode(F.sequence(bin_of(low), bin_of(high))))
    return a.join(b, [key, "_kb_bin"]).where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_kb_bin")
