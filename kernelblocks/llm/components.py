"""Connected components of a distributed edge list by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.llm.runtime import cut

MAX_ROUNDS = 60


def _hook(edges: DataFrame, both_ways: bool) -> DataFrame:
    """Ties the neighbours of every node to the least of them.

    both_ways: all neighbours count and the larger ones move (the large star);
    else only the smaller neighbours count and the node moves too (the small star).
    """
    if both_ways:
        seen = edges.union(edges.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
    else:
        seen = edges
    seen = seen.select(F.col("hi").alias("u"), F.col("lo").alias("v"))
    least = seen.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    tied = seen.join(least, "u")
    if both_ways:
        moved = tied.where("v > u").select(F.col("v").alias("hi"), F.col("m").alias("lo"))
    else:
        moved = tied.select(F.col("v").alias("hi"), F.col("m").alias("lo")).union(
            least.select(F.col("u").alias("hi"), F.col("m").alias("lo"))
        )
    return moved.where("hi > lo").distinct()


def connected_components(edges: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root): every node of an edge with the least node that it reaches.

    Rows stay distributed throughout; only a count and a checksum of a round come to the driver.
    Self loops and repeated edges do no harm; nodes without an edge don't appear.
    """
    e = cut(
        edges.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where("hi > lo").distinct()
    )

    def seal(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.bit_xor(F.xxhash64("hi", "lo")), F.sum(F.col("lo") % 1000003)).first())

    state = seal(e)
    for _ in range(MAX_ROUNDS):
        if not state[0]:
            break
        e = cut(_hook(_hook(e, True), False))
        before, state = state, seal(e)
        if state == before:
            break
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    return e.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(
        e.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct()
    )
