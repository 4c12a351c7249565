"""Examples from tables: inputs, planted targets, coding of labels, splits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DIMS = 64


def e(k: int, vector: str = "embedding") -> Column:
    """Coordinate k as a double."""
    return F.element_at(vector, k + 1).cast("double")


def ripple_col() -> Column:
    return F.sin(F.col("l_quantity") / 4) * F.cos(F.lit(40.0) * F.col("l_discount"))


def checker_col() -> Column:
    return F.when((F.col("l_quantity") > 25) != (F.col("l_discount") > 0.05), 1).otherwise(-1)


def cells_col() -> Column:
    """One of 25 cells of a grid on quantity and discount."""
    q = F.least(F.floor((F.col("l_quantity") - 1) / 10), F.lit(4))
    d = F.least(F.floor(F.round(F.col("l_discount") * 100) / 2.2), F.lit(4))
    return (5 * q + d).cast("int")


def charge_col() -> Column:
    return F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))


def standardize(df: DataFrame, cols: list[str], suffix: str = "_z") -> DataFrame:
    """Adds each column less its mean over its deviation; a constant column becomes 0. One aggregate row is broadcast."""
    stats = df.agg(*(F.avg(c).alias(f"_m_{c}") for c in cols), *(F.stddev_pop(c).alias(f"_s_{c}") for c in cols))
    out = df.join(F.broadcast(stats))
    z = {f"{c}{suffix}": F.when(F.col(f"_s_{c}") > 0, (F.col(c) - F.col(f"_m_{c}")) / F.col(f"_s_{c}")).otherwise(F.lit(0.0)) for c in cols}
    return out.withColumns(z).drop(*(f"_m_{c}" for c in cols), *(f"_s_{c}" for c in cols))


def code_labels(df: DataFrame, col: str, classes: list, coding: str = "ovr") -> DataFrame:
    """Adds label (the place of the class) and y: 1 in the column of the class and -1 elsewhere, one column for two classes."""
    place = F.array_position(F.array(*(F.lit(c) for c in classes)), F.col(col)) - 1
    out = df.withColumn("label", place.cast("int"))
    if len(classes) == 2 and coding == "ovr":
        return out.withColumn("y", F.array(F.when(F.col("label") == 1, 1.0).otherwise(-1.0)))
    return out.withColumn("y", F.array(*(F.when(F.col("label") == k, 1.0).otherwise(-1.0) for k in range(len(classes)))))


def binarize(df: DataFrame, label: str, n_classes: int) -> DataFrame:
    """The lower half of the classes against the upper half."""
    return df.withColumn("side", F.when(F.col(label) < n_classes / 2, 1).otherwise(-1))


def is_test(key: str = "row_id", share: int = 5) -> Column:
    """One row in `share` is held out, by a mix of its key."""
    prime = F.lit(2147483647)
    return F.pmod(F.pmod(F.col(key), prime) * 48271 + 11, prime) % share == 0


def split(df: DataFrame, key: str = "row_id") -> tuple[DataFrame, DataFrame]:
    return df.where(~is_test(key)), df.where(is_test(key))


def embedding_task(vectors: DataFrame, task: str) -> DataFrame:
    """example(row_id, x, y, label) of xor01, shell01, argmax10 or noise10."""
    base = vectors.select(F.col("vec_id").alias("row_id"), "embedding", F.col("label").alias("noise"))
    if task in ("xor01", "shell01"):
        base = base.withColumn("x", F.array(8 * e(0), 8 * e(1)))
        if task == "xor01":
            side = e(0) * e(1) > 0
        else:
            half = base.agg(F.median(e(0) * e(0) + e(1) * e(1)).alias("_half"))
            base = base.join(F.broadcast(half))
            side = e(0) * e(0) + e(1) * e(1) > F.col("_half")
        coded = base.withColumn("label", F.when(side, 1).otherwise(-1)).withColumn("y", F.array(F.col("label").cast("double")))
    elif task == "argmax10":
        first = F.transform(F.slice("embedding", 1, 10), lambda v: v.cast("double"))
        place = (F.array_position(first, F.array_max(first)) - 1).cast("int")
        coded = code_labels(base.withColumn("x", F.transform(first, lambda v: 8 * v)).withColumn("c", place), "c", list(range(10)))
    elif task == "noise10":
        coded = code_labels(base.withColumn("x", F.transform("embedding", lambda v: v.cast("double"))), "noise", list(range(10)))
    else:
        raise ValueError(task)
    return coded.select("row_id", "x", "y", "label")


LINEITEM_KEY = (
    "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate"
).split()


def lineitem_task(lineitem: DataFrame, task: str) -> DataFrame:
    """example(row_id, x, y, label) of checker, ripple, charge or cells25; row_id is a hash of the whole row."""
    inputs = ["l_quantity", "l_discount"] if task != "charge" else ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    base = lineitem.withColumn("row_id", F.xxhash64(*LINEITEM_KEY))
    if task == "checker":
        base = base.withColumn("label", checker_col())
    elif task == "cells25":
        base = base.withColumn("label", cells_col())
    else:
        base = standardize(base.withColumn("_t", ripple_col() if task == "ripple" else charge_col()), ["_t"], "")
        base = base.withColumn("label", F.col("_t"))
    out = standardize(base, inputs).withColumn("x", F.array(*(F.col(f"{c}_z") for c in inputs)))
    if task == "cells25":
        out = code_labels(out, "label", list(range(25)))
    else:
        out = out.withColumn("y", F.array(F.col("label").cast("double")))
    return out.select("row_id", "x", "y", "label")


def trigram_totals(docs: DataFrame, by: str, text: str) -> DataFrame:
    """(by, gram, n): how often each character trigram stands in the lower-case texts of a group.

    Signs are code points; a text is cut in them once, however long, and counts are added up before the shuffle.
    """
    signs = docs.select(by, F.expr(f"regexp_extract_all(lower(coalesce(`{text}`, '')), '(?s).', 0)").alias("c"))
    grams = F.expr("transform(slice(c, 1, greatest(size(c) - 2, 0)), (x, i) -> concat(x, c[i + 1], c[i + 2]))")
    return signs.select(by, F.explode(grams).alias("gram")).groupBy(by, "gram").agg(F.count("*").alias("n"))


#: A task makes so many texts' examples at once.
TEXT_ROWS = 256


def text_task(docs: DataFrame, key: str, text: str, target: str, classes: list, buckets: int = 256) -> DataFrame:
    """Sparse example: shares of hashed character trigrams over the whole text, scaled to unit length, in one pass."""
    from collections import Counter
    from collections.abc import Iterator

    import numpy as np
    import pyarrow as pa
    import zlib

    coded = code_labels(docs, target, classes).select(F.col(key).alias("row_id"), F.lower(F.coalesce(text, F.lit(""))).alias("t"), "y", "label")
    schema = "row_id long, x struct<size:int,idx:array<int>,val:array<double>>, y array<double>, label int"

    def example(b: pa.RecordBatch) -> pa.RecordBatch:
        idx, val = [np.zeros(0, np.int32)], [np.zeros(0)]
        for text in b.column(1):
            t = text.as_py()
            counts: dict[int, int] = {}
            for g, c in Counter(map("".join, zip(t, t[1:], t[2:], strict=False))).items():
                k = zlib.crc32(g.encode("utf-8", "surrogatepass")) % buckets
                counts[k] = counts.get(k, 0) + c
            keys = sorted(counts)
            v = np.array([counts[k] for k in keys], float)
            idx.append(np.array(keys, np.int32))
            val.append(v / max(np.sqrt((v * v).sum()), 1e-300))
        at = pa.array(np.cumsum([len(k) for k in idx]), pa.int32())
        x = pa.StructArray.from_arrays(
            [pa.array([buckets] * b.num_rows, pa.int32()), pa.ListArray.from_arrays(at, pa.array(np.concatenate(idx))), pa.ListArray.from_arrays(at, pa.array(np.concatenate(val)))],
            names=["size", "idx", "val"],
        )
        return pa.RecordBatch.from_arrays([b.column(0), x, b.column(2), b.column(3)], names=["row_id", "x", "y", "label"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, TEXT_ROWS):
                yield example(b.slice(k, TEXT_ROWS))

    return coded.mapInArrow(run, schema)


def densified(df: DataFrame) -> DataFrame:
    """Sparse inputs as plain arrays."""
    full = "transform(sequence(0, x.size - 1), k -> coalesce(element_at(map_from_arrays(x.idx, x.val), cast(k AS int)), 0D))"
    return df.withColumn("x", F.expr(full))
