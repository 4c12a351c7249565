"""Examples as packed row blocks: one row of binaries for each block, so that a matrix never becomes cells.

example(row_id, x array<double> or struct<size,idx,val>, y array<double>) becomes
packed(row_block, n, d, x, y, ids): row-major little-endian doubles in the order of row_id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.functions.featuremaps import Batch, Sparse

PACKED = "row_block int, n long, d long, x binary, y binary, ids binary"


def is_sparse(df: DataFrame) -> bool:
    return isinstance(df.schema["x"].dataType, T.StructType)


def checked(df: DataFrame) -> DataFrame:
    """Rows with a null input or target stop the job with a message and don't slip through as zeros."""
    x = F.col("x.val") if is_sparse(df) else F.col("x")
    bad = F.exists(x, lambda v: v.isNull() | F.isnan(v)) | F.exists("y", lambda v: v.isNull() | F.isnan(v)) | x.isNull()
    return df.withColumn("x", F.when(F.coalesce(bad, F.lit(True)), F.raise_error(F.lit("an input or target is null or not a number")).cast(df.schema["x"].dataType)).otherwise(F.col("x")))


#: Rows are counted by so many hash buckets where blocks are to be even.
EVEN_BUCKETS = 4096


def even_blocks(examples: DataFrame, rows: int) -> DataFrame:
    """examples with row_block, blocks of sizes that differ by one row at most.

    Rows are numbered by hash bucket and, within one, by id; only the buckets' counts come to the driver.
    """
    dealt = examples.withColumn("_bucket", F.pmod(F.xxhash64("row_id"), F.lit(EVEN_BUCKETS)).cast("int"))
    counts = {r["_bucket"]: r["n"] for r in dealt.groupBy("_bucket").agg(F.count("*").alias("n")).collect()}
    before = np.concatenate(([0], np.cumsum([counts.get(k, 0) for k in range(EVEN_BUCKETS)])))
    order = Window.partitionBy("_bucket").orderBy("row_id", F.xxhash64("x", "y"))
    starts = F.array(*(F.lit(int(v)) for v in before[:-1]))
    size, more = divmod(int(before[-1]), rows)
    at = F.element_at(starts, F.col("_bucket") + 1) + F.row_number().over(order) - 1
    numbered = dealt.withColumn("_at", at)
    # the first blocks hold one row more
    block = F.when(F.col("_at") < more * (size + 1), F.floor(F.col("_at") / (size + 1))).otherwise(more + F.floor((F.col("_at") - more * (size + 1)) / max(size, 1)))
    return numbered.withColumn("row_block", block.cast("int")).drop("_bucket", "_at")


def pack(examples: DataFrame, rows: int) -> DataFrame:
    """One packed row for each row block; the block of a row is a hash of its id, the same in every run.

    A column row_block, where examples has one, decides instead.
    """
    return _packed(examples, rows)


def squeezed(raw: bytes) -> bytes:
    """The same bytes, packed without loss: tables repeat their values, and so do the outputs of equal rows."""
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def loosened(raw: bytes) -> bytes:
    return pa.decompress(raw[8:], int.from_bytes(raw[:8], "little"), codec="zstd", asbytes=True)


TILE = "row_block int, tile long, slot int, n long, d long, x binary, y binary, counts binary"


def pack_tiles(examples: DataFrame, rows: int, tile_rows: int, slots: int) -> DataFrame:
    """Packed tiles of at most tile_rows rows of one row block, made by the tasks that read the rows: no row is moved.

    Row blocks are those of pack. A block's tiles are dealt to so many slots of it; x and y are squeezed. Rows of a tile
    that are alike in x and y, whose outputs are alike in every round, are one of its n rows with a count (plain
    inputs; no counts where most rows differ).
    """
    block = F.col("row_block") if "row_block" in examples.columns else F.pmod(F.xxhash64("row_id"), F.lit(rows))
    x = F.col("x") if is_sparse(examples) else F.col("x").cast("array<double>")
    dealt = checked(examples).select(block.cast("int").alias("row_block"), x.alias("x"), F.col("y").cast("array<double>").alias("y"))
    names = [f.split()[0] for f in TILE.split(", ")]

    def tile(who: int, number: int, table: pa.Table) -> pa.RecordBatch:
        n, d, packed, y, counts = _binaries(table)
        cols = ([who], [number], [who * slots + number % slots], [n], [d], [squeezed(packed)], [squeezed(y)], [None if counts is None else squeezed(counts)])
        kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    def run(batches):
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 32
        waiting: dict[int, list[pa.RecordBatch]] = {}
        for b in batches:
            who = b.column(0).to_numpy()
            for k in np.unique(who).tolist():
                own = b.filter(pa.array(who == k))
                waiting.setdefault(k, []).append(own)
                if sum(p.num_rows for p in waiting[k]) >= tile_rows:
                    whole = pa.Table.from_batches(waiting.pop(k)).combine_chunks()
                    full = whole.num_rows // tile_rows * tile_rows
                    for at in range(0, full, tile_rows):
                        yield tile(k, number, whole.slice(at, tile_rows).combine_chunks())
                        number += 1
                    if full < whole.num_rows:
                        waiting[k] = whole.slice(full).to_batches()
        for k, parts in sorted(waiting.items()):
            yield tile(k, number, pa.Table.from_batches(parts).combine_chunks())
            number += 1

    return dealt.mapInArrow(run, TILE)


def _binaries(table: pa.Table) -> tuple[int, int, bytes, bytes, bytes | None]:
    """(n, d, x, y, counts) of rows of one block; d is negative for sparse rows, counts None where most rows differ."""
    n, xs = table.num_rows, pa.concat_arrays(table.column("x").chunks)
    y = pa.concat_arrays(table.column("y").chunks).flatten().to_numpy(zero_copy_only=False).astype("<f8").reshape(n, -1)
    if pa.types.is_struct(xs.type):
        x = unpack_rows(xs)
        return n, -x.d, pack_batch(x), y.tobytes(), None
    flat = xs.flatten().to_numpy(zero_copy_only=False)
    size = len(flat) // n
    if (np.diff(xs.offsets.to_numpy()) != size).any():
        raise ValueError("inputs have different lengths")
    x = flat.astype("<f8").reshape(n, size)
    rows = np.ascontiguousarray(np.hstack((x, y)))
    _, first, counts = np.unique(rows.view(np.dtype((np.void, rows.shape[1] * 8)))[:, 0], return_index=True, return_counts=True)
    if 2 * len(first) > n:
        return n, size, x.tobytes(), y.tobytes(), None
    return len(first), size, x[first].tobytes(), y[first].tobytes(), counts.astype("<f8").tobytes()


def _packed(examples: DataFrame, rows: int) -> DataFrame:
    sparse = is_sparse(examples)
    block = F.col("row_block") if "row_block" in examples.columns else F.pmod(F.xxhash64("row_id"), F.lit(rows))
    x = F.col("x") if sparse else F.col("x").cast("array<double>")
    dealt = checked(examples).select(
        block.cast("int").alias("row_block"), "row_id", x.alias("x"), F.col("y").cast("array<double>").alias("y")
    )

    def gather(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("row_id").to_numpy(), kind="stable")
        table = table.take(pa.array(order)).combine_chunks()
        n = table.num_rows
        xs = table.column("x").combine_chunks()
        if sparse:
            size = int(xs.field("size").to_numpy().max())
            idx, val = xs.field("idx"), xs.field("val")
            ptr = np.concatenate(([0], np.cumsum(np.diff(idx.offsets.to_numpy()))))
            packed = pack_batch(Sparse(ptr, idx.flatten().to_numpy().astype(np.int64), val.flatten().to_numpy().astype(float), size))
        else:
            flat = xs.flatten().to_numpy(zero_copy_only=False)
            size = len(flat) // n
            if (np.diff(xs.offsets.to_numpy()) != size).any():
                raise ValueError("inputs have different lengths")
            packed = flat.astype("<f8").tobytes()
        y = table.column("y").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype("<f8")
        return pa.table(
            {
                "row_block": pa.array([table.column("row_block")[0].as_py()], pa.int32()),
                "n": pa.array([n], pa.int64()),
                "d": pa.array([-size if sparse else size], pa.int64()),
                "x": pa.array([packed], pa.binary()),
                "y": pa.array([y.tobytes()], pa.binary()),
                "ids": pa.array([table.column("row_id").to_numpy().astype("<i8").tobytes()], pa.binary()),
            }
        )

    return dealt.groupBy("row_block").applyInArrow(gather, PACKED)


def pack_batch(x: Batch) -> bytes:
    if isinstance(x, Sparse):
        head = np.array([len(x.ptr), len(x.idx)], "<i8").tobytes()
        return head + x.ptr.astype("<i8").tobytes() + x.idx.astype("<i8").tobytes() + x.val.astype("<f8").tobytes()
    return x.astype("<f8").tobytes()


def unpack_batch(raw: bytes, d: int) -> Batch:
    """d is negative for sparse rows."""
    if d >= 0:
        return np.frombuffer(raw, "<f8").reshape(-1, d)
    a, b = np.frombuffer(raw, "<i8", 2)
    ptr = np.frombuffer(raw, "<i8", a, 16)
    idx = np.frombuffer(raw, "<i8", b, 16 + 8 * a)
    return Sparse(ptr, idx, np.frombuffer(raw, "<f8", b, 16 + 8 * (a + b)), -d)


def unpack_rows(column: pa.Array) -> Batch:
    """The rows of an Arrow column of arrays or of sparse structs."""
    if pa.types.is_struct(column.type):
        idx, val = column.field("idx"), column.field("val")
        ptr = np.concatenate(([0], np.cumsum(np.diff(idx.offsets.to_numpy()))))
        size = int(column.field("size").to_numpy().max()) if len(column) else 0
        return Sparse(ptr, idx.flatten().to_numpy().astype(np.int64), val.flatten().to_numpy().astype(float), size)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(float)
    return flat.reshape(len(column), -1)
