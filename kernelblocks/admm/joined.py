"""The block solver with a consensus that never passes through the driver.

The root's model, its dual and the consensus are a frame by column block; its prox and the reduce are done
column block by column block where the sums arrive, which separable regularizers allow. The consensus
reaches the row blocks by a join, so a round moves rows x s x m numbers once each way. The packed inputs
stay where they are: only states and consensus are dealt by the row block.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kernelblocks.admm.engine import add_payloads
from kernelblocks.admm.step import BlockState, SolverConfig, row_block_step
from kernelblocks.functions.prox import reg_of
from kernelblocks.plans.blocks import unpack_batch
from kernelblocks.storage import kept_flat

ROOT = "col_block int, w binary, mu binary, w_bar binary"
OUT = "kind string, row_block int, block int, payload binary"


def empty_root(spark: SparkSession, cfg: SolverConfig) -> DataFrame:
    def zero(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            j = b.column(0).to_pylist()
            z = pa.array([np.zeros((cfg.fmap.width(k), cfg.m)).tobytes() for k in j], pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(j, pa.int32()), z, z, z], names=["col_block", "w", "mu", "w_bar"])

    return spark.range(cfg.cols).mapInArrow(zero, ROOT)


def prox_by_column(root: DataFrame, it: int, cfg: SolverConfig) -> DataFrame:
    now, last = set(map(int, cfg.active(it))), set(map(int, cfg.active(it - 1))) if it > 1 else set()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reg = reg_of(cfg.reg)
        for b in batches:
            out: list[list] = [[], []]
            for j, *raw in zip(*(c.to_pylist() for c in b.columns), strict=True):
                w, mu, bar = (np.frombuffer(r, "<f8").reshape(-1, cfg.m) for r in raw)
                mu = mu + w - bar if j in last else mu
                w = reg.prox(bar - mu, cfg.lam / (cfg.rho * cfg.weight_pull)) if j in now else w
                out[0].append(w.tobytes())
                out[1].append(mu.tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(o, pa.binary()) for o in out), b.column(3)], names=b.schema.names)

    return root.mapInArrow(run, ROOT)


def reduce_by_column(root: DataFrame, sums: DataFrame, it: int, cfg: SolverConfig) -> DataFrame:
    joined = root.join(sums.select(F.col("block").alias("col_block"), F.col("payload").alias("total")), "col_block", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            w, bar, total = (b.column(k).to_pylist() for k in (1, 3, 4))
            new = [old if t is None else ((np.frombuffer(a, "<f8") + np.frombuffer(t, "<f8")) / (cfg.rows + 1)).tobytes() for a, old, t in zip(w, bar, total, strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(new, pa.binary())], names=["col_block", "w", "mu", "w_bar"])

    return joined.select("col_block", "w", "mu", "w_bar", "total").mapInArrow(run, ROOT)


def _step(packed: DataFrame, state: DataFrame | None, root: DataFrame, it: int, cfg: SolverConfig, parts: int) -> DataFrame:
    # every row block gets every column block of the consensus: a copy is addressed to each
    copies = root.select("col_block", "w_bar", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("row_block"))
    sent = copies.groupBy("row_block").agg(F.sort_array(F.collect_list(F.struct("col_block", "w_bar"))).alias("bars"))
    joined = packed.join(sent, "row_block")
    if state is None:
        joined = joined.withColumn("payload", F.lit(None).cast("binary"))
    else:
        joined = joined.join(state, "row_block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                who, n, d, raw_x, raw_y, payload, bars = (b.column(k)[r].as_py() for k in range(7))
                w_bar = [np.frombuffer(p["w_bar"], "<f8").reshape(-1, cfg.m) for p in bars]
                st = pickle.loads(payload) if payload is not None else BlockState.zero(n, cfg)
                st = row_block_step(st, unpack_batch(raw_x, d), np.frombuffer(raw_y, "<f8").reshape(n, -1), w_bar, it, cfg)
                st.seconds = {}
                active = [int(j) for j in cfg.active(it)]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(["state"] + ["sum"] * len(active)),
                        pa.array([who] * (1 + len(active)), pa.int32()),
                        pa.array([None, *active], pa.int32()),
                        pa.array([pickle.dumps(st), *(st.w[j].tobytes() for j in active)], pa.binary()),
                    ],
                    names=["kind", "row_block", "block", "payload"],
                )

    return joined.select("row_block", "n", "d", "x", "y", "payload", "bars").mapInArrow(run, OUT)


def solve_joined(packed: DataFrame, cfg: SolverConfig, iters: int, checkpoint_every: int, parts: int) -> DataFrame:
    """(col_block, w_bar): the consensus after so many rounds; packed is kept and dealt by row_block."""
    root, state = empty_root(packed.sparkSession, cfg), None
    drop: list[Callable[[], None]] = []
    for it in range(1, iters + 1):
        root = prox_by_column(root, it, cfg)
        out, free_out = kept_flat(_step(packed, state, root, it, cfg, parts))
        sums = out.where("kind = 'sum'").select("row_block", "block", "payload")
        if cfg.rows > 16:
            width = int(np.ceil(np.sqrt(cfg.rows)))
            part = sums.withColumn("part", (F.col("row_block") / width).cast("int"))
            sums = add_payloads(part, ["block", "part"], "block int, part int, row_block int, payload binary").select("row_block", "block", "payload")
        total = add_payloads(sums, ["block"], "block int, row_block int, payload binary")
        root, free_root = kept_flat(reduce_by_column(root, total, it, cfg))
        state = out.where("kind = 'state'").select("row_block", "payload")
        root.select(F.max("col_block")).collect()  # the round is worked off here; a number comes back
        if it % checkpoint_every == 0:
            root, state = root.checkpoint(eager=True), state.checkpoint(eager=True)
        for f in drop:
            f()
        drop = [free_out, free_root]
    return root.select("col_block", "w_bar")
