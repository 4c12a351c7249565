"""The block-splitting solver on Spark.

A row block is one row of packed inputs, kept where it is together with its factors, which the first round makes.
A round joins the blocks' states to them, in one stage behind an exchange of the states alone, and gives the new
states, the local models and the times; inputs and factors never leave. A sum of the local models (keyed and in two
levels where they are large together) and a root step on the driver over s x m numbers follow. Every few rounds the
states go to the checkpoint folder, so lineage stays short and a lost executor costs those rounds at most; random
parameters come from (seed, block), so a task that runs again repeats itself bit by bit.

A row block that is too large for a task is spread over many (spread_rows, tiled.py).
"""

from __future__ import annotations

import json
import pickle
import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kernelblocks.admm.step import BlockState, Root, SolverConfig, complete_factors, root_prox, root_reduce, row_block_step
from kernelblocks.functions.featuremaps import FeatureMap
from kernelblocks.functions.prox import loss_of, reg_of
from kernelblocks.plans.blocks import even_blocks, is_sparse, pack, unpack_batch, unpack_rows
from kernelblocks.storage import ensure_checkpoint_dir, kept_flat

#: Above so many bytes the model is not collected on the driver in one piece.
MAX_MODEL_BYTES = 2 << 30
MAX_ROW_BYTES = 1_800_000_000
#: A row block whose inputs, outputs and features would take a task more than this is spread over tasks.
BLOCK_BYTES = 128 << 20
#: What the inputs, outputs and features of one tile may take each.
TILE_BYTES = 8 << 20
#: Local models that are this small together come to the driver as they are; beyond, the keyed sum spreads them.
DIRECT_BYTES = 64 << 20
BASE = ["row_block", "n", "d", "x", "y", "factors"]
STEP_OUT = "kind string, row_block int, block int, step string, value double, payload binary"


@dataclass
class Model:
    """Weights by column block, the map that makes the features, and what the outputs mean."""

    fmap: FeatureMap
    weights: list[np.ndarray]
    coding: str = "ovr"
    classes: list | None = None

    @property
    def matrix(self) -> np.ndarray:
        return np.vstack(self.weights)

    def save(self, spark: SparkSession, path: str) -> None:
        """Weights as Parquet, a file for each column block, with the map and the classes beside them."""
        rows = [(j, bytearray(w.astype("<f8").tobytes()), w.shape[1]) for j, w in enumerate(self.weights)]
        spark.createDataFrame(rows, "col_block int, w binary, m int").write.mode("overwrite").partitionBy("col_block").parquet(f"{path}/weights")
        head = bytearray(pickle.dumps((self.fmap, self.coding, self.classes)))
        spark.createDataFrame([(head,)], "config binary").write.mode("overwrite").parquet(f"{path}/config")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Model:
        fmap, coding, classes = pickle.loads(bytes(spark.read.parquet(f"{path}/config").first()["config"]))
        got = sorted(spark.read.parquet(f"{path}/weights").collect(), key=lambda r: r["col_block"])
        return cls(fmap, [np.frombuffer(bytes(r["w"]), "<f8").reshape(-1, r["m"]) for r in got], coding, classes)


@dataclass
class Run:
    model: Model
    history: list[dict] = field(default_factory=list)
    profile: list[tuple[int, int, str, float]] = field(default_factory=list)
    seconds: float = 0.0
    rounds: int = 0
    trajectory: list[np.ndarray] = field(default_factory=list)
    config: SolverConfig | None = None

    def history_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(int(h["iter"]), k, float(v)) for h in self.history for k, v in h.items() if k != "iter"]
        return spark.createDataFrame(rows, "iter int, measure string, value double")

    def profile_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.profile, "iter int, row_block int, step string, sec double")



@dataclass
class SharedBlocks:
    """Packed row blocks, kept, and beside them the factors that runs on them have made."""

    packed: DataFrame
    factors: dict = field(default_factory=dict)


@contextmanager
def shared(examples: DataFrame, rows: int) -> Iterator[SharedBlocks]:
    """Row blocks for several runs on the same examples."""
    _check_row(examples, rows)
    held = SharedBlocks(pack(examples, rows).repartition(rows, "row_block").persist())
    try:
        yield held
    finally:
        for f in (*held.factors.values(), held.packed):
            f.unpersist()


def solve(
    examples: DataFrame,
    fmap: FeatureMap,
    loss: str = "hinge",
    reg: str = "ridge",
    lam: float = 1e-3,
    rho: float | None = None,
    rows: int | None = None,
    iters: int = 30,
    layout: str = "reorganized",
    cache: str = "inverse",
    gram_shortcut: bool = False,
    block_fraction: float = 1.0,
    checkpoint_every: int = 5,
    eval_df: DataFrame | None = None,
    eval_every: int = 0,
    tol: float | None = None,
    patience: int | None = None,
    resume: str | None = None,
    save_state: str | None = None,
    threads: int = 1,
    seed: int = 0,
    coding: str = "ovr",
    classes: list | None = None,
    keep_trajectory: bool = False,
    tile_rows: int = 0,
    consensus: str = "broadcast",
    spread_rows: int = 0,
    block_tasks: int = 0,
    even: bool = False,
    blocks: SharedBlocks | None = None,
    weight_pull: float = 1.0,
) -> Run:
    """Fits W for mean loss + lam * reg on example(row_id, x, y[, label]).

    rho defaults to 1/n. tol stops when the primal and the dual residual fall below it; patience stops when
    the accuracy on eval_df, measured every eval_every rounds, hasn't grown for so many measurements.
    resume and save_state name a folder that holds a run's whole state. tile_rows bounds the features that a
    task holds at once to so many rows of one column block, for twice the transforms.
    consensus "broadcast" takes the root's step on the driver; "join" takes it by column block on the executors
    (a fixed number of rounds, no history) and the driver gets the weights at the end alone. spread_rows spreads each
    row block over tasks, in tiles of about so many rows whose features a task holds whole (a fixed number of rounds,
    accuracies as history); a row block that would take a task more than BLOCK_BYTES is spread by itself where the
    options allow it; block_tasks, if set, is the number of tasks of each spread block. even makes the blocks' sizes differ by one row at most, for one more exchange.
    blocks gives row blocks that several runs share (shared). weight_pull is the step of the models in parts of rho: in
    proportion to the rows it makes the progress of a round independent of their number.
    """
    spark = examples.sparkSession
    ensure_checkpoint_dir(spark)
    began = time.perf_counter()
    rows = rows or max(1, spark.sparkContext.defaultParallelism)
    if even:
        examples = even_blocks(examples, rows)
    if not spread_rows and blocks is None:
        plain = layout == "reorganized" and not gram_shortcut and cache != "none" and tol is None and patience is None and resume is None and save_state is None
        spread_rows = _check_row(examples, rows, fmap, plain)
    if spread_rows:
        return _spread(examples, fmap, (loss, reg, lam, rho), rows, iters, cache, block_fraction, checkpoint_every, eval_df, eval_every, seed, coding, classes, spread_rows, keep_trajectory, consensus == "join", block_tasks, weight_pull)
    packed = blocks.packed if blocks is not None else pack(examples, rows).repartition(rows, "row_block").persist()
    shape = packed.agg(F.sum("n"), F.count("*"), F.max(F.length("y") / F.col("n"))).first()
    if not shape[0]:
        packed.unpersist()
        raise ValueError("there are no examples")
    n, full, m = int(shape[0]), int(shape[1]), int(shape[2]) // 8
    cfg = SolverConfig(fmap, loss, reg, lam, rho or 1.0 / n, n, m, full, layout, cache, gram_shortcut, block_fraction, threads, seed, tile_rows, weight_pull)
    if consensus == "join":
        from kernelblocks.admm.joined import solve_joined

        got = sorted(solve_joined(packed, cfg, iters, checkpoint_every, rows).collect(), key=lambda r: r["col_block"])
        packed.unpersist()
        weights = [np.frombuffer(bytes(r["w_bar"]), "<f8").reshape(-1, m) for r in got]
        return Run(Model(fmap, weights, coding, classes), seconds=time.perf_counter() - began, rounds=iters, config=cfg)
    if fmap.s * m * 8 > MAX_MODEL_BYTES:
        raise ValueError("the model is too large for the driver; use fewer outputs or features")
    per_block = 8 * (3 * fmap.s * m + 3 * n * m / full + (fmap.s * max(fmap.width(0), 1) if cache != "none" else 0))
    if per_block > MAX_ROW_BYTES:
        raise ValueError(f"a row block's state would take {per_block:.3g} bytes; use more column blocks, cache='none' or spread_rows")
    root, first, state = Root.zero(cfg), 1, None
    known = None if blocks is None or cache == "none" else blocks.factors.get((fmap, cache, gram_shortcut, bool(tile_rows), weight_pull))
    base = known if known is not None else packed.select(*BASE[:-1], F.lit(None).cast("binary").alias("factors"))
    if resume:
        root, first = pickle.loads(bytes(spark.read.parquet(f"{resume}/root").first()["payload"]))
        state = spark.read.parquet(f"{resume}/state")
    run = Run(Model(fmap, root.w_bar, coding, classes), config=cfg)
    best, stale, last = -1.0, 0, None
    for it in range(first, first + iters):
        old = [w.copy() for w in root.w_bar] if tol is not None else None
        root_prox(root, it, cfg)
        round_began = time.perf_counter()
        make = it == first and known is None
        out, let_go = kept_flat(_round(base, state, root.w_bar, it, cfg, make))
        sums, times, gap = _reduce(out, cfg, it)
        run.profile += [(it, r, step, sec) for r, step, sec in times]
        root_reduce(root, sums, it, cfg)
        state = out.where("kind = 'state'").select("row_block", "payload")
        if make and cache != "none" and (iters > 1 or blocks is not None):
            made = out.where("kind = 'factor'").select("row_block", F.col("payload").alias("factors")).checkpoint(eager=True)
            base = packed.join(made, "row_block").select(BASE).persist()
            base.count()  # a plan knows how rows lie once they do
            if blocks is not None:
                blocks.factors[fmap, cache, gram_shortcut, bool(tile_rows), weight_pull] = base
        if it % checkpoint_every == 0 and it < first + iters - 1:
            state = state.checkpoint(eager=True)
        run.profile.append((it, -1, "wall", time.perf_counter() - round_began))
        if last is not None:
            last()
        last = let_go
        record = {"iter": it}
        if tol is not None:
            spread = sum(float(((w - root.w_bar[j]) ** 2).sum()) for j, w in enumerate(root.w))
            moved = sum(float(((w - o) ** 2).sum()) for w, o in zip(root.w_bar, old, strict=True))
            size = fmap.s * m
            # root mean squares: of the local models and outputs against their consensus, and of the consensus' step
            record |= {"primal_residual": float(np.sqrt((spread + gap) / ((full + 1) * size + n * m))), "dual_residual": float(np.sqrt(moved / size))}
        if eval_df is not None and eval_every and it % eval_every == 0:
            from kernelblocks.measures import accuracy

            record["accuracy"] = accuracy(predict(eval_df, Model(fmap, root.w_bar, coding, classes)))
        if len(record) > 1:
            run.history.append(record)
        run.rounds = it
        if keep_trajectory:
            run.trajectory.append(np.vstack(root.w_bar))
        if tol is not None and it > 1 and max(record["primal_residual"], record["dual_residual"]) < tol:
            break
        if patience is not None and "accuracy" in record:
            stale = 0 if record["accuracy"] > best else stale + 1
            best = max(best, record["accuracy"])
            if stale >= patience:
                break
    if save_state:
        state.write.mode("overwrite").parquet(f"{save_state}/state")
        spark.createDataFrame([(bytearray(pickle.dumps((root, run.rounds + 1))),)], "payload binary").write.mode("overwrite").parquet(f"{save_state}/root")
    if last is not None:
        last()
    if blocks is None:
        base.unpersist()
        packed.unpersist()
    run.model = Model(fmap, [w.copy() for w in root.w_bar], coding, classes)
    run.seconds = time.perf_counter() - began
    return run


def _check_row(examples: DataFrame, rows: int, fmap: FeatureMap | None = None, may_spread: bool = False) -> int:
    """Rows of a tile where row blocks are to be spread, else 0. A block that isn't spread must fit in one row."""
    x = F.size("x.idx") * 16 + 8 if is_sparse(examples) else F.size("x") * 8
    got = examples.agg(F.count("*"), F.sum((x + F.size("y") * 8).cast("long")), F.max(F.size("y"))).first()
    n, size, m = got[0], (got[1] or 0) / rows, got[2] or 1
    if may_spread and n:
        # inputs as rows, packed and unpacked; outputs, their dual, gap and what a round makes of them; features twice
        if 3 * size + 8.0 * n / rows * (8 * m + 2 * fmap.width(0)) > BLOCK_BYTES:
            widest = max(size * rows / n, 8.0 * fmap.s, 8.0 * m * 8)
            return int(min(1 << 16, max(64, TILE_BYTES // widest)))
    if size > MAX_ROW_BYTES:
        raise ValueError(f"a row block's inputs would take {size:.3g} bytes in one row; use more row blocks or spread_rows")
    return 0


def _spread(examples, fmap, problem, rows, iters, cache, block_fraction, checkpoint_every, eval_df, eval_every, seed, coding, classes, spread_rows, keep_trajectory, joined=False, block_tasks=0, weight_pull=1.0) -> Run:
    from kernelblocks.admm.tiled import solve_tiled
    from kernelblocks.measures import accuracy

    began = time.perf_counter()
    shape = examples.agg(F.count("*"), F.max(F.size("y"))).first()
    if not shape[0]:
        raise ValueError("there are no examples")
    loss, reg, lam, rho = problem
    n, m = int(shape[0]), int(shape[1])
    if 8 * max(fmap.width(0) ** 2, fmap.s * m) > MAX_ROW_BYTES:
        raise ValueError("a column block's factor or the model is too large for one row; use more column blocks")
    run = Run(Model(fmap, [], coding, classes), rounds=iters)

    def watch(it: int, root: Root) -> None:
        run.rounds = it
        if keep_trajectory:
            run.trajectory.append(np.vstack(root.w_bar))
        if eval_df is not None and eval_every and it % eval_every == 0:
            run.history.append({"iter": it, "accuracy": accuracy(predict(eval_df, Model(fmap, root.w_bar, coding, classes)))})

    cfg = SolverConfig(fmap, loss, reg, lam, rho or 1.0 / n, n, m, rows, "reorganized", cache, False, block_fraction, 1, seed, weight_pull=weight_pull)
    root, run.profile, run.config = solve_tiled(examples, cfg, iters, checkpoint_every, spread_rows, watch, joined, block_tasks)
    run.model = Model(fmap, [w.copy() for w in root.w_bar], coding, classes)
    run.seconds = time.perf_counter() - began
    return run


def _round(base: DataFrame, state: DataFrame | None, w_bar: list[np.ndarray], it: int, cfg: SolverConfig, make: bool = False) -> DataFrame:
    """Rows of states, local models, times and residuals, and with make of the factors."""
    sent = base.sparkSession.sparkContext.broadcast([w.copy() for w in w_bar])
    joined = base.withColumn("payload", F.lit(None).cast("binary")) if state is None else base.join(state, "row_block")
    names = [f.split()[0] for f in STEP_OUT.split(", ")]

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = sent.value
        for b in batches:
            for row in range(b.num_rows):
                who, n, d, raw_x, raw_y, factors, payload = (b.column(k)[row].as_py() for k in range(7))
                x = unpack_batch(raw_x, d)
                y = np.frombuffer(raw_y, "<f8").reshape(n, -1)
                st = pickle.loads(payload) if payload is not None else BlockState.zero(n, cfg)
                if factors is not None:
                    st.q, st.gram = pickle.loads(factors)
                began = time.perf_counter()
                st = row_block_step(st, x, y, w, it, cfg)
                if make and cfg.cache != "none":
                    complete_factors(st, x, cfg)
                st.seconds["round"] = time.perf_counter() - began
                seconds, st.seconds = st.seconds, {}
                held, (st.q, st.gram) = (st.q, st.gram), ([None] * cfg.cols, [None] * cfg.cols)
                active = [int(j) for j in cfg.active(it)]
                gap = sum(float(((st.w[j] - w[j]) ** 2).sum()) for j in active) + float((st.gap**2).sum())
                rows = [("state", None, None, None, pickle.dumps(st))]
                rows += [("factor", None, None, None, pickle.dumps(held))] * (make and cfg.cache != "none")
                rows += [("sum", j, None, None, st.w[j].tobytes()) for j in active]
                rows += [("time", None, k, v, None) for k, v in seconds.items()]
                rows.append(("gap", None, None, gap, None))
                kind, block, name, value, sent_out = zip(*rows, strict=True)
                cols = (kind, [who] * len(rows), block, name, value, sent_out)
                kinds = (pa.string(), pa.int32(), pa.int32(), pa.string(), pa.float64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    return joined.select(*BASE, "payload").mapInArrow(step, STEP_OUT)


def add_payloads(df: DataFrame, keys: list[str], like: str) -> DataFrame:
    """Sums binaries of doubles by key; like is the schema of the result. The terms of a key come in a fixed order."""

    def add(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("row_block").to_numpy(), kind="stable")
        parts = [np.frombuffer(table.column("payload")[int(i)].as_py(), "<f8") for i in order]
        total = parts[0].copy()
        for p in parts[1:]:
            total += p
        out = {k: pa.array([table.column(k)[0].as_py()], pa.int32()) for k in keys}
        if "row_block" not in keys:
            out["row_block"] = pa.array([table.column("row_block")[0].as_py()], pa.int32())
        return pa.table(out | {"payload": pa.array([total.tobytes()], pa.binary())}).select([c.split()[0] for c in like.split(", ")])

    return df.groupBy(*keys).applyInArrow(add, like)


def _reduce(out: DataFrame, cfg: SolverConfig, it: int) -> tuple[dict[int, np.ndarray], list[tuple[int, str, float]], float]:
    """(sums of the local models by column block, times of steps, squared residual)."""
    if cfg.rows * cfg.fmap.s * cfg.m * 8 <= DIRECT_BYTES:
        rows = sorted(out.where("kind in ('sum', 'time', 'gap')").select("kind", "row_block", "block", "step", "value", "payload").collect(), key=lambda r: (r["row_block"], r["block"] or 0))
        got = {}
        for r in rows:
            if r["kind"] == "sum":
                w = np.frombuffer(bytes(r["payload"]), "<f8").reshape(-1, cfg.m)
                got[r["block"]] = got[r["block"]] + w if r["block"] in got else w.copy()
        times = [(r["row_block"], r["step"], r["value"]) for r in rows if r["kind"] == "time"]
        return got, times, sum(r["value"] for r in rows if r["kind"] == "gap")
    sums = out.where("kind = 'sum'").select("row_block", "block", "payload")
    group = int(np.ceil(np.sqrt(cfg.rows)))
    if cfg.rows > 16:
        first = sums.withColumn("part", (F.col("row_block") / group).cast("int"))
        sums = add_payloads(first, ["block", "part"], "block int, part int, row_block int, payload binary").select("row_block", "block", "payload")
    added = add_payloads(sums, ["block"], "block int, row_block int, payload binary")
    got = {
        r["block"]: np.frombuffer(bytes(r["payload"]), "<f8").reshape(-1, cfg.m).copy() for r in added.select("block", "payload").collect()
    }
    small = out.where("kind in ('time', 'gap')").select("kind", "row_block", "step", "value").collect()
    times = [(r["row_block"], r["step"], r["value"]) for r in small if r["kind"] == "time"]
    return got, times, sum(r["value"] for r in small if r["kind"] == "gap")


SCORED = "scores array<double>, pred double, margin double"


def _decide(scores: np.ndarray, coding: str, classes: list | None) -> tuple[np.ndarray, np.ndarray]:
    if coding == "regression":
        return scores[:, 0], scores[:, 0]
    if scores.shape[1] == 1:
        sign = np.where(scores[:, 0] >= 0, 1, 0)
        names = np.array(classes if classes is not None else [-1, 1], float)
        return names[sign], scores[:, 0]
    top = np.argmax(scores, axis=1)
    names = np.array(classes if classes is not None else range(scores.shape[1]), float)
    part = np.sort(scores, axis=1)
    return names[top], part[:, -1] - part[:, -2]


def predict(df: DataFrame, model: Model, proba: bool = False, tile_rows: int = 4096) -> DataFrame:
    """df with scores, pred and margin; features are made for a tile of rows and one column block at a time.

    proba turns scores into class shares. No shuffle; every column of df passes through.
    """
    held = df.sparkSession.sparkContext.broadcast((model.fmap, model.weights, model.coding, model.classes))
    at = df.columns.index("x")
    names = [*df.columns, "scores", "pred", "margin"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + ", " + SCORED

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fmap, weights, coding, classes = held.value
        for batch in batches:
            for k in range(0, batch.num_rows, tile_rows):
                b = batch.slice(k, tile_rows)
                x = unpack_rows(b.column(at))
                out = np.zeros((b.num_rows, weights[0].shape[1]))
                for j, w in enumerate(weights):
                    out += fmap.block(x, j) @ w
                if proba:
                    out = np.exp(out - out.max(axis=1, keepdims=True))
                    out /= out.sum(axis=1, keepdims=True)
                pred, margin = _decide(out, coding, classes)
                offsets = np.arange(0, out.size + 1, out.shape[1]).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [*b.columns, pa.ListArray.from_arrays(offsets, out.ravel()), pa.array(pred.astype(float)), pa.array(margin)], names=names
                )

    return df.mapInArrow(score, schema)


def objective(df: DataFrame, model: Model, loss: str, reg: str, lam: float) -> float:
    """Mean loss plus lam times the regularizer, over all rows; features are made again and dropped."""
    held = df.sparkSession.sparkContext.broadcast((model.fmap, model.weights))

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fmap, weights = held.value
        total, count = 0.0, 0
        for b in batches:
            x = unpack_rows(b.column(0))
            y = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(b.num_rows, -1)
            o = sum(fmap.block(x, j) @ w for j, w in enumerate(weights))
            total += loss_of(loss).value(o, y)
            count += b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([count])], names=["total", "count"])

    got = df.select("x", "y").mapInArrow(part, "total double, count long").agg(F.sum("total"), F.sum("count")).first()
    return got[0] / got[1] + lam * reg_of(reg).value(model.matrix)


def describe(model: Model) -> str:
    return json.dumps({"map": type(model.fmap).__name__, "d": model.fmap.d, "s": model.fmap.s, "blocks": model.fmap.col_blocks, "coding": model.coding})


__all__ = ["Model", "Run", "is_sparse", "objective", "predict", "solve"]
