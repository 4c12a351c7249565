"""The block solver with a row block spread over many tasks.

A row block is cut in tiles, each a row of packed inputs with its outputs and their dual, all squeezed without loss.
Per round:

1. each tile finishes the last round with its row block's local models and begins the next: it moves its
   outputs by the prox and gives, for each column block, its part of Z'(pull); a task adds up its tiles'
   parts, and a keyed sum the tasks' (the first round does the same for Z'Z);
2. for each (row block, column block) the summed right side meets its dual, its product and its factor, and the
   local model is solved for; the root's step follows as in engine.py, or by column block on the executors (joined);
3. the local models go back to the tiles: broadcast while they are small together, by a join beyond.

A tile's features are made once a round. Tiles of one slot lie in one task; a round gives its successor's tiles where
they lie, on disk and without an exchange, and moves three small matrices for each (row block, column block). Factors
are made once, apart from the state.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kernelblocks.admm.step import Root, SolverConfig, _Clock, root_prox, root_reduce
from kernelblocks.functions.graphproj import factor_of_gram
from kernelblocks.functions.prox import loss_of
from kernelblocks.plans.blocks import loosened, pack_tiles, squeezed, unpack_batch
from kernelblocks.storage import kept_flat

#: Local models that are this small together come to the driver and go out as a broadcast.
DIRECT_BYTES = 64 << 20
#: Outputs and their duals that a task has, before they are squeezed.
TASK_BYTES = 32 << 20
TILE = ["row_block", "tile", "slot", "n", "d", "x", "y", "counts"]
PASSED = "kind string, row_block int, tile long, slot int, n long, d long, x binary, y binary, counts binary, block int, step string, sec double, payload binary"
KINDS = (pa.string(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int32(), pa.string(), pa.float64(), pa.binary())
SUMMED = "row_block int, block int, payload binary"
SOLVED = "row_block int, block int, sec double, w binary, payload binary"


def _flat(raw: bytes, m: int) -> np.ndarray:
    return np.frombuffer(raw, "<f8").reshape(-1, m)


class _Pass:
    """What a task does with its tiles in one round."""

    def __init__(self, cfg: SolverConfig, it: int) -> None:
        self.cfg, self.it = cfg, it
        self.active = [int(j) for j in cfg.active(it)]
        self.parts: dict[tuple[str, int, int], tuple[int, np.ndarray]] = {}
        self.seconds: dict[int, dict[str, float]] = {}

    def tile(self, row_block: int, tile: int, x, y: np.ndarray, counts: np.ndarray | None, held: bytes | None, w: list[np.ndarray] | None) -> bytes:
        """The tile's outputs and dual after the beginning of this round; its parts of the sums are added up.

        A row counts counts times in the sums; its outputs are those of all rows like it.
        """
        cfg, c = self.cfg, self.cfg.cols
        clock = _Clock(self.seconds.setdefault(row_block, {}))
        zs = [cfg.fmap.block(x, j) for j in range(c)]
        clock.lap("transform")
        if held is None:
            gap = o_bar = nu = np.zeros((len(y), cfg.m))
        else:
            o, nu = _flat(held, cfg.m).reshape(2, len(y), cfg.m)
            total = sum(z @ v for z, v in zip(zs, w, strict=True))
            clock.lap("projection")
            gap, o_bar = o - total, (c * o + total) / (c + 1)
            nu = nu + o - o_bar
            clock.lap("sums")
        o = loss_of(cfg.loss).prox(o_bar - nu, y, 1.0 / (cfg.n * cfg.rho))
        clock.lap("prox")
        pull = gap / (c + 1) + nu
        if counts is not None:
            pull = pull * counts[:, None]
        for j in self.active:
            self._add("part", row_block, tile, j, zs[j].T @ pull)
        clock.lap("projection")
        if self.it == 1:
            for j in range(c):
                self._add("gram", row_block, tile, j, zs[j].T @ (zs[j] if counts is None else zs[j] * counts[:, None]))
            clock.lap("factor")
        return o.tobytes() + nu.tobytes()

    def _add(self, kind: str, row_block: int, tile: int, j: int, part: np.ndarray) -> None:
        first, known = self.parts.get((kind, row_block, j), (tile, None))
        if known is None:
            known = part.copy()
        else:
            known += part
        self.parts[kind, row_block, j] = (first, known)


def _passed(kind: str, row_block: int, tile=None, slot=None, n=None, d=None, x=None, y=None, counts=None, block=None, step=None, sec=None, payload=None) -> pa.RecordBatch:
    row = (kind, row_block, tile, slot, n, d, x, y, counts, block, step, sec, payload)
    return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, KINDS, strict=True)], names=[f.split()[0] for f in PASSED.split(", ")])


def _pass(tiles: DataFrame, models, it: int, cfg: SolverConfig) -> DataFrame:
    """Rows of tiles with their states, of parts and of times.

    tiles has held, the state; models is a broadcast {row block: local models}, a frame (slot, models), or None.
    """
    by_join = isinstance(models, DataFrame)
    joined = tiles.join(models.hint("shuffle_hash"), "slot") if by_join else tiles.withColumn("models", F.lit(None).cast("binary"))
    sent = None if by_join else models

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = _Pass(cfg, it)
        for b in batches:
            for r in range(b.num_rows):
                row_block, tile, slot, n, d, x, y, counts, held, own = (b.column(k)[r].as_py() for k in range(10))
                if own is not None:
                    w = [_flat(p["w"], cfg.m) for p in sorted(own, key=lambda p: p["block"])]
                else:
                    w = sent.value[row_block] if sent is not None else None
                began = time.perf_counter()
                held = loosened(held) if held is not None else None
                many = np.frombuffer(loosened(counts), "<f8") if counts is not None else None
                payload = squeezed(step.tile(row_block, tile, unpack_batch(loosened(x), d), np.frombuffer(loosened(y), "<f8").reshape(n, -1), many, held, w))
                yield _passed("state", row_block, tile, slot, n, d, x, y, counts, sec=time.perf_counter() - began, payload=payload)
        for (kind, row_block, j), (tile, part) in sorted(step.parts.items()):
            yield _passed(kind, row_block, tile, block=j, payload=part.tobytes())
        for row_block, laps in sorted(step.seconds.items()):
            for name, sec in laps.items():
                yield _passed("time", row_block, step=name, sec=sec)

    return joined.select(*TILE, "held", "models").mapInArrow(run, PASSED)


@contextmanager
def _at_most(spark: SparkSession, rows: int) -> Iterator[None]:
    """Plans that are made inside give Python so many rows at once at most."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(int(before), rows) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def _summed(passed: DataFrame, kind: str) -> DataFrame:
    """(row_block, block, payload): the parts of all tasks, added up in the order of their tiles."""

    def add(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("tile").to_numpy(), kind="stable")
        total = sum(np.frombuffer(table.column("payload")[int(i)].as_py(), "<f8") for i in order)
        return pa.table({"row_block": table.column("row_block").slice(0, 1), "block": table.column("block").slice(0, 1), "payload": pa.array([total.tobytes()], pa.binary())})

    return passed.where(F.col("kind") == kind).select("row_block", "block", "tile", "payload").groupBy("row_block", "block").applyInArrow(add, SUMMED)


def _factors(grams: DataFrame, cfg: SolverConfig) -> DataFrame:
    """(row_block, block, gram, factor, sec), made once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                raw, began = b.column(2)[r].as_py(), time.perf_counter()
                size = round((len(raw) // 8) ** 0.5)
                q = factor_of_gram(np.frombuffer(raw, "<f8").reshape(size, size), "tall", "cholesky" if cfg.cache == "cholesky" else "inverse", cfg.weight_pull).matrix
                sec = pa.array([time.perf_counter() - began])
                yield pa.RecordBatch.from_arrays([*b.slice(r, 1).columns, pa.array([q.tobytes()], pa.binary()), sec], names=["row_block", "block", "gram", "factor", "sec"])

    return grams.mapInArrow(run, "row_block int, block int, gram binary, factor binary, sec double")


def _solve(sums: DataFrame, model: DataFrame | None, factors: DataFrame, w_bar, it: int, cfg: SolverConfig) -> DataFrame:
    """(row_block, block, sec, w, payload): the local models of the active column blocks, and the state of all.

    w_bar is a broadcast of the consensus or a frame (block, bar) of it.
    """
    from kernelblocks.functions.graphproj import Factor

    keys = ["row_block", "block"]
    joined = factors.join(sums.withColumnRenamed("payload", "part"), keys, "left")
    held = model.select(*keys, F.col("payload").alias("held")) if model is not None else None
    joined = joined.withColumn("held", F.lit(None).cast("binary")) if held is None else joined.join(held, keys)
    by_join = isinstance(w_bar, DataFrame)
    joined = joined.join(w_bar, "block") if by_join else joined.withColumn("bar", F.lit(None).cast("binary"))
    sent = None if by_join else w_bar
    last = {int(j) for j in cfg.active(it - 1)} if it > 1 else set()
    kind = "cholesky" if cfg.cache == "cholesky" else "inverse"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                row_block, j, gram, q, part, raw, own = (b.column(k)[r].as_py() for k in range(7))
                began = time.perf_counter()
                bar = sent.value[j] if sent is not None else _flat(own, cfg.m)
                s = bar.shape[0]
                w, mu, u = _flat(raw, cfg.m).reshape(3, s, cfg.m) if raw is not None else np.zeros((3, s, cfg.m))
                if j in last:
                    mu = mu + w - bar
                if part is not None:
                    w = Factor("tall", kind, np.frombuffer(q, "<f8").reshape(s, s)).solve(None, cfg.weight_pull * (bar - mu) + u + _flat(part, cfg.m))
                    u = np.frombuffer(gram, "<f8").reshape(s, s) @ w
                sec = time.perf_counter() - began
                cols = ([row_block], [j], [sec], [w.tobytes()], [w.tobytes() + mu.tobytes() + u.tobytes()])
                kinds = (pa.int32(), pa.int32(), pa.float64(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols, kinds, strict=True)], names=[f.split()[0] for f in SOLVED.split(", ")])

    return joined.select(*keys, "gram", "factor", "part", "held", "bar").mapInArrow(run, SOLVED)


def _column_sums(solved: DataFrame, cfg: SolverConfig) -> DataFrame:
    """(row_block, block, w): sums of the local models by column block, in two levels."""

    def add(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("row_block").to_numpy(), kind="stable")
        total = sum(np.frombuffer(table.column("w")[int(i)].as_py(), "<f8") for i in order)
        return pa.table({"row_block": table.column("row_block").slice(0, 1), "block": table.column("block").slice(0, 1), "w": pa.array([total.tobytes()], pa.binary())})

    like = "row_block int, block int, w binary"
    group = int(np.ceil(np.sqrt(cfg.rows)))
    first = solved.select("row_block", "block", "w").groupBy("block", (F.col("row_block") / group).cast("int")).applyInArrow(lambda _, t: add(t), like)
    return first.groupBy("block").applyInArrow(add, like)


def solve_tiled(examples: DataFrame, cfg: SolverConfig, iters: int, checkpoint_every: int, tile_rows: int, watch=None, joined: bool = False, block_tasks: int = 0) -> tuple[Root, list, SolverConfig]:
    """(the root after so many rounds, times, the problem); up to cfg.rows row blocks, each in tiles of at most tile_rows rows.

    joined takes the root's step by column block on the executors; the root then has the consensus at the end alone.
    block_tasks is the number of tasks for each row block, where the size of the outputs isn't to decide.
    """
    from kernelblocks.admm.joined import empty_root, prox_by_column, reduce_by_column

    spark = examples.sparkSession
    at_once = spark.sparkContext.defaultParallelism
    parts = max(cfg.rows, 4 * at_once, -(-16 * cfg.n * cfg.m // TASK_BYTES))
    slots = block_tasks or -(-parts // cfg.rows)
    parts = cfg.rows * slots if block_tasks else parts
    # a task has a few tiles at once, however many lie in its partition
    some = max(1, TASK_BYTES // (tile_rows * 32 * cfg.m))
    # kept in the shared folder: tiles made again by other tasks wouldn't have their rows in the same order
    tiles = pack_tiles(examples, cfg.rows, tile_rows, slots).repartition(parts, "slot").checkpoint(eager=True)
    cfg = replace(cfg, rows=tiles.agg(F.countDistinct("row_block")).first()[0])  # blocks without rows don't count
    root, profile, drop = Root.zero(cfg), [], []
    state = tiles.withColumn("held", F.lit(None).cast("binary"))
    model = factors = models = None
    frame = empty_root(spark, cfg) if joined else None
    direct = not joined and cfg.rows * cfg.fmap.s * cfg.m * 8 <= DIRECT_BYTES
    for it in range(1, iters + 1):
        began = time.perf_counter()
        if joined:
            frame = prox_by_column(frame, it, cfg)
            bars = frame.select(F.col("col_block").alias("block"), F.col("w_bar").alias("bar"))
        else:
            root_prox(root, it, cfg)
            bars = spark.sparkContext.broadcast([w.copy() for w in root.w_bar])
        with _at_most(spark, some):
            passed, free_passed = kept_flat(_pass(state, models, it, cfg), on_disk=True)
        made, free_frame = {}, lambda: None
        if factors is None:
            few = min(parts, cfg.rows * cfg.cols)
            factors = _factors(_summed(passed, "gram"), cfg).checkpoint(eager=True).repartition(few, "row_block", "block").persist()
            factors.count()  # a plan knows how rows lie once they do
            made = {r["row_block"]: r["sec"] for r in factors.groupBy("row_block").agg(F.sum("sec").alias("sec")).collect()}
        solved, free_solved = kept_flat(_solve(_summed(passed, "part"), model, factors.drop("sec"), bars, it, cfg))
        active = {int(j) for j in cfg.active(it)}
        laps: dict[int, dict[str, float]] = {}
        if direct:
            own: dict[int, list] = {}
            sums: dict[int, np.ndarray] = {}
            for r in sorted(solved.select("row_block", "block", "sec", "w").collect(), key=lambda r: (r["row_block"], r["block"])):
                w = _flat(bytes(r["w"]), cfg.m)
                own.setdefault(r["row_block"], []).append(w)
                sums[r["block"]] = sums[r["block"]] + w if r["block"] in sums else w.copy()
                laps.setdefault(r["row_block"], {}).setdefault("solve", 0.0)
                laps[r["row_block"]]["solve"] += r["sec"]
            models = spark.sparkContext.broadcast(own)
        elif joined:
            added = _column_sums(solved, cfg).where(F.col("block").isin(sorted(active))).select("block", F.col("w").alias("payload"))
            frame, free_frame = kept_flat(reduce_by_column(frame, added, it, cfg))
            frame.select(F.max("col_block")).collect()  # the round is worked off here; a number comes back
        else:
            sums = {r["block"]: _flat(bytes(r["w"]), cfg.m) for r in _column_sums(solved, cfg).collect()}
        if not joined:
            for r in passed.where("kind in ('state', 'time')").groupBy("row_block", F.coalesce("step", F.lit("tiles")).alias("step")).agg(F.sum("sec").alias("sec")).collect():
                laps.setdefault(r["row_block"], {})[r["step"]] = r["sec"]
            for who, own_laps in sorted(laps.items()):
                own_laps["factor"] = own_laps.get("factor", 0.0) + made.get(who, 0.0)
                spent = own_laps["tiles"] + own_laps.get("solve", 0.0) + made.get(who, 0.0)
                # as many of a block's tasks run at once as there are places for each block
                profile += [(it, who, k, v) for k, v in own_laps.items()] + [(it, who, "round", spent / max(1, min(slots, at_once // cfg.rows)))]
            root_reduce(root, {j: v for j, v in sums.items() if j in active}, it, cfg)
        state, model = passed.where("kind = 'state'").select(*TILE, F.col("payload").alias("held")), solved
        if it % checkpoint_every == 0 and it < iters:
            state, model = state.checkpoint(eager=True), solved.checkpoint(eager=True)
            frame = frame.checkpoint(eager=True) if joined else None
        if not direct:
            each = model.groupBy("row_block").agg(F.collect_list(F.struct("block", "w")).alias("models"))
            models = each.select(F.explode(F.sequence(F.col("row_block") * slots, F.col("row_block") * slots + slots - 1)).alias("slot"), "models")
        for f in drop:
            f()
        drop = [free_passed, free_solved, free_frame]
        profile.append((it, -1, "wall", time.perf_counter() - began))
        if watch is not None and not joined:
            watch(it, root)
    if joined:
        root.w_bar = [_flat(bytes(r["w_bar"]), cfg.m) for r in sorted(frame.select("col_block", "w_bar").collect(), key=lambda r: r["col_block"])]
    for f in drop:
        f()
    if factors is not None:
        factors.unpersist()
    return root, profile, cfg
