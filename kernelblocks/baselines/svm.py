"""Kernel support vector machines: working sets on the driver, and a low-rank factor with interior point steps.

Both minimize mean hinge + lam |f|^2, in the dual with box [0, cost], cost = 1/(2 n lam). Rows that are alike in input
and target have one variable with the box of them all, which they share evenly: the optimum is that of all rows.
"""

from __future__ import annotations

import pickle
from collections import OrderedDict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kernelblocks.baselines.ridge import DualModel, local_rows
from kernelblocks.functions.kernels import Kernel
from kernelblocks.plans.blocks import pack, unpack_batch
from kernelblocks.storage import ensure_checkpoint_dir, kept_flat

#: Above so many rows the pairs are chosen inside working sets of so many variables.
PAIR_ROWS = 20_000
WORKING_SET = 512
#: A factor of up to so many bytes comes to the driver; the steps of a larger one are taken where its rows lie.
DRIVER_FACTOR_BYTES = 8 << 20


def alike(df: DataFrame) -> DataFrame:
    """(row_id, x, y): one row, of the least id, for rows alike in x and y; y is the target and the number of them."""
    y = F.transform("y", lambda v: v.cast("double"))
    merged = df.groupBy("x", y.alias("y")).agg(F.min("row_id").alias("row_id"), F.count("*").cast("double").alias("count"))
    return merged.select("row_id", "x", F.array(F.element_at("y", 1), "count").alias("y"))


class _KernelRows:
    """Rows of the kernel matrix, the most recent ones kept."""

    def __init__(self, x: np.ndarray, kernel: Kernel, keep: int) -> None:
        self.x, self.kernel, self.keep = x, kernel, keep
        self.rows: OrderedDict[int, np.ndarray] = OrderedDict()

    def __getitem__(self, i: int) -> np.ndarray:
        row = self.rows.get(i)
        if row is None:
            row = self.kernel(self.x[i : i + 1], self.x)[0]
            self.rows[i] = row
            if len(self.rows) > self.keep:
                self.rows.popitem(last=False)
        else:
            self.rows.move_to_end(i)
        return row


def smo(
    x: np.ndarray, y: np.ndarray, kernel: Kernel, cost: float, tol: float = 1e-3, cache_rows: int = 2000, max_steps: int = 1_000_000, bias: bool = True, counts: np.ndarray | None = None
) -> DualModel:
    """With a bias: pairs chosen by the largest violation and the best second-order gain. Without: one variable at a time.

    A row stands for counts rows like it, one where there are no counts.
    """
    n = len(y)
    counts = np.ones(n) if counts is None else counts
    cost = cost * counts
    rows = _KernelRows(x, kernel, cache_rows)
    diag = np.array([kernel(x[i : i + 1], x[i : i + 1])[0, 0] for i in range(n)])
    alpha, grad = np.zeros(n), -np.ones(n)  # gradient of a'Qa/2 - 1'a
    steps = 0
    for steps in range(1, max_steps + 1):  # noqa: B007
        if bias:
            up = ((y > 0) & (alpha < cost)) | ((y < 0) & (alpha > 0))
            low = ((y < 0) & (alpha < cost)) | ((y > 0) & (alpha > 0))
            score = -y * grad
            if not up.any() or not low.any():
                break
            i = int(np.argmax(np.where(up, score, -np.inf)))
            if score[i] - np.where(low, score, np.inf).min() < tol:
                break
            ki = rows[i]
            gap = score[i] - score
            curve = np.maximum(diag[i] + diag - 2 * ki, 1e-12)
            j = int(np.argmax(np.where(low & (gap > 0), gap * gap / curve, -np.inf)))
            kj = rows[j]
            move = gap[j] / curve[j]
            room_i = cost[i] - alpha[i] if y[i] > 0 else alpha[i]
            room_j = alpha[j] if y[j] > 0 else cost[j] - alpha[j]
            move = min(move, room_i, room_j)
            alpha[i] += y[i] * move
            alpha[j] -= y[j] * move
            grad += y * move * (ki - kj)
        else:
            step = np.clip(alpha - grad / np.maximum(diag, 1e-12), 0, cost) - alpha
            i = int(np.argmax(np.abs(step) * np.sqrt(diag)))
            if abs(step[i]) * diag[i] < tol:
                break
            alpha[i] += step[i]
            grad += step[i] * y[i] * y * rows[i]
    alpha = np.clip(alpha, 0, cost)
    b = 0.0
    if bias:
        score = -y * grad
        free = (alpha > 1e-9 * cost) & (alpha < cost * (1 - 1e-9))
        if free.any():
            b = float(score[free].mean())
        else:
            up = ((y > 0) & (alpha < cost)) | ((y < 0) & (alpha > 0))
            low = ((y < 0) & (alpha < cost)) | ((y > 0) & (alpha > 0))
            b = float((np.where(up, score, -np.inf).max() + np.where(low, score, np.inf).min()) / 2)
    kept = alpha > 1e-9 * cost
    return DualModel(x[kept], (alpha * y)[kept, None], kernel, int(counts[kept].sum()), b, rounds=steps)


def smo_svm(df: DataFrame, kernel: Kernel, lam: float, tol: float = 1e-3, bias: bool = True) -> DualModel:
    """The sequential exact solver, on a table whose rows the driver can hold; of the kernel it holds parts alone."""
    _, x, y = local_rows(alike(df), None)
    fit = smo if not bias or len(y) <= PAIR_ROWS else working_set_smo
    return fit(x, y[:, 0], kernel, 1.0 / (2 * y[:, 1].sum() * lam), tol, bias=bias, counts=y[:, 1])


def working_set_smo(x: np.ndarray, y: np.ndarray, kernel: Kernel, cost: float, tol: float = 1e-3, max_sets: int = 100_000, bias: bool = True, size: int = WORKING_SET, counts: np.ndarray | None = None) -> DualModel:
    """smo for many rows, all of them in the problem: pairs move inside a set of the largest violations, to the same
    tolerance, and the gradient of all rows follows once for each set."""
    n = len(y)
    counts = np.ones(n) if counts is None else counts
    cost = cost * counts
    alpha, grad = np.zeros(n), -np.ones(n)
    steps, half, strip = 0, size // 2, 8192
    for _ in range(max_sets):
        up = ((y > 0) & (alpha < cost)) | ((y < 0) & (alpha > 0))
        low = ((y < 0) & (alpha < cost)) | ((y > 0) & (alpha > 0))
        score = -y * grad
        if not up.any() or not low.any() or score[up].max() - score[low].min() < tol:
            break
        first, last = np.where(up, score, -np.inf), np.where(low, -score, -np.inf)
        ids = [np.argpartition(-v, min(half, n - 1))[:half] for v in (first, last)]
        own = np.unique(np.concatenate([i[np.isfinite(v[i])] for i, v in zip(ids, (first, last), strict=True)]))
        xo, yo, co, a, g = x[own], y[own], cost[own], alpha[own].copy(), grad[own].copy()
        k = kernel(xo, xo)
        diag, goal = np.diag(k), max(tol / 2, 0.1 * float(score[up].max() - score[low].min()))
        for _ in range(20 * size):
            up = ((yo > 0) & (a < co)) | ((yo < 0) & (a > 0))
            low = ((yo < 0) & (a < co)) | ((yo > 0) & (a > 0))
            score = -yo * g
            if not up.any() or not low.any():
                break
            i = int(np.argmax(np.where(up, score, -np.inf)))
            if score[i] - np.where(low, score, np.inf).min() < goal:
                break
            gap = score[i] - score
            curve = np.maximum(diag[i] + diag - 2 * k[i], 1e-12)
            j = int(np.argmax(np.where(low & (gap > 0), gap * gap / curve, -np.inf)))
            room_i = co[i] - a[i] if yo[i] > 0 else a[i]
            room_j = a[j] if yo[j] > 0 else co[j] - a[j]
            move = min(gap[j] / curve[j], room_i, room_j)
            # a variable that takes all of its room lies on its bound exactly
            a[i] = (co[i] if yo[i] > 0 else 0.0) if move == room_i else a[i] + yo[i] * move
            a[j] = (0.0 if yo[j] > 0 else co[j]) if move == room_j else a[j] - yo[j] * move
            g += yo * move * (k[i] - k[j])
            steps += 1
        moved = (a - alpha[own]) * yo
        alpha[own] = a
        some = np.flatnonzero(moved)
        for at in range(0, n, strip):
            part = slice(at, at + strip)
            grad[part] += y[part] * (kernel(x[part], xo[some]) @ moved[some])
    return _dual_model(x, y, alpha, grad, kernel, cost, steps, counts)


def _dual_model(x: np.ndarray, y: np.ndarray, alpha: np.ndarray, grad: np.ndarray, kernel: Kernel, cost: np.ndarray, steps: int, counts: np.ndarray) -> DualModel:
    score = -y * grad
    free = (alpha > 1e-9 * cost) & (alpha < cost * (1 - 1e-9))
    up = ((y > 0) & (alpha < cost)) | ((y < 0) & (alpha > 0))
    low = ((y < 0) & (alpha < cost)) | ((y > 0) & (alpha > 0))
    b = float(score[free].mean()) if free.any() else float((np.where(up, score, -np.inf).max() + np.where(low, score, np.inf).min()) / 2)
    kept = alpha > 1e-9 * cost
    return DualModel(x[kept], (alpha * y)[kept, None], kernel, int(counts[kept].sum()), b, rounds=steps)


def incomplete_cholesky(df: DataFrame, kernel: Kernel, rank: int, pivots_per_pass: int = 8, tol: float = 1e-10, rows: int | None = None):
    """K ~ H H' with rows of H beside the examples.

    Each pass takes the rows of the largest residual as pivots, orders them on the driver, and every
    task adds the new columns for its rows. Returns (frame of packed blocks with their factor, the pivots'
    rows of x and the triangle that maps kernel rows to columns).
    """
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    rows = rows or spark.sparkContext.defaultParallelism
    packed = pack(df, rows).select("row_block", "n", "d", "x", "y", "ids", F.lit(None).cast("binary").alias("h")).checkpoint()
    px, ph = None, np.zeros((0, 0))
    columns = 0
    schema = packed.schema
    while columns < rank:
        take = min(pivots_per_pass, rank - columns)

        def top(batches: Iterator[pa.RecordBatch], take=take) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for r in range(b.num_rows):
                    n, d = b.column(1)[r].as_py(), b.column(2)[r].as_py()
                    x = unpack_batch(b.column(3)[r].as_py(), d)
                    ids = np.frombuffer(b.column(5)[r].as_py(), "<i8")
                    raw = b.column(6)[r].as_py()
                    h = np.frombuffer(raw, "<f8").reshape(n, -1) if raw is not None else np.zeros((n, 0))
                    left = np.array([kernel(x[i : i + 1], x[i : i + 1])[0, 0] for i in range(n)]) - (h * h).sum(axis=1)
                    best = np.lexsort((ids, -left))[:take]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(left[best]), pa.array(ids[best]), pa.array([pickle.dumps((x[i], h[i])) for i in best], pa.binary())], names=["left", "id", "row"]
                    )

        picked = packed.mapInArrow(top, "left double, id long, row binary").orderBy(F.desc("left"), "id").limit(take).collect()
        picked = [p for p in picked if p["left"] > tol]
        if not picked:
            break
        x_new = np.array([pickle.loads(bytes(p["row"]))[0] for p in picked])
        h_new = np.array([pickle.loads(bytes(p["row"]))[1] for p in picked]).reshape(len(picked), columns)
        schur = kernel(x_new, x_new) - h_new @ h_new.T
        # pivots of one pass can depend on each other: those without residual of their own fall away
        use, low = [], np.zeros((0, 0))
        for i in range(len(picked)):
            cross = np.linalg.solve(low, schur[use, i]) if use else np.zeros(0)
            rest = schur[i, i] - cross @ cross
            if rest > tol:
                grown = np.zeros((len(use) + 1, len(use) + 1))
                grown[: len(use), : len(use)] = low
                grown[-1, : len(use)], grown[-1, -1] = cross, np.sqrt(rest)
                use, low = [*use, i], grown
        x_new, h_new = x_new[use], h_new[use]
        sent = spark.sparkContext.broadcast((x_new, h_new, low))

        def extend(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            xp, hp, tri = sent.value
            for b in batches:
                out = []
                for r in range(b.num_rows):
                    n, d = b.column(1)[r].as_py(), b.column(2)[r].as_py()
                    x = unpack_batch(b.column(3)[r].as_py(), d)
                    raw = b.column(6)[r].as_py()
                    h = np.frombuffer(raw, "<f8").reshape(n, -1) if raw is not None else np.zeros((n, 0))
                    more = np.linalg.solve(tri, (kernel(x, xp) - h @ hp.T).T).T
                    out.append(np.hstack((h, more)).tobytes())
                yield pa.RecordBatch.from_arrays([*b.columns[:6], pa.array(out, pa.binary())], names=b.schema.names)

        packed = packed.mapInArrow(extend, schema).checkpoint()
        grown = np.zeros((columns + len(use), columns + len(use)))
        grown[:columns, :columns] = ph
        grown[columns:, :columns], grown[columns:, columns:] = h_new, low
        px = x_new if px is None else np.vstack((px, x_new))
        ph, columns = grown, columns + len(use)
    return packed, px, ph


def interior_point_svm(h: np.ndarray, y: np.ndarray, cost: float | np.ndarray, tol: float = 1e-8, max_steps: int = 60) -> np.ndarray:
    """Dual variables for the kernel h h' by primal-dual steps; each solves one p x p system by the inversion lemma."""
    n, p = h.shape
    g = h * y[:, None]
    cost = np.broadcast_to(np.asarray(cost, float), n)
    a = cost / 2
    low, high = np.ones(n), np.ones(n)  # multipliers of a >= 0 and a <= cost
    for _ in range(max_steps):
        slope = g @ (g.T @ a) - 1.0
        mu = (low @ a + high @ (cost - a)) / (2 * n)
        dual = slope - low + high
        if mu < tol * cost.mean() and np.abs(dual).max() < 1e-6:
            break
        aim = 0.1 * mu
        weight = low / a + high / (cost - a)
        r = -slope + aim / a - aim / (cost - a)
        inv = 1.0 / weight
        core = np.eye(p) + (g * inv[:, None]).T @ g
        step = inv * (r - g @ np.linalg.solve(core, g.T @ (inv * r)))
        d_low = aim / a - low - low / a * step
        d_high = aim / (cost - a) - high + high / (cost - a) * step

        def room(v, dv):
            neg = dv < 0
            return min(1.0, float(0.99 * (-v[neg] / dv[neg]).min())) if neg.any() else 1.0

        t = min(room(a, step), room(cost - a, -step))
        s = min(room(low, d_low), room(high, d_high))
        a, low, high = a + t * step, low + s * d_low, high + s * d_high
    return a


def _interior_terms(a, low, high, g, v, mu, cost):
    """(slope's residual, weights' inverses, right side) at a point whose g'a is v."""
    slope, aim = g @ v - 1.0, 0.1 * mu
    inv = 1.0 / (low / a + high / (cost - a))
    return slope - low + high, inv, -slope + aim / a - aim / (cost - a), aim


def _room(v: np.ndarray, dv: np.ndarray) -> float:
    neg = dv < 0
    return min(1.0, float(0.99 * (-v[neg] / dv[neg]).min())) if neg.any() else 1.0


INNER = "row_block int, kind string, payload binary"


def interior_point_blocks(packed: DataFrame, cost: float, tol: float = 1e-8, max_steps: int = 60) -> tuple[np.ndarray, int]:
    """(H'(alpha y), number of support vectors) for packed row blocks (row_block, n, y, h), which stay where they are.

    y is the target and the number of rows that a row stands for.

    The steps of interior_point_svm: a first pass gives each block's p x p and p sums, which are added up, a second
    the step of its rows and how far it may go. Only sums come to the driver.
    """
    spark = packed.sparkSession
    base = packed.select("row_block", "n", "y", "h").repartition(max(1, packed.count()), "row_block").persist()
    n, packed_rows = base.agg(F.sum("n"), F.count("*")).first()
    p = base.select((F.length("h") / F.col("n") / 8).cast("int")).first()[0]

    def one_pass(state: DataFrame | None, work) -> tuple[DataFrame, DataFrame, object]:
        joined = base.withColumn("state", F.lit(None).cast("binary")) if state is None else base.join(state, "row_block")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for r in range(b.num_rows):
                    block, count, raw_y, raw_h, held = (b.column(k)[r].as_py() for k in range(5))
                    y, counts = np.frombuffer(raw_y, "<f8").reshape(count, 2).T
                    g = np.frombuffer(raw_h, "<f8").reshape(count, -1) * y[:, None]
                    rows = np.frombuffer(held, "<f8").reshape(-1, count) if held is not None else np.vstack((cost * counts / 2, np.ones((2, count))))
                    new, sums = work(rows, g, counts)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([block, block], pa.int32()), pa.array(["state", "sums"]), pa.array([new.tobytes(), sums.tobytes()], pa.binary())],
                        names=["row_block", "kind", "payload"],
                    )

        out, let_go = kept_flat(joined.select("row_block", "n", "y", "h", "state").mapInArrow(run, INNER))
        return out, out.where("kind = 'sums'").select("row_block", "payload"), let_go

    def added(sums: DataFrame) -> np.ndarray:
        """The sums of all blocks, in two levels where they are large."""

        def add(table: pa.Table) -> pa.Table:
            order = np.argsort(table.column("row_block").to_numpy(), kind="stable")
            total = sum(np.frombuffer(table.column("payload")[int(i)].as_py(), "<f8") for i in order)
            return pa.table({"row_block": table.column("row_block").slice(0, 1), "payload": pa.array([total.tobytes()], pa.binary())})

        width = max(1, int(packed_rows ** 0.5)) if p > 512 else 0
        if width:
            sums = sums.withColumn("part", (F.col("row_block") / width).cast("int")).groupBy("part").applyInArrow(lambda _, t: add(t), "row_block int, payload binary")
        rows = sorted(sums.collect(), key=lambda r: r["row_block"])
        return sum(np.frombuffer(bytes(r["payload"]), "<f8") for r in rows)

    v, mu, moved = None, None, (0.0, 0.0)
    state, drop, support = None, [], 0

    def start(rows, g, counts):
        a, low, high = rows[:3]
        return rows[:3], np.concatenate((g.T @ a, [low @ a + high @ (cost * counts - a), counts.sum()]))

    out, sums, let_go = one_pass(None, start)
    total = added(sums)
    v, mu, close = total[:p], total[p] / (2 * n), tol * cost * total[p + 1] / n
    state = out.where("kind = 'state'").select("row_block", F.col("payload").alias("state"))
    drop.append(let_go)
    for it in range(max_steps):
        t, s = moved
        at = spark.sparkContext.broadcast((v, mu))

        def first(rows, g, counts, t=t, s=s, at=at):
            v, mu = at.value
            now = rows if len(rows) == 3 else np.vstack((rows[0] + t * rows[3], rows[1] + s * rows[4], rows[2] + s * rows[5]))
            gap, inv, r, _ = _interior_terms(*now, g, v, mu, cost * counts)
            core = (g * inv[:, None]).T @ g
            # the largest gap travels as a high power of it, so that it adds up like the rest
            return now, np.concatenate((core.ravel(), g.T @ (inv * r), [np.abs(gap).max() ** 16, counts[now[0] > 1e-6 * cost * counts].sum()]))

        out, sums, let_go = one_pass(state, first)
        drop.append(let_go)
        total = added(sums)
        support = int(total[-1])
        state = out.where("kind = 'state'").select("row_block", F.col("payload").alias("state"))
        if mu < close and total[-2] < 1e-96:
            break
        q = np.linalg.solve(np.eye(p) + total[: p * p].reshape(p, p), total[p * p : p * p + p])
        sent = spark.sparkContext.broadcast((v, mu, q))

        def second(rows, g, counts, sent=sent):
            v, mu, q = sent.value
            (a, low, high), box = rows, cost * counts
            _, inv, r, aim = _interior_terms(a, low, high, g, v, mu, box)
            step = inv * (r - g @ q)
            d_low = aim / a - low - low / a * step
            d_high = aim / (box - a) - high + high / (box - a) * step
            rooms = [min(_room(a, step), _room(box - a, -step)), min(_room(low, d_low), _room(high, d_high))]
            pairs = [low @ a + high @ (box - a), (low - high) @ step, d_low @ a + d_high @ (box - a), (d_low - d_high) @ step]
            return np.vstack((rows, step, d_low, d_high)), np.concatenate((rooms, pairs, g.T @ step))

        out, sums, let_go = one_pass(state, second)
        drop.append(let_go)
        parts = [np.frombuffer(bytes(r["payload"]), "<f8") for r in sorted(sums.collect(), key=lambda r: r["row_block"])]
        t, s = (min(x[k] for x in parts) for k in (0, 1))
        total = sum(parts)
        state = out.where("kind = 'state'").select("row_block", F.col("payload").alias("state"))
        if it % 5 == 4:
            state = state.checkpoint(eager=True)
        v = v + t * total[6:]
        mu = (total[2] + t * total[3] + s * total[4] + s * t * total[5]) / (2 * n)
        moved = (t, s)
        for f in drop[:-2]:
            f()
        drop = drop[-2:]
    for f in drop:
        f()
    base.unpersist()
    return v, support


def lowrank_svm(df: DataFrame, kernel: Kernel, lam: float, rank: int | None = None, pivots_per_pass: int = 8) -> DualModel:
    """Parallel low-rank kernel machine; the rank defaults to the root of the number of rows."""
    merged = alike(df).persist()
    total, n = merged.agg(F.sum(F.element_at("y", 2)), F.count("*")).first()
    rank = rank or max(1, round(total**0.5))
    packed, px, tri = incomplete_cholesky(merged, kernel, rank, pivots_per_pass)
    merged.unpersist()
    cost = 1.0 / (2 * total * lam)
    # f(x) = h(x)' H'(alpha y) with h(x) = tri^-1 k(pivots, x): a function of the pivots alone
    if n * len(px) * 8 > DRIVER_FACTOR_BYTES:
        v, support = interior_point_blocks(packed, cost)
    else:
        got = packed.select("n", "y", "h").collect()
        h = np.vstack([np.frombuffer(bytes(r["h"]), "<f8").reshape(r["n"], -1) for r in got])
        y, counts = np.concatenate([np.frombuffer(bytes(r["y"]), "<f8").reshape(-1, 2) for r in got]).T
        alpha = interior_point_svm(h, y, cost * counts)
        v, support = h.T @ (alpha * y), int(counts[alpha > 1e-6 * cost * counts].sum())
    return DualModel(px, np.linalg.solve(tri.T, v)[:, None], kernel, support)
