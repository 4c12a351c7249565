"""What one row block does in a round, and what the root does: plain NumPy, no Spark.

A round on a row block, given the consensus of the last one:

1. the duals of the local models catch up with the consensus that has just arrived;
2. the outputs move by the prox of the local loss;
3. for each column block the features are made, the local model is projected on the graph of the
   features, and the block's outputs enter two running sums, after which the features are dropped;
4. the output dual moves by the part of the gap that the exchange spread.

The state holds one output gap and one averaged output for all column blocks, not an output matrix for
each. `layout` selects other forms: "explicit" keeps an output matrix for every column block, "printed"
leaves out the output dual in the projection and updates duals with the old consensus (it stalls; for
tests), `gram_shortcut` forms Z'Z W from a stored Gram matrix, and `tile_rows` makes the features of so
many rows at a time: a block whose features don't fit in memory takes two transforms a round instead of one.

`weight_pull` is the step of the models in parts of rho, the outputs' step. At 1 the models of very many rows
hardly move: Z'Z grows with the rows, the pull to the consensus doesn't.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from kernelblocks.functions.featuremaps import Batch, FeatureMap, Sparse
from kernelblocks.functions.graphproj import Factor, factor, factor_of_gram
from kernelblocks.functions.prox import loss_of, reg_of
from kernelblocks.functions.rng import generator


@dataclass(frozen=True)
class SolverConfig:
    fmap: FeatureMap
    loss: str = "squared"
    reg: str = "ridge"
    lam: float = 1e-3
    rho: float = 1e-3
    n: int = 1
    m: int = 1
    rows: int = 1
    layout: str = "reorganized"
    cache: str = "inverse"
    gram_shortcut: bool = False
    block_fraction: float = 1.0
    threads: int = 1
    seed: int = 0
    tile_rows: int = 0
    weight_pull: float = 1.0

    @property
    def cols(self) -> int:
        return self.fmap.col_blocks

    def active(self, it: int) -> np.ndarray:
        """Column blocks that move in a round: a choice that depends on the seed and the round alone."""
        if self.block_fraction >= 1.0:
            return np.arange(self.cols)
        count = max(1, round(self.block_fraction * self.cols))
        return np.sort(generator(self.seed + (1 << 33), it).permutation(self.cols)[:count])


@dataclass
class BlockState:
    o_bar: np.ndarray
    nu: np.ndarray
    gap: np.ndarray
    w: list[np.ndarray]
    mu: list[np.ndarray]
    u: list[np.ndarray]
    q: list[Factor | None]
    gram: list[np.ndarray | None]
    own: list[np.ndarray] = field(default_factory=list)  # outputs by column block, explicit layout alone
    own_bar: list[np.ndarray] = field(default_factory=list)
    own_nu: list[np.ndarray] = field(default_factory=list)
    partial: np.ndarray | None = None  # running sum of all blocks' outputs, stochastic rounds alone
    seconds: dict[str, float] = field(default_factory=dict)

    @classmethod
    def zero(cls, n: int, cfg: SolverConfig) -> BlockState:
        def outputs():
            return np.zeros((n, cfg.m))

        def models():
            return [np.zeros((cfg.fmap.width(j), cfg.m)) for j in range(cfg.cols)]

        each = range(cfg.cols) if cfg.layout == "explicit" else ()
        return cls(
            outputs(), outputs(), outputs(), models(), models(), models(), [None] * cfg.cols, [None] * cfg.cols,
            [outputs() for _ in each], [outputs() for _ in each], [outputs() for _ in each],
            outputs() if cfg.block_fraction < 1.0 else None,
        )


class _Clock:
    def __init__(self, into: dict[str, float]) -> None:
        self.into, self.last = into, time.perf_counter()

    def lap(self, step: str) -> None:
        now = time.perf_counter()
        self.into[step] = self.into.get(step, 0.0) + now - self.last
        self.last = now


def _made(st: BlockState, x: Batch, j: int, cfg: SolverConfig, clock: _Clock) -> tuple[np.ndarray, Factor]:
    z = cfg.fmap.block(x, j)
    clock.lap("transform")
    q = st.q[j]
    if q is None:
        kind = "cholesky" if cfg.cache == "cholesky" else "inverse"
        q = factor(z, kind=kind, pull=cfg.weight_pull)
        if cfg.cache != "none":
            st.q[j] = q
        if cfg.gram_shortcut and st.gram[j] is None:
            st.gram[j] = z.T @ z
        clock.lap("factor")
    return z, q


def complete_factors(st: BlockState, x: Batch, cfg: SolverConfig) -> None:
    """Makes the factors of the column blocks that haven't moved yet, so that all can be kept apart from the state."""
    kind = "cholesky" if cfg.cache == "cholesky" else "inverse"
    for j in range(cfg.cols):
        if st.q[j] is None:
            if cfg.tile_rows:
                g = sum(z.T @ z for z in (cfg.fmap.block(tile, j) for tile, _ in _tiles(x, cfg.tile_rows)))
                st.gram[j], st.q[j] = g, factor_of_gram(g, "tall", kind, cfg.weight_pull)
            else:
                z = cfg.fmap.block(x, j)
                st.q[j] = factor(z, kind=kind, pull=cfg.weight_pull)
                if cfg.gram_shortcut:
                    st.gram[j] = z.T @ z


def _tiles(x: Batch, size: int):
    for k in range(0, x.shape[0], size):
        rows = slice(k, min(k + size, x.shape[0]))
        yield (x.rows(rows.start, rows.stop) if isinstance(x, Sparse) else x[rows]), rows


def row_block_step(st: BlockState, x: Batch, y: np.ndarray, w_bar: list[np.ndarray], it: int, cfg: SolverConfig) -> BlockState:
    """One round; st is changed and returned. st.seconds then has the time of each step."""
    if cfg.layout == "explicit":
        return _explicit_step(st, x, y, w_bar, it, cfg)
    st.seconds = {}
    clock = _Clock(st.seconds)
    loss, c = loss_of(cfg.loss), cfg.cols
    printed = cfg.layout == "printed"
    if it > 1 and not printed:
        for j in cfg.active(it - 1):
            st.mu[j] += st.w[j] - w_bar[j]
    o = loss.prox(st.o_bar - st.nu, y, 1.0 / (cfg.n * cfg.rho))
    clock.lap("prox")
    pull = st.gap / (c + 1) + (0.0 if printed else st.nu)
    gap = o.copy()
    o_bar = (c / (c + 1)) * o
    active = cfg.active(it)
    stochastic = st.partial is not None

    def one_tiled(j: int) -> np.ndarray:
        s_j, known = cfg.fmap.width(j), st.q[j] is not None
        a, g = np.zeros((s_j, cfg.m)), None if known else np.zeros((s_j, s_j))
        before = st.w[j]
        for tile, rows in _tiles(x, cfg.tile_rows):
            z = cfg.fmap.block(tile, j)
            clock.lap("transform")
            a += z.T @ pull[rows]
            if g is not None:
                g += z.T @ z
            clock.lap("projection")
        if g is not None:
            st.gram[j], st.q[j] = g, factor_of_gram(g, "tall", "cholesky" if cfg.cache == "cholesky" else "inverse", cfg.weight_pull)
            clock.lap("factor")
        st.w[j] = st.q[j].solve(None, cfg.weight_pull * (w_bar[j] - st.mu[j]) + st.u[j] + a)
        st.u[j] = st.gram[j] @ st.w[j]
        step = st.w[j] - before if stochastic else st.w[j]
        p = np.empty_like(o)
        for tile, rows in _tiles(x, cfg.tile_rows):
            z = cfg.fmap.block(tile, j)
            clock.lap("transform")
            p[rows] = z @ step
            clock.lap("projection")
        return p

    def one(j: int) -> np.ndarray:
        if cfg.tile_rows:
            return one_tiled(j)
        z, q = _made(st, x, j, cfg, clock)
        before = z @ st.w[j] if stochastic else None
        st.w[j] = q.solve(z, cfg.weight_pull * (w_bar[j] - st.mu[j]) + st.u[j] + z.T @ pull)
        p = z @ st.w[j]
        st.u[j] = st.gram[j] @ st.w[j] if st.gram[j] is not None else z.T @ p
        if printed:
            st.mu[j] += st.w[j] - w_bar[j]
        clock.lap("projection")
        return p if before is None else p - before

    if cfg.threads > 1:
        from concurrent.futures import ThreadPoolExecutor

        with ThreadPoolExecutor(cfg.threads) as pool:  # each thread's products are added when it is done: no lock
            parts = list(pool.map(one, active))
        total = sum(parts) if parts else np.zeros_like(o)
    else:
        total = np.zeros_like(o)
        for j in active:
            total += one(j)
    if stochastic:
        st.partial = st.partial + total
        total = st.partial
    gap -= total
    o_bar += total / (c + 1)
    st.nu = st.nu + o - o_bar
    st.gap, st.o_bar = gap, o_bar
    clock.lap("sums")
    return st


def _explicit_step(st: BlockState, x: Batch, y: np.ndarray, w_bar: list[np.ndarray], it: int, cfg: SolverConfig) -> BlockState:
    """The same round with an output, an averaged output and a dual for every column block."""
    st.seconds = {}
    clock = _Clock(st.seconds)
    c = cfg.cols
    if it > 1:
        for j in range(c):
            st.mu[j] += st.w[j] - w_bar[j]
    o = loss_of(cfg.loss).prox(st.o_bar - st.nu, y, 1.0 / (cfg.n * cfg.rho))
    clock.lap("prox")
    for j in range(c):
        z, q = _made(st, x, j, cfg, clock)
        target = st.own_bar[j] - st.own_nu[j]
        st.own[j], st.w[j] = q.project(z, target, w_bar[j] - st.mu[j])
        clock.lap("projection")
    share = (o - sum(st.own)) / (c + 1)
    o_bar = o - share
    for j in range(c):
        st.own_bar[j] = st.own[j] + share
        st.own_nu[j] = st.own_nu[j] + st.own[j] - st.own_bar[j]
    st.nu = st.nu + o - o_bar
    st.o_bar = o_bar
    clock.lap("sums")
    return st


@dataclass
class Root:
    """The model's own copy, its dual and the consensus."""

    w: list[np.ndarray]
    mu: list[np.ndarray]
    w_bar: list[np.ndarray]

    @classmethod
    def zero(cls, cfg: SolverConfig) -> Root:
        def models():
            return [np.zeros((cfg.fmap.width(j), cfg.m)) for j in range(cfg.cols)]

        return cls(models(), models(), models())


def root_prox(root: Root, it: int, cfg: SolverConfig) -> None:
    """The root's part of a round before the reduce."""
    reg = reg_of(cfg.reg)
    if it > 1 and cfg.layout != "printed":
        for j in cfg.active(it - 1):
            root.mu[j] += root.w[j] - root.w_bar[j]
    for j in cfg.active(it):
        root.w[j] = reg.prox(root.w_bar[j] - root.mu[j], cfg.lam / (cfg.rho * cfg.weight_pull))
        if cfg.layout == "printed":
            root.mu[j] += root.w[j] - root.w_bar[j]


def root_reduce(root: Root, sums: dict[int, np.ndarray], it: int, cfg: SolverConfig) -> None:
    for j in cfg.active(it):
        root.w_bar[j] = (root.w[j] + sums[j]) / (cfg.rows + 1)


def solve_local(
    xs: list[Batch], ys: list[np.ndarray], cfg: SolverConfig, iters: int, watch=None
) -> tuple[Root, list[BlockState]]:
    """All row blocks in one process: the reference that the distributed solver must equal."""
    states = [BlockState.zero(x.shape[0], cfg) for x in xs]
    root = Root.zero(cfg)
    for it in range(1, iters + 1):
        root_prox(root, it, cfg)
        states = [row_block_step(s, x, y, root.w_bar, it, cfg) for s, x, y in zip(states, xs, ys, strict=True)]
        root_reduce(root, {j: sum(s.w[j] for s in states) for j in cfg.active(it)}, it, cfg)
        if watch is not None:
            watch(it, root)
    return root, states
