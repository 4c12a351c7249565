"""How rows and features are cut in blocks, and what a plan costs in memory, work and communication."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

BYTES = 8


def block_bounds(n: int, parts: int) -> np.ndarray:
    """Bounds of parts blocks of 0..n; the first n mod parts blocks hold one more."""
    size, more = divmod(n, parts)
    return np.concatenate(([0], np.cumsum([size + (k < more) for k in range(parts)]))).astype(np.int64)


@dataclass(frozen=True)
class BlockPlan:
    rows: int
    cols: int


def suggest_blocks(n: int, d: int, m: int, s: int, nodes: int, memory_bytes: float, threads: int = 1) -> BlockPlan:
    """One row block for each node; as many column blocks as features over inputs, then more until a node's share fits."""
    cols = max(1, round(s / max(d, 1)), threads)
    while cols < s and memory_model(n, m, d, s, cols, nodes, nodes, threads)["total"] * BYTES > memory_bytes:
        cols = min(s, cols * 2)
    return BlockPlan(nodes, cols)


def memory_model(n: int, m: int, d: int, s: int, cols: int, rows: int, nodes: int, threads: int) -> dict[str, float]:
    """Numbers held by a process that has one row block, by part; total_node counts the processes of a node."""
    part = {
        "data": n * (m + d) / rows,
        "model_state": 5.0 * s * m,
        "output_state": 4.0 * n * m / rows,
        "column_work": threads * (n * s / (rows * cols) + m * s / cols),
        "output_work": (threads + 1) * n * m / rows,
        "factors": s * s / cols,
    }
    part["total"] = sum(part.values())
    part["total_node"] = part["total"] * rows / nodes
    return part


def memory_model_node(n: int, m: int, d: int, s: int, cols: int, nodes: int, threads: int) -> dict[str, float]:
    """Numbers held by a node that has one row block and works on threads column blocks at once, by part.

    The same parts as memory_model with as many row blocks as nodes, the outputs of all threads counted together.
    """
    share = n / nodes
    part = {
        "data": share * (m + d),
        "model_state": 5.0 * s * m,
        "output_state": (threads + 5) * share * m,
        "features": threads * share * s / cols,
        "column_models": threads * m * s / cols,
        "factors": s * s / cols,
    }
    part["total"] = sum(part.values())
    return part


def memory_model_simple(n: int, m: int, d: int, s: int, nodes: int, kappa: float = 1.0, threads: int = 1) -> float:
    """Numbers for each node where rows are cut by node and there are kappa s/d column blocks."""
    share = n / nodes
    return share * m * (threads + 6) + share * d + 5.0 * s * m + (threads * share * d + threads * m * d + s * d) / kappa


def materialized_bytes(n: int, s: int) -> float:
    return float(n) * s * BYTES


def flop_model(n: int, m: int, d: int, s: int, cols: int, rows: int, gram_shortcut: bool = False) -> dict[str, float]:
    """Multiplications of one round by step, over all row blocks."""
    return {
        "transform": float(n) * d * s,
        "sums": float(n) * m * cols,
        "solves": float(rows) * s * s * m / cols,
        "products": (2.0 if gram_shortcut else 3.0) * n * s * m,
        "factor_once": float(n) * s * s / cols + rows * float(s) ** 3 / cols**2,
    }


def comm_model(s: int, m: int, nodes: int) -> dict[str, float]:
    """Bytes of the model buffer and of a round's broadcast and reduce along a tree."""
    buffer = float(s) * m * BYTES
    return {"buffer": buffer, "round": 2.0 * buffer * max(1.0, math.log2(max(nodes, 2)))}
