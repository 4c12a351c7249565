"""Cumulative-link (proportional odds) regression on sparse rows, fitted on the driver from a bounded sample.

One weight vector is shared by all grades: P(grade >= k) = logistic(w.x - theta_k), with the
thresholds theta_1 < theta_2 < ... kept in order by positive increments. A grade that the sample
lacks keeps a threshold from smoothed counts; an empty sample gives a model of zero weights.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Rows:
    """Sparse rows: row i holds columns idx[ptr[i]:ptr[i+1]] with values val."""

    ptr: np.ndarray
    idx: np.ndarray
    val: np.ndarray
    width: int

    @classmethod
    def of(cls, rows: list[tuple[np.ndarray, np.ndarray]], width: int) -> Rows:
        ptr = np.cumsum([0] + [len(i) for i, _ in rows])
        none = np.zeros(0)
        return cls(
            ptr,
            np.concatenate([i for i, _ in rows] or [none]).astype(np.int64),
            np.concatenate([v for _, v in rows] or [none]).astype(np.float64),
            width,
        )

    def dot(self, w: np.ndarray) -> np.ndarray:
        sums = np.concatenate(([0.0], np.cumsum(w[self.idx] * self.val)))
        return sums[self.ptr[1:]] - sums[self.ptr[:-1]]

    def back(self, g: np.ndarray) -> np.ndarray:
        return np.bincount(self.idx, weights=np.repeat(g, np.diff(self.ptr)) * self.val, minlength=self.width)


def logistic(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1.0 + np.tanh(0.5 * x))


@dataclass
class OrdinalModel:
    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, scores: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1, 2, ...; a column for each threshold."""
        return logistic(scores[:, None] - self.thresholds[None, :])

    def expected(self, scores: np.ndarray) -> np.ndarray:
        return self.tails(scores).sum(axis=1)

    def grade(self, scores: np.ndarray) -> np.ndarray:
        """The largest grade whose tail is one half or more."""
        return (self.tails(scores) >= 0.5).sum(axis=1)


def _unpack(theta: np.ndarray) -> np.ndarray:
    return np.cumsum(np.concatenate((theta[:1], np.exp(theta[1:]))))


def loss_and_gradient(p: np.ndarray, x: Rows, y: np.ndarray, k: int, l2: float) -> tuple[float, np.ndarray]:
    d = x.width
    w, raw = p[:d], p[d:]
    cuts = np.concatenate(([-np.inf], _unpack(raw), [np.inf]))
    s = x.dot(w)
    up, low = logistic(s - cuts[y]), logistic(s - cuts[y + 1])
    prob = np.maximum(up - low, 1e-12)
    n = max(len(y), 1)
    value = -np.log(prob).sum() / n + 0.5 * l2 * (w @ w)
    du, dl = up * (1 - up), low * (1 - low)
    ds = -(du - dl) / prob / n
    grad_w = x.back(ds) + l2 * w
    g_cut = np.bincount(y, weights=du / prob / n, minlength=k)[1:] - np.bincount(y + 1, weights=dl / prob / n, minlength=k)[1:k]
    tail = np.cumsum(g_cut[::-1])[::-1]
    g_raw = np.concatenate((tail[:1], tail[1:] * np.exp(raw[1:])))
    return value, np.concatenate((grad_w, g_raw))


def fit(x: Rows, y: np.ndarray, grades: int, l2: float = 1e-4, rounds: int = 120, memory: int = 8) -> OrdinalModel:
    """Limited-memory quasi-Newton with backtracking; the objective is the mean loss plus l2/2 |w|^2."""
    share = (np.bincount(y, minlength=grades) + 0.5) / (len(y) + 0.5 * grades)
    above = np.cumsum(share[::-1])[::-1][1:]
    cut = -np.log(above / (1 - above))
    raw = np.concatenate((cut[:1], np.log(np.maximum(np.diff(cut), 1e-3))))
    p = np.concatenate((np.zeros(x.width), raw))
    if not len(y):
        return OrdinalModel(p[: x.width], _unpack(raw))
    value, grad = loss_and_gradient(p, x, y, grades, l2)
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(rounds):
        step = -_two_loop(grad, pairs)
        slope, size = step @ grad, 1.0
        if slope >= 0:
            step, slope = -grad, -(grad @ grad)
        while size > 1e-8:
            v2, g2 = loss_and_gradient(p + size * step, x, y, grades, l2)
            if v2 <= value + 1e-4 * size * slope:
                break
            size /= 2
        else:
            break
        s, t = size * step, g2 - grad
        if s @ t > 1e-12:
            pairs = [*pairs, (s, t)][-memory:]
        done = value - v2 < 1e-9 * max(1.0, abs(value))
        p, value, grad = p + s, v2, g2
        if done:
            break
    return OrdinalModel(p[: x.width], _unpack(p[x.width :]))


def _two_loop(grad: np.ndarray, pairs: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    q, seen = grad.copy(), []
    for s, t in reversed(pairs):
        a = (s @ q) / (s @ t)
        q -= a * t
        seen.append(a)
    if pairs:
        s, t = pairs[-1]
        q *= (s @ t) / (t @ t)
    for (s, t), a in zip(pairs, reversed(seen), strict=True):
        q += (a - (t @ q) / (s @ t)) * s
    return q
