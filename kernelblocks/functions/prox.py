"""Losses, regularizers and projections as proximal operators, with column twins.

prox of a loss at v with weight kappa: argmin_o kappa * loss(o, y) + |o - v|^2 / 2, row by row.
prox of a regularizer at v with weight tau: argmin_w tau * r(w) + |w - v|^2 / 2.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


class Loss(Protocol):
    name: str

    def value(self, o: np.ndarray, y: np.ndarray) -> float: ...

    def prox(self, v: np.ndarray, y: np.ndarray, kappa: float) -> np.ndarray: ...

    def slope(self, o: np.ndarray, y: np.ndarray) -> np.ndarray: ...


class Reg(Protocol):
    name: str

    def value(self, w: np.ndarray) -> float: ...

    def prox(self, v: np.ndarray, tau: float) -> np.ndarray: ...


def soft(v: np.ndarray, tau: float) -> np.ndarray:
    return np.sign(v) * np.maximum(np.abs(v) - tau, 0.0)


class Squared:
    """Sum of squares without a half."""

    name = "squared"

    def value(self, o, y):
        return float(((o - y) ** 2).sum())

    def prox(self, v, y, kappa):
        return (v + 2.0 * kappa * y) / (1.0 + 2.0 * kappa)

    def slope(self, o, y):
        return 2.0 * (o - y)


class Absolute:
    name = "absolute"

    def value(self, o, y):
        return float(np.abs(o - y).sum())

    def prox(self, v, y, kappa):
        return y + soft(v - y, kappa)

    def slope(self, o, y):
        return np.sign(o - y)


class Hinge:
    """Margins of outputs coded -1 and 1, each output by itself."""

    name = "hinge"

    def value(self, o, y):
        return float(np.maximum(0.0, 1.0 - o * y).sum())

    def prox(self, v, y, kappa):
        u = v * y
        return np.where(u >= 1.0, v, np.where(u <= 1.0 - kappa, v + kappa * y, y))

    def slope(self, o, y):
        return np.where(o * y < 1.0, -y, 0.0)


class Logistic:
    """Multinomial: y holds a one in the column of the class and minus one or zero elsewhere."""

    name = "logistic"
    most_steps = 60

    @staticmethod
    def _log_shares(o):
        o = o - o.max(axis=1, keepdims=True)
        return o - np.log(np.exp(o).sum(axis=1, keepdims=True))

    def value(self, o, y):
        return float(-self._log_shares(o)[y > 0].sum())

    def slope(self, o, y):
        return np.exp(self._log_shares(o)) - (y > 0)

    def prox(self, v, y, kappa):
        hit = (y > 0).astype(float)
        o = v.copy()

        def worth(o):
            return -kappa * (self._log_shares(o) * hit).sum(axis=1) + 0.5 * ((o - v) ** 2).sum(axis=1)

        at = worth(o)
        for _ in range(self.most_steps):
            p = np.exp(self._log_shares(o))
            g = kappa * (p - hit) + o - v
            if np.abs(g).max(initial=0.0) < 1e-12:
                break
            # (I + kappa (diag p - p p'))^-1 g by the rank-one correction
            dinv = 1.0 / (1.0 + kappa * p)
            dg, dp = dinv * g, dinv * p
            step = dg + dp * (kappa * (p * dg).sum(1) / (1.0 - kappa * (p * dp).sum(1)))[:, None]
            size = np.ones(len(o))
            for _ in range(30):
                new = o - size[:, None] * step
                got = worth(new)
                worse = got > at - 1e-4 * size * (g * step).sum(1) + 1e-15
                if not worse.any():
                    break
                size[worse] *= 0.5
            keep = got <= at
            o[keep], at[keep] = new[keep], got[keep]
            if not keep.any():
                break
        return o


class Ridge:
    name = "ridge"

    def value(self, w):
        return float((w * w).sum())

    def prox(self, v, tau):
        return v / (1.0 + 2.0 * tau)


class Lasso:
    name = "lasso"

    def value(self, w):
        return float(np.abs(w).sum())

    def prox(self, v, tau):
        return soft(v, tau)


class NoReg:
    name = "none"

    def value(self, w):
        return 0.0

    def prox(self, v, tau):
        return v


class GroupRows:
    """Sum of the lengths of rows: a feature's weights vanish together."""

    name = "group"

    def value(self, w):
        return float(np.sqrt((w * w).sum(axis=1)).sum())

    def prox(self, v, tau):
        size = np.sqrt((v * v).sum(axis=1, keepdims=True))
        return v * np.maximum(0.0, 1.0 - tau / np.maximum(size, 1e-300))


class ElasticNet:
    name = "elastic"

    def __init__(self, mix: float = 0.5) -> None:
        self.mix = mix

    def value(self, w):
        return float(self.mix * np.abs(w).sum() + (1.0 - self.mix) * (w * w).sum())

    def prox(self, v, tau):
        return soft(v, tau * self.mix) / (1.0 + 2.0 * tau * (1.0 - self.mix))


LOSSES: dict[str, type] = {c.name: c for c in (Squared, Absolute, Hinge, Logistic)}
REGS: dict[str, type] = {c.name: c for c in (Ridge, Lasso, NoReg, GroupRows, ElasticNet)}


def register_loss(name: str, cls: type) -> None:
    LOSSES[name] = cls


def register_reg(name: str, cls: type) -> None:
    REGS[name] = cls


def loss_of(what) -> Loss:
    return LOSSES[what]() if isinstance(what, str) else what


def reg_of(what) -> Reg:
    return REGS[what]() if isinstance(what, str) else what


# projections: the prox of a set's indicator


def onto_box(v, low, high):
    return np.clip(v, low, high)


def onto_nonnegative(v):
    return np.maximum(v, 0.0)


def onto_ball(v, radius):
    size = np.linalg.norm(v)
    return v if size <= radius else v * (radius / size)


def onto_affine(v, a, b):
    """Nearest point with a x = b, for a of full row rank."""
    return v - a.T @ np.linalg.solve(a @ a.T, a @ v - b)


def consensus_mean(w, parts):
    """The common value nearest to w and all parts."""
    return (w + sum(parts)) / (1 + len(parts))


def exchange(total, parts):
    """Nearest (total, parts) whose parts sum to the total: the gap is spread evenly over all terms."""
    share = (total - sum(parts)) / (len(parts) + 1)
    return total - share, [p + share for p in parts]


# column twins


def _soft_col(v: Column, tau) -> Column:
    return F.signum(v) * F.greatest(F.abs(v) - F.lit(tau), F.lit(0.0))


def prox_squared_col(v: Column, y: Column, kappa: float) -> Column:
    return (v + F.lit(2.0 * kappa) * y) / F.lit(1.0 + 2.0 * kappa)


def prox_absolute_col(v: Column, y: Column, kappa: float) -> Column:
    return y + _soft_col(v - y, kappa)


def prox_hinge_col(v: Column, y: Column, kappa: float) -> Column:
    u = v * y
    return F.when(u >= 1.0, v).when(u <= F.lit(1.0 - kappa), v + F.lit(kappa) * y).otherwise(y)


def prox_ridge_col(v: Column, tau: float) -> Column:
    return v / F.lit(1.0 + 2.0 * tau)


def prox_lasso_col(v: Column, tau: float) -> Column:
    return _soft_col(v, tau)
