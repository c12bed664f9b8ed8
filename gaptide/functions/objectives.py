"""Generalised linear models as f(v) + sum of g_i, v the weighted sum of the columns.

Each class gives f and its gradient, and for one coordinate the value g, the duality gap and the minimiser of the local
model, twice: as numpy functions for the fast tier and as Columns for plans. All gaps follow from one rule, the sum of
alpha * u, g(alpha) and the conjugate of g at -u, where u is the column's product with the gradient of f.

A coordinate's step minimises u * delta + curvature / 2 * delta**2 + g(alpha + delta), curvature being L times the
column's squared norm; for quadratic f this is exact. A zero column has no step (curvature 0 and u 0) but a gap.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def soft(x: np.ndarray, t: np.ndarray | float) -> np.ndarray:
    return np.sign(x) * np.maximum(np.abs(x) - t, 0)


def soft_col(x: Column, t: Column) -> Column:
    return F.signum(x) * F.greatest(F.abs(x) - t, F.lit(0.0))


def clip_col(x: Column, lo: float, hi: float) -> Column:
    return F.greatest(F.lit(lo), F.least(F.lit(hi), x))


@dataclass
class Objective:
    """lam scales the regulariser. b is the target of each row where f is a data fit; y the target of each coordinate of a dual."""

    lam: float = 1.0
    b: np.ndarray | None = field(default=None, repr=False)
    name = "objective"
    quadratic = True
    uses_target = False  # whether g_i has a target of its own (column y)
    rests = False  # whether a coordinate's step is 0 for a range of products

    def __post_init__(self):
        if not self.lam > 0:
            raise ValueError("lam must be above 0")

    # --- f
    def f(self, v: np.ndarray) -> float:
        r = v - self.b
        return 0.5 * float(r @ r)

    def grad(self, v: np.ndarray) -> np.ndarray:
        return v - self.b

    def f_conj(self, w: np.ndarray) -> float:
        return 0.5 * float(w @ w) + float(w @ self.b)

    smooth = 1.0
    strong = 0.0  # strong convexity of each g_i
    bound = None  # bound of each g_i's support

    def constants(self) -> dict[str, float | None]:
        return {"L": self.smooth, "mu": self.strong, "B": self.bound}

    # --- one coordinate, numpy; y is the coordinate's target or 0
    def g(self, a, y=0.0):
        raise NotImplementedError

    def g_conj(self, s, y=0.0):
        raise NotImplementedError

    def gap(self, a, u, y=0.0):
        return np.maximum(a * u + self.g(a, y) + self.g_conj(-u, y), 0.0)

    def minimiser(self, a, u, q, y=0.0):
        """New value of the coordinate."""
        raise NotImplementedError

    def step(self, a, u, q, y=0.0):
        q = np.asarray(q, float)
        return np.where(q > 0, self.minimiser(a, u, np.where(q > 0, q, 1.0), y) - a, 0.0)

    def step_one(self, a: float, u: float, q: float, y: float) -> float:
        """The step of a single coordinate, in plain numbers where a model has its own form."""
        return float(self.step(a, u, q, y))

    # --- the same as Columns
    def g_col(self, a: Column, y: Column) -> Column:
        raise NotImplementedError

    def conj_col(self, s: Column, y: Column) -> Column:
        raise NotImplementedError

    def gap_col(self, a: Column, u: Column, y: Column | None = None) -> Column:
        y = F.lit(0.0) if y is None else y
        return F.greatest(a * u + self.g_col(a, y) + self.conj_col(-u, y), F.lit(0.0))

    def minimiser_col(self, a: Column, u: Column, q: Column, y: Column) -> Column:
        raise NotImplementedError

    def step_col(self, a: Column, u: Column, q: Column, y: Column | None = None) -> Column:
        y = F.lit(0.0) if y is None else y
        return F.when(q > 0, self.minimiser_col(a, u, q, y) - a).otherwise(0.0)


class RidgePrimal(Objective):
    name = "ridge"

    @property
    def strong(self):
        return self.lam

    def g(self, a, y=0.0):
        return 0.5 * self.lam * np.square(a)

    def g_conj(self, s, y=0.0):
        return np.square(s) / (2 * self.lam)

    def minimiser(self, a, u, q, y=0.0):
        return (q * a - u) / (q + self.lam)

    def step_one(self, a, u, q, y):
        return -(u + self.lam * a) / (q + self.lam) if q > 0 else 0.0

    def g_col(self, a, y):
        return a * a * (0.5 * self.lam)

    def conj_col(self, s, y):
        return s * s / (2 * self.lam)

    def minimiser_col(self, a, u, q, y):
        return (q * a - u) / (q + self.lam)


class DualObjective(Objective):
    """f is the conjugate of the squared norm: the coordinates are samples."""

    def f(self, v):
        return float(v @ v) / (2 * self.lam)

    def grad(self, v):
        return v / self.lam

    def f_conj(self, w):
        return 0.5 * self.lam * float(w @ w)

    @property
    def smooth(self):
        return 1.0 / self.lam


class RidgeDual(DualObjective):
    name, strong, uses_target = "ridge_dual", 1.0, True

    def g(self, a, y=0.0):
        return 0.5 * np.square(a) - y * a

    def g_conj(self, s, y=0.0):
        return 0.5 * np.square(s + y)

    def minimiser(self, a, u, q, y=0.0):
        return (q * a + y - u) / (q + 1)

    def step_one(self, a, u, q, y):
        return (y - u - a) / (q + 1) if q > 0 else 0.0

    def g_col(self, a, y):
        return a * a * 0.5 - y * a

    def conj_col(self, s, y):
        return (s + y) * (s + y) * 0.5

    def minimiser_col(self, a, u, q, y):
        return (q * a + y - u) / (q + 1)


@dataclass
class LassoBoxed(Objective):
    """L1 with each coordinate kept within a box, so that the conjugate and with it the gap is finite. By default the box is f(0) / lam, which no iterate leaves; a smaller one tightens the gaps."""

    box: float | None = None
    name, rests = "lasso", True

    def __post_init__(self):
        super().__post_init__()
        if self.box is None and self.b is not None:
            self.box = max(self.f(np.zeros_like(self.b)) / self.lam, 1e-12)

    @property
    def bound(self):
        return self.box

    def g(self, a, y=0.0):
        return self.lam * np.abs(a)

    def g_conj(self, s, y=0.0):
        return self.box * np.maximum(np.abs(s) - self.lam, 0)

    def minimiser(self, a, u, q, y=0.0):
        return np.clip(soft(a - u / q, self.lam / q), -self.box, self.box)

    def step_one(self, a, u, q, y):
        if q <= 0:
            return 0.0
        z, t = a - u / q, self.lam / q
        new = z - t if z > t else z + t if z < -t else 0.0
        return min(max(new, -self.box), self.box) - a

    def g_col(self, a, y):
        return F.abs(a) * self.lam

    def conj_col(self, s, y):
        return F.greatest(F.abs(s) - self.lam, F.lit(0.0)) * self.box

    def minimiser_col(self, a, u, q, y):
        return clip_col(soft_col(a - u / q, F.lit(self.lam) / q), -self.box, self.box)


class HingeSvmDual(DualObjective):
    """Columns are sample times label; coordinates stay in [0, 1]."""

    name, bound, rests = "svm", 1.0, True

    def g(self, a, y=0.0):
        return -np.asarray(a, float)

    def g_conj(self, s, y=0.0):
        return np.maximum(0.0, s + 1)

    def minimiser(self, a, u, q, y=0.0):
        return np.clip(a + (1 - u) / q, 0.0, 1.0)

    def step_one(self, a, u, q, y):
        return min(max(a + (1 - u) / q, 0.0), 1.0) - a if q > 0 else 0.0

    def g_col(self, a, y):
        return -a

    def conj_col(self, s, y):
        return F.greatest(F.lit(0.0), s + 1)

    def minimiser_col(self, a, u, q, y):
        return clip_col(a + (1 - u) / q, 0.0, 1.0)


class LogisticL1(LassoBoxed):
    """b holds labels -1 and 1."""

    name, quadratic, smooth = "logit_l1", False, 0.25

    def f(self, v):
        return float(np.logaddexp(0, -self.b * v).sum())

    def grad(self, v):
        return self.grad_at(v, slice(None))

    def grad_at(self, v, at):
        """The gradient's numbers at some places, from those of v there."""
        b = self.b[at]
        return -b / (1 + np.exp(np.clip(b * v, -700, 700)))

    def f_conj(self, w):
        t = np.clip(-w * self.b, 1e-300, 1 - 1e-16)
        return float((t * np.log(t) + (1 - t) * np.log(1 - t)).sum())


@dataclass
class ElasticNet(Objective):
    """lam is the L1 part, lam2 the squared part."""

    lam2: float = 1.0
    name, rests = "enet", True

    @property
    def strong(self):
        return self.lam2

    def g(self, a, y=0.0):
        return self.lam * np.abs(a) + 0.5 * self.lam2 * np.square(a)

    def g_conj(self, s, y=0.0):
        return np.square(np.maximum(np.abs(s) - self.lam, 0)) / (2 * self.lam2)

    def minimiser(self, a, u, q, y=0.0):
        return soft(q * a - u, self.lam) / (q + self.lam2)

    def step_one(self, a, u, q, y):
        if q <= 0:
            return 0.0
        z, t = q * a - u, self.lam
        return (z - t if z > t else z + t if z < -t else 0.0) / (q + self.lam2) - a

    def g_col(self, a, y):
        return F.abs(a) * self.lam + a * a * (0.5 * self.lam2)

    def conj_col(self, s, y):
        x = F.greatest(F.abs(s) - self.lam, F.lit(0.0))
        return x * x / (2 * self.lam2)

    def minimiser_col(self, a, u, q, y):
        return soft_col(q * a - u, F.lit(self.lam)) / (q + self.lam2)


class SquaredHingeSvmDual(DualObjective):
    name, strong, rests = "sqhinge", 0.5, True

    def g(self, a, y=0.0):
        return np.square(a) / 4 - a

    def g_conj(self, s, y=0.0):
        return np.square(np.maximum(0.0, s + 1))

    def minimiser(self, a, u, q, y=0.0):
        return np.maximum(0.0, a + (1 - u - a / 2) / (q + 0.5))

    def step_one(self, a, u, q, y):
        return max(0.0, a + (1 - u - a / 2) / (q + 0.5)) - a if q > 0 else 0.0

    def g_col(self, a, y):
        return a * a / 4 - a

    def conj_col(self, s, y):
        x = F.greatest(F.lit(0.0), s + 1)
        return x * x

    def minimiser_col(self, a, u, q, y):
        return F.greatest(F.lit(0.0), a + (1 - u - a / 2) / (q + 0.5))


class LogisticDual(DualObjective):
    """Entropy of coordinates in (0, 1); the step is a bracketed Newton search."""

    name, strong = "logit_dual", 4.0

    def g(self, a, y=0.0):
        a = np.clip(a, 0.0, 1.0)
        safe = lambda x: np.where(x > 0, x * np.log(np.where(x > 0, x, 1.0)), 0.0)
        return safe(a) + safe(1 - a)

    def g_conj(self, s, y=0.0):
        return np.logaddexp(0, s)

    def minimiser(self, a, u, q, y=0.0):
        a, u, q = np.broadcast_arrays(np.asarray(a, float), np.asarray(u, float), np.asarray(q, float))
        lo, hi = np.zeros(a.shape), np.ones(a.shape)
        x = np.clip(a, 1e-9, 1 - 1e-9)
        for _ in range(60):
            slope = u + q * (x - a) + np.log(x / (1 - x))
            lo, hi = np.where(slope < 0, x, lo), np.where(slope > 0, x, hi)
            new = x - slope / (q + 1 / (x * (1 - x)))
            x = np.clip(np.where((new > lo) & (new < hi), new, (lo + hi) / 2), 1e-15, 1 - 1e-15)
        return x

    def step_one(self, a, u, q, y):
        if q <= 0:
            return 0.0
        lo, hi, x = 0.0, 1.0, min(max(a, 1e-9), 1 - 1e-9)
        for _ in range(60):
            slope = u + q * (x - a) + math.log(x / (1 - x))
            lo, hi = (x, hi) if slope < 0 else (lo, x) if slope > 0 else (lo, hi)
            new = x - slope / (q + 1 / (x * (1 - x)))
            if abs(new - x) <= 1e-16:
                break
            x = min(max(new if lo < new < hi else (lo + hi) / 2, 1e-15), 1 - 1e-15)
        return x - a

    def g_col(self, a, y):
        safe = lambda x: F.when(x > 0, x * F.log(F.when(x > 0, x).otherwise(1.0))).otherwise(0.0)
        return safe(a) + safe(1 - a)

    def conj_col(self, s, y):
        return F.greatest(s, F.lit(0.0)) + F.log1p(F.exp(-F.abs(s)))

    def minimiser_col(self, a, u, q, y):
        """A few Newton steps as one expression."""
        x = F.greatest(F.lit(1e-9), F.least(F.lit(1 - 1e-9), a))
        for _ in range(3):
            x = F.greatest(F.lit(1e-9), F.least(F.lit(1 - 1e-9), x - (u + q * (x - a) + F.log(x / (1 - x))) / (q + 1 / (x * (1 - x)))))
        return x


@dataclass
class GenericObjective(Objective):
    """Any f and g of the user's: numpy functions, and Column functions if plans are to use it."""

    f_: Callable = None
    grad_: Callable = None
    smooth_: float = 1.0
    g_: Callable = None
    g_conj_: Callable = None
    prox_: Callable = None  # (a, u, q) -> new value
    g_col_: Callable | None = None
    g_conj_col_: Callable | None = None
    f_conj_: Callable | None = None
    name = "generic"
    quadratic = False

    @property
    def smooth(self):
        return self.smooth_

    def f(self, v):
        return self.f_(v)

    def grad(self, v):
        return self.grad_(v)

    def f_conj(self, w):
        return self.f_conj_(w)

    def g(self, a, y=0.0):
        return self.g_(a)

    def g_conj(self, s, y=0.0):
        return self.g_conj_(s)

    def minimiser(self, a, u, q, y=0.0):
        return self.prox_(a, u, q)

    def g_col(self, a, y):
        return self.g_col_(a)

    def conj_col(self, s, y):
        return self.g_conj_col_(s)


MODELS = {c.name: c for c in (RidgePrimal, RidgeDual, LassoBoxed, HingeSvmDual, LogisticL1, ElasticNet, SquaredHingeSvmDual, LogisticDual)}


def total(obj: Objective, v: np.ndarray, alpha: np.ndarray, y: np.ndarray | float = 0.0) -> float:
    return obj.f(v) + float(np.sum(obj.g(alpha, y)))
