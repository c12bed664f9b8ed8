"""Rate bounds as functions that runs are held against."""

from __future__ import annotations

import math

import numpy as np


def strong_constant(L: float, mu: float, sigma: float, m: int, n: int) -> float:
    return m / n * mu / (sigma * L + mu)


def step_bound(epsilon: float, theta: float, rho: float, L: float, mu: float, sigma: float, m: int, n: int) -> float:
    """Most that may be left after a round on strongly convex g."""
    return (1 - theta * rho * strong_constant(L, mu, sigma, m, n)) * epsilon


def rate_strong(epsilon0: float, t: int, eta: float, L: float, mu: float, sigma: float, m: int, n: int) -> float:
    return (1 - eta * strong_constant(L, mu, sigma, m, n)) ** t * epsilon0


def rounds_needed_strong(share: float, eta: float, L: float, mu: float, sigma: float, m: int, n: int) -> int:
    """Rounds after which the linear rate leaves at most this share."""
    return math.ceil(math.log(share) / math.log(1 - eta * strong_constant(L, mu, sigma, m, n)))


def gamma(L: float, B: float, sigma: float) -> float:
    return 2 * L * B * B * sigma


def t0(epsilon0: float, eta: float, g: float, m: int, n: int) -> float:
    x = 2 * eta * m * epsilon0 / (n * g)
    return max(0.0, n / m * math.log(x)) if x > 0 else 0.0


def rate_bounded(epsilon0: float, t: int, eta: float, g: float, m: int, n: int) -> float:
    """Sublinear rate for bounded support, for t from t0 on."""
    return 2 * g * n * n / (eta * m * (2 * n + t - t0(epsilon0, eta, g, m, n)))


def step_bound_bounded(epsilon: float, theta: float, rho: float, g: float, m: int, n: int) -> float:
    """One round's bound for bounded support, at the best step share within 0 and 1."""
    s = np.linspace(0, 1, 1001)
    return float(np.min((1 - theta * s * rho * m / n) * epsilon + theta * s * s * g * m))
