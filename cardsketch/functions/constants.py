"""Bias and variance constants of the estimators, from integrals over (0, inf)."""

from __future__ import annotations

from functools import wraps

import numpy as np

LN2 = float(np.log(2))
PHI = 0.77351  # fixed value: first-gap bias of a coupon bitmap
LOGLOG = 0.39701  # fixed value: large-m bias of the geometric-mean estimator
PANELS, NODES = 100, 20


def remembered(f):
    """f, with its results kept; a plain function, which is pickled by value for executors."""
    kept: dict = {}

    @wraps(f)
    def g(*args, **options):
        key = (args, *sorted(options.items()))
        if key not in kept:
            kept[key] = f(*args, **options)
        return kept[key]
    return g


def f_hll(u):
    return np.log2((2 + u) / (1 + u))


def f_nb(u):
    return f_hll(u) + np.log2((4 + 3 * u) / (3 + 3 * u)) - np.log2((4 + u) / (3 + u))


@remembered
def _nodes() -> tuple[np.ndarray, np.ndarray]:
    x, w = np.polynomial.legendre.leggauss(NODES)
    left = np.arange(PANELS)[:, None]
    return ((left + (x + 1) / 2) / PANELS).ravel(), np.tile(w / (2 * PANELS), PANELS)


@remembered
def integral(kind: str, m: int, power: int) -> float:
    """Integral of u**power * f(u)**m; u = c s / (1 - s) with c of the width of the peak."""
    s, w = _nodes()
    c = 8.0 / m
    u = c * s / (1 - s)
    f = f_nb(u) if kind == "nb" else f_hll(u)
    with np.errstate(divide="ignore"):
        y = np.exp(m * np.log(np.maximum(f, 1e-300)))
    return float((w * y * u**power * c / (1 - s) ** 2).sum())


@remembered
def gamma(m: int, how: str = "integral") -> float:
    if how == "limit":
        return 2 / (3 * LN2)
    if how == "laplace":
        return 1 / (m * laplace(m, 0))
    return 1 / (m * integral("nb", m, 0))


@remembered
def alpha(m: int, how: str = "integral") -> float:
    return 1 / (2 * LN2) if how == "limit" else 1 / (m * integral("hll", m, 0))


def laplace(m: int, power: int) -> float:
    a, c = 3 * LN2 / (2 * m), 41 * LN2 / 16 - 1
    return a * (1 + c / m) if power == 0 else a * a * (1 + 3 * c / m)


@remembered
def variance(kind: str, m: int | None) -> float:
    """m times the relative variance of a mergeable estimator; the limit where m is None."""
    if kind == "pcsa":
        return 0.78**2
    if kind == "loglog":
        return 1.69
    if m is None:
        return 41 * LN2 / 16 - 1 if kind == "nb" else 3 * LN2 - 1
    return m * (integral(kind, m, 1) / integral(kind, m, 0) ** 2 - 1)


def martingale_variance(kind: str) -> float:
    """m times the relative variance of a sequential estimator, for many elements."""
    return 1 / (2 * (gamma(1, "limit") if kind == "nb" else alpha(1, "limit")))
