"""Laws and moments behind the estimators, for tests and tables; plain numpy, on the driver."""

from __future__ import annotations

from itertools import product

import numpy as np

from .constants import alpha, f_hll, f_nb, gamma


def p_top(k: int, n: int) -> float:
    """P(the largest of n draws is k)."""
    if k == 0:
        return float(n == 0)
    return (1 - 2.0**-k) ** n - (1 - 2.0 ** (1 - k)) ** n


def p_pair(k: int, seen: int, n: int) -> float:
    """P(largest is k and the rank under it was seen or not): the exact law."""
    if n == 0:
        return float(k == 0 and seen == 1)
    if k <= 1:
        return p_top(k, n) if seen else 0.0
    unseen = (1 - 3 * 2.0**-k) ** n - (1 - 4 * 2.0**-k) ** n
    return unseen if not seen else p_top(k, n) - unseen


def p_pair_printed(k: int, seen: int, n: int) -> float:
    """The law as a product, which takes the rank under the largest to be missed independently of it: it
    agrees with p_pair for many arrivals only."""
    missed = (1 - 2.0 ** (1 - k)) ** n if k >= 1 else 0.0
    return p_top(k, n) * (1 - missed if seen else missed)


def cell_terms(kind: str, n: int, depth: int = 50) -> list[tuple[float, float]]:
    """(term, probability) of one cell after n arrivals."""
    if kind == "hll":
        return [(2.0**-k, p_top(k, n)) for k in range(depth)]
    return [(2.0**-k * (1 if s else 3), p_pair(k, s, n)) for k in range(depth) for s in (0, 1)]


def exact_moment(kind: str, m: int, n: int, power: int = 1, depth: int = 14) -> float:
    """E[indicator**power] for tiny m and n, over all ways to deal n elements to m cells."""
    from math import comb

    def deals(left: int, cells: int):
        if cells == 1:
            yield (left,), 1
            return
        for k in range(left + 1):
            for rest, ways in deals(left - k, cells - 1):
                yield (k, *rest), ways * comb(left, k)

    total = 0.0
    for deal, ways in deals(n, m):
        laws = [[(t, p) for t, p in cell_terms(kind, c, depth) if p > 0] for c in deal]
        for xs in product(*laws):
            total += ways * np.prod([p for _, p in xs]) * (1 / sum(t for t, _ in xs)) ** power
    return float(total / m**n)


def poisson_cell(kind: str, x: float, u: float, depth: int = 60) -> float:
    """E[exp(-u x term)] of a cell that gets Poisson(x) arrivals, less the empty cell."""
    k = np.arange(1, depth)
    s = 2.0**-k
    e = lambda c: np.exp(-c * x * s)
    if kind == "hll":
        return float((np.exp(-u * x * s) * (e(1) - e(2))).sum())
    unseen = np.where(k >= 2, e(3) - e(4), 0.0)
    return float((np.exp(-u * x * s) * (e(1) - e(2) - unseen) + np.exp(-3 * u * x * s) * unseen).sum())


def integrand(x: float, u: float, form: str = "simplified", depth: int = 80) -> float:
    """The transform of a cell with x arrivals on average, at u x: with the terms of x / 4**k that the product law
    gives ("printed"), or without ("simplified"), which is the exact law's but for k = 1."""
    k = np.arange(1, depth)
    s = 2.0**-k
    q = s * s if form == "printed" else 0.0
    pair = np.exp(-x * (3 * s - 2 * q)) - np.exp(-x * (4 * s - 4 * q))
    return float(((np.exp(-x * s) - np.exp(-2 * x * s)) * np.exp(-u * x * s) + pair * (np.exp(-3 * u * x * s) - np.exp(-u * x * s))).sum())


def mean_error(m: int, x: float = 1e5) -> float:
    """m times the difference between the mean of the poissonised indicator over n / m and the integral of f**m."""
    s, w = np.polynomial.legendre.leggauss(400)
    s, w = (s + 1) / 2, w / 2
    c = 8.0 / m
    u = c * s / (1 - s)
    g = np.array([integrand(x, v) for v in u])
    return float(m * (w * (g**m - f_nb(u) ** m) * c / (1 - s) ** 2).sum())


def harmonic_sum(a: float, b: float, x: float = 1e5, depth: int = 80) -> float:
    """Sum over k of exp(-a x / 2**k) - exp(-b x / 2**k), which tends to log2(b / a)."""
    k = np.arange(1, depth)
    return float((np.exp(-a * x / 2.0**k) - np.exp(-b * x / 2.0**k)).sum())


def poisson_mean(kind: str, m: int, lam: float, power: int = 1) -> float:
    """E[indicator**power] when lam elements arrive on average: an integral of the cell's transform."""
    s, w = np.polynomial.legendre.leggauss(400)
    s, w = (s + 1) / 2, w / 2
    c, x = 8.0 / m, lam / m
    u = c * s / (1 - s)
    g = np.array([poisson_cell(kind, x, v) + np.exp(-x * (1 + v)) for v in u])
    return float((w * g**m * u ** (power - 1) * c / (1 - s) ** 2).sum() * x**power)


def poisson_variance(kind: str, m: int, lam: float) -> float:
    return poisson_mean(kind, m, lam, 2) - poisson_mean(kind, m, lam) ** 2


def martingale_relative_variance(kind: str, m: int, n: int) -> float:
    c = gamma(m) if kind == "nb" else alpha(m)
    return (n * (n + 1) / (2 * c * m) - n) / n**2


def bounds_hold(u: np.ndarray) -> bool:
    """1 - u/2 > f on (0, 1], f < 1 / (1 + u) from 1 on, and f of the new sketch under the other's."""
    f = f_nb(u)
    return bool(np.all(f[u <= 1] < 1 - u[u <= 1] / 2) and np.all(f[u >= 1] < 1 / (1 + u[u >= 1])) and np.all(f <= f_hll(u)))
