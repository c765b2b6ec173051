"""The entropy-coded bitmap: likelihood estimate and ideal code length from counts of bits by level."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def levels(sketch: DataFrame, by: list[str] = (), depth: int = 60) -> DataFrame:
    """(by..., level, cells): cells whose bit `level` (from 1) is set; all that the likelihood needs."""
    k = F.explode(F.sequence(F.lit(1), F.lit(depth)))
    x = sketch.select(*by, "bitmap", k.alias("level"))
    return x.groupBy(*by, "level").agg(F.sum(F.expr("shiftright(bitmap, level - 1) & 1")).cast("long").alias("cells"))


def log_likelihood(lam: float, s: dict[int, int], m: int) -> float:
    out = 0.0
    for k, c in s.items():
        x = lam / (m * 2.0**k)
        out += (c * math.log(-math.expm1(-x)) if c else 0.0) - (m - c) * x
    return out


def solve(s: dict[int, int], m: int) -> tuple[float, float]:
    """(estimate, bits): the likelihood's peak by ternary search on a log scale, and the code length."""
    if not any(s.values()):
        return 0.0, 0.0
    a, b = 0.0, 60 * math.log(2)
    for _ in range(200):
        p, q = a + (b - a) / 3, b - (b - a) / 3
        if log_likelihood(math.exp(p), s, m) < log_likelihood(math.exp(q), s, m):
            a = p
        else:
            b = q
    lam = math.exp((a + b) / 2)
    return lam, -log_likelihood(lam, s, m) / math.log(2)


def solve_all(s: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """solve() of many sketches: a row each, with the counts of levels 1, 2, ... in its columns."""
    s, rate = np.asarray(s, np.float64), 1 / (m * 2.0 ** np.arange(1, s.shape[1] + 1))

    def likelihood(lam: np.ndarray) -> np.ndarray:
        x = lam[:, None] * rate
        return (np.where(s > 0, s * np.log(-np.expm1(-x)), 0.0) - (m - s) * x).sum(axis=1)

    a, b = np.zeros(len(s)), np.full(len(s), 60 * math.log(2))
    for _ in range(200):
        p, q = a + (b - a) / 3, b - (b - a) / 3
        up = likelihood(np.exp(p)) < likelihood(np.exp(q))
        a, b = np.where(up, p, a), np.where(up, b, q)
    lam = np.where(s.any(axis=1), np.exp((a + b) / 2), 0.0)
    return lam, np.where(lam > 0, -likelihood(np.maximum(lam, 1e-300)) / math.log(2), 0.0)


def entropy_estimate(sketch: DataFrame, m: int) -> tuple[float, float]:
    return solve({r["level"]: r["cells"] for r in levels(sketch).collect()}, m)  # 60 rows
