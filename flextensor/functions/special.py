"""The normal distribution's Φ, log Φ and hazard φ/Φ, in numpy with stable tails and as Columns."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

LOG_2PI = float(np.log(2 * np.pi))
MID, TERMS = 3.5, 32  # where the variable of the Mills ratio's series is 0, and how many terms it has


def _mills_at(x: float) -> float:
    """(1 - Φ(x)) / φ(x) for x >= 0: by the series of Φ up to 1, by a continued fraction beyond."""
    if x < 1:
        term = total = x
        for n in range(1, 60):
            term *= x * x / (2 * n + 1)
            total += term
        return float(np.sqrt(np.pi / 2) * np.exp(0.5 * x * x)) - total
    f = 0.0
    for k in range(2000, 0, -1):
        f = k / (x + f)
    return 1 / (x + f)


@lru_cache(1)
def _series() -> np.ndarray:
    """Chebyshev coefficients of (1 + x) times the Mills ratio by (x - MID) / (x + MID), which takes all x >= 0 to -1..1."""
    angle = np.pi * (np.arange(TERMS) + 0.5) / TERMS
    x = MID * (1 + np.cos(angle)) / (1 - np.cos(angle))
    f = np.array([(1 + v) * _mills_at(v) for v in x])
    c = 2 / TERMS * (np.cos(np.outer(np.arange(TERMS), angle)) @ f)
    c[0] /= 2
    return c


def _mills(x: np.ndarray) -> np.ndarray:
    """(1 - Φ(x)) / φ(x) for x >= 0."""
    c, t = _series(), 2 * ((x - MID) / (x + MID))
    a, b, new = np.zeros_like(t), np.zeros_like(t), np.empty_like(t)
    for v in c[:0:-1]:
        np.multiply(t, a, out=new)
        new -= b
        new += v
        a, b, new = new, a, b
    return (0.5 * t * a - b + c[0]) / (1 + x)


def _density(x: np.ndarray) -> np.ndarray:
    return np.exp(-0.5 * x * x - 0.5 * LOG_2PI)


def ndtr(x) -> np.ndarray:
    x = np.asarray(x, float)
    tail = _density(x) * _mills(np.abs(x))
    return np.where(x > 0, 1 - tail, tail)


def log_ndtr(x) -> np.ndarray:
    return hazard_and_log(x)[1]


def hazard(x) -> np.ndarray:
    """φ(x) / Φ(x)"""
    return hazard_and_log(x)[0]


def hazard_and_log(x) -> tuple[np.ndarray, np.ndarray]:
    """(φ(x) / Φ(x), log Φ(x)) from one Mills ratio."""
    x = np.asarray(x, float)
    r, density = _mills(np.abs(x)), _density(x)
    tail = density * r
    return np.where(x > 0, density / (1 - tail), 1 / r), np.where(x > 0, np.log1p(-np.minimum(tail, 0.5)), -0.5 * x * x - 0.5 * LOG_2PI + np.log(r))


def phi_expr(x: Column) -> Column:
    return F.exp(-0.5 * x * x) / float(np.sqrt(2 * np.pi))


def ndtr_expr(x: Column, terms: int = 60) -> Column:
    """Φ as a Column for |x| <= 3, by the same series as a fold; stays in the JVM."""
    seed = F.struct(x.alias("t"), x.alias("s"))

    def step(acc: Column, n: Column) -> Column:
        t = acc["t"] * x * x / (2 * n + 1)
        return F.struct(t.alias("t"), (acc["s"] + t).alias("s"))

    return F.lit(0.5) + phi_expr(x) * F.aggregate(F.sequence(F.lit(1), F.lit(terms)), seed, step, lambda a: a["s"])


def log_ndtr_expr(x: Column) -> Column:
    return F.log(ndtr_expr(x))


def hazard_expr(x: Column) -> Column:
    return phi_expr(x) / ndtr_expr(x)


def student_p(t: float, df: int) -> float:
    """Two-sided p-value of Student's t by the incomplete beta function's continued fraction."""
    from math import exp, lgamma, log

    if not np.isfinite(t):
        return 0.0
    x, a, b = df / (df + t * t), df / 2, 0.5
    if x >= 1:
        return 1.0

    def fraction(x: float, a: float, b: float) -> float:
        c, d = 1.0, 1 - (a + b) * x / (a + 1)
        d = 1 / (d if abs(d) > 1e-300 else 1e-300)
        h = d
        for m in range(1, 300):
            for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
                d = 1 / (1 + num * d or 1e-300)
                c = 1 + num / c or 1e-300
                h *= c * d
        return h

    front = exp(lgamma(a + b) - lgamma(a) - lgamma(b) + a * log(x) + b * log(1 - x))
    return front * fraction(x, a, b) / a if x < (a + 1) / (a + b + 2) else 1 - front * fraction(1 - x, b, a) / b
