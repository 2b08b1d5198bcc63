"""L-BFGS (maximising) with a strong-Wolfe line search. Vectors need sums, multiples and dot products only, so they may be sharded."""

from __future__ import annotations

from collections import deque
from collections.abc import Callable

import numpy as np


def direction(g: np.ndarray, pairs: deque) -> np.ndarray:
    """The inverse-Hessian product of the two loops over stored pairs; only dot products and sums of vectors."""
    q, alphas = g.copy(), []
    for s, y, rho in reversed(pairs):
        a = rho * (s @ q)
        alphas.append(a)
        q = q - a * y
    if pairs:
        s, y, _ = pairs[-1]
        q = q * ((s @ y) / (y @ y))
    for (s, y, rho), a in zip(pairs, reversed(alphas), strict=True):
        q = q + s * (a - rho * (y @ q))
    return q


def wolfe(f: Callable, x: np.ndarray, value: float, g: np.ndarray, d: np.ndarray, first: float, c1: float = 1e-4, c2: float = 0.9, most: int = 20):
    """(step, value, gradient) by bracketing and bisection; of the points seen the best if none meets both conditions."""
    slope, lo, hi, t = g @ d, 0.0, np.inf, first
    best = (0.0, value, g)
    for _ in range(most):
        v, ng = f(x + t * d)
        if np.isfinite(v) and v > best[1]:
            best = (t, v, ng)
        if not np.isfinite(v) or v < value + c1 * t * slope:
            hi = t
        elif ng @ d > c2 * slope:
            lo = t
        elif ng @ d < -c2 * slope:
            hi = t
        else:
            return t, v, ng
        t = (lo + hi) / 2 if np.isfinite(hi) else 2 * t
        if hi - lo < 1e-12:
            break
    return best


def _abs_sum(g) -> float:
    return g.abs_sum() if hasattr(g, "abs_sum") else float(np.abs(g).sum())


def lbfgs(f: Callable[[np.ndarray], tuple[float, np.ndarray]], x: np.ndarray, steps: int = 50, memory: int = 10, tol: float = 1e-7, callback: Callable | None = None) -> tuple[np.ndarray, float, list[float]]:
    value, g = f(x)
    trace, pairs = [value], deque(maxlen=memory)
    for i in range(steps):
        d = direction(g, pairs)
        if d @ g <= 0:
            pairs.clear()
            d = g.copy()
        t, v, ng = wolfe(f, x, value, g, d, 1.0 if pairs else min(1.0, 1.0 / (_abs_sum(g) + 1e-12)))
        if t == 0.0:
            if not pairs:
                break
            pairs.clear()
            continue
        s, y = t * d, g - ng
        if s @ y > 1e-10:
            pairs.append((s, y, 1 / (s @ y)))
        moved, x, value, g = v - value, x + s, v, ng
        trace.append(value)
        if callback:
            callback(i, x, value)
        if abs(moved) < tol * max(1.0, abs(value)):
            break
    return x, value, trace
