"""Gradient ascent with constant, decaying or backtracking steps."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


def gd(f: Callable[[np.ndarray], tuple[float, np.ndarray]], x: np.ndarray, steps: int = 50, rate: float = 0.01, schedule: str = "backtrack", tol: float = 1e-7, callback: Callable | None = None) -> tuple[np.ndarray, float, list[float]]:
    """Maximises f; returns (x, value, trace)."""
    value, g = f(x)
    trace = [value]
    for i in range(steps):
        if schedule == "backtrack":
            while True:
                new = x + rate * g
                v, ng = f(new)
                if np.isfinite(v) and v >= value + 1e-4 * rate * g @ g or rate < 1e-12:
                    break
                rate *= 0.5
            moved, x, value, g = v - value, new, v, ng
            rate *= 1.5
        else:
            x = x + (rate if schedule == "constant" else rate / np.sqrt(i + 1)) * g
            v, g = f(x)
            moved, value = v - value, v
        trace.append(value)
        if callback:
            callback(i, x, value)
        if abs(moved) < tol * max(1.0, abs(value)):
            break
    return x, value, trace
