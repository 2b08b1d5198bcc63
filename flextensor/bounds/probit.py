"""Collapsed bound for binary values, the λ fixed point, adjoints, and the bound before λ (with q(z))."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from ..exec.passes import Adjoints, Stats, lambda_pass
from ..functions.special import hazard, log_ndtr
from ..model import ModelState
from ..tensor import TensorFrame
from .gaussian import _inv, kzz, prior


def value(m: ModelState, s: Stats, lam: np.ndarray, log_phi: float, k: np.ndarray | None = None, with_prior_constant: bool = False) -> float:
    k = kzz(m) if k is None else k
    ki, lk = _inv(k)
    _, lm = _inv(k + s.g)
    return float(0.5 * (lk - lm) - 0.5 * s.c + 0.5 * (ki * s.g).sum() + log_phi - 0.5 * lam @ k @ lam + prior(m, with_prior_constant))


def fixed_point(t: TensorFrame, m: ModelState, s: Stats, lam: np.ndarray | None = None, tol: float = 1e-6, max_iter: int = 100, run: Callable | None = None, first: tuple[np.ndarray, float] | None = None, last: bool = True) -> tuple[np.ndarray, float | None, list[float]]:
    """(λ, Σ log Φ at λ, trace of the bound): one solve with a factorisation made once, one pass per step. ``first``: what the pass at
    the given λ says, if that is known; without ``last`` none is made at the λ found."""
    run = run or lambda_pass
    k = kzz(m)
    lam = np.zeros(len(k)) if lam is None else lam
    inv, _ = _inv(k + s.g)
    trace = []
    for _ in range(max_iter):
        g, log_phi = first or run(t, m, lam)
        first = None
        trace.append(value(m, s, lam, log_phi, k))
        new = inv @ (s.g @ lam + g)
        gap = float(np.abs(new - lam).max())
        lam = new
        if gap < tol:
            break
    if not last:
        return lam, None, trace
    _, log_phi = run(t, m, lam)
    trace.append(value(m, s, lam, log_phi, k))
    return lam, log_phi, trace


def adjoints(m: ModelState, s: Stats, lam: np.ndarray, k: np.ndarray | None = None) -> tuple[Adjoints, np.ndarray]:
    """Adjoints at fixed λ; at the maximiser these are the whole derivative."""
    k = kzz(m) if k is None else k
    ki, _ = _inv(k)
    mi, _ = _inv(k + s.g)
    return Adjoints(0.5 * (ki - mi), np.zeros(len(k)), -0.5, lam), 0.5 * (ki - mi - ki @ s.g @ ki - np.outer(lam, lam))


def lambda_gradient(m: ModelState, lam: np.ndarray, g: np.ndarray, k: np.ndarray | None = None) -> np.ndarray:
    """∂bound/∂λ, for the ablation that climbs in λ together with the rest."""
    return g - (kzz(m) if k is None else k) @ lam


def conjugate_lower(a: np.ndarray, w: np.ndarray, lam: np.ndarray) -> float:
    """λᵀw - ½ λᵀAλ, which is at most ½ wᵀA⁻¹w and equals it at λ = A⁻¹w."""
    return float(lam @ w - 0.5 * lam @ a @ lam)


def mid_value(m: ModelState, kx: np.ndarray, c: float, y: np.ndarray, u: np.ndarray, k: np.ndarray | None = None) -> float:
    """The bound with q(v) eliminated and q(z) kept, for dense rows kx: q(z_j) is N(u_j, 1) cut at 0 on y_j's side."""
    k = kzz(m) if k is None else k
    g = kx.T @ kx
    ki, lk = _inv(k)
    mi, lm = _inv(k + g)
    t = 2 * y - 1
    ez = u + t * hazard(t * u)
    ez2 = 1 + u * ez
    # entropy of the cut normal: E[-log q] = log Φ(tu) + ½ log 2π + ½ E[(z - u)²]
    entropy = log_ndtr(t * u) + 0.5 * np.log(2 * np.pi) + 0.5 * (ez2 - 2 * u * ez + u * u)
    w = kx.T @ ez
    return float(0.5 * (lk - lm) - 0.5 * c + 0.5 * (ki * g).sum() - 0.5 * ez2.sum() - 0.5 * len(y) * np.log(2 * np.pi) + entropy.sum() + 0.5 * w @ mi @ w + prior(m))
