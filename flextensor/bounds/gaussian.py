"""Collapsed bound for continuous values, its adjoints and its gradient."""

from __future__ import annotations

import numpy as np

from ..exec.passes import Adjoints, Stats
from ..model import ModelState

JITTER = 1e-6


def cholesky(a: np.ndarray, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """(L, a + jitter): jitter grows tenfold until the factorisation succeeds."""
    eps = JITTER * scale
    for _ in range(8):
        try:
            b = a + eps * np.eye(len(a))
            return np.linalg.cholesky(b), b
        except np.linalg.LinAlgError:
            eps *= 10
    raise np.linalg.LinAlgError("the inducing gram is not positive definite")


def kzz(m: ModelState, jitter: bool = True) -> np.ndarray:
    k = m.kernel.gram(m.inducing, m.inducing)
    k = (k + k.T) / 2
    return cholesky(k, m.kernel.amp2)[1] if jitter else k


def _inv(a: np.ndarray) -> tuple[np.ndarray, float]:
    low = np.linalg.cholesky(a)
    half = np.linalg.solve(low, np.eye(len(a)))
    return half.T @ half, 2 * float(np.log(np.diag(low)).sum())


def prior(m: ModelState, with_constant: bool = False) -> float:
    size = sum(u.size for u in m.factors)
    return -0.5 * sum(float((u * u).sum()) for u in m.factors) - 0.5 * size * np.log(2 * np.pi) * with_constant


def value(m: ModelState, s: Stats, k: np.ndarray | None = None, with_prior_constant: bool = False) -> float:
    k = kzz(m) if k is None else k
    b = m.beta
    ki, lk = _inv(k)
    mi, lm = _inv(k + b * s.g)
    return float(0.5 * (lk - lm) - 0.5 * b * (s.s + s.c) + 0.5 * b * (ki * s.g).sum() + 0.5 * b * b * s.h @ mi @ s.h + 0.5 * s.n * np.log(b / (2 * np.pi)) + prior(m, with_prior_constant))


def adjoints(m: ModelState, s: Stats, k: np.ndarray | None = None) -> tuple[Adjoints, np.ndarray, float]:
    """(adjoints of the data sums, of Kzz, and of β)"""
    k = kzz(m) if k is None else k
    b = m.beta
    ki, _ = _inv(k)
    mi, _ = _inv(k + b * s.g)
    w = mi @ s.h
    ww = np.outer(w, w)
    dg = 0.5 * b * (ki - mi) - 0.5 * b**3 * ww
    dk = 0.5 * (ki - mi - b * ki @ s.g @ ki - b * b * ww)
    db = 0.5 * ((ki * s.g).sum() - (mi * s.g).sum() - s.s - s.c) + b * s.h @ w - 0.5 * b * b * w @ s.g @ w + s.n / (2 * b)
    return Adjoints(dg, b * b * w, -0.5 * b), dk, float(db)


def finish(m: ModelState, data: np.ndarray, dk: np.ndarray, db: float | None) -> np.ndarray:
    """The gradient by raw parameters: data part, what flows through Kzz, and the prior, each once."""
    n_u = sum(u.size for u in m.factors)
    n_z, n_l = m.inducing.size, len(m.kernel.lengths)
    out = data.copy()
    dx, dz, dl, da = m.kernel.vjp(m.inducing, m.inducing, dk)
    out[:n_u] -= np.concatenate([u.ravel() for u in m.factors])
    out[n_u : n_u + n_z] += (dx + dz).ravel()
    out[n_u + n_z : n_u + n_z + n_l] += dl
    out[n_u + n_z + n_l] += da
    return out if db is None else np.append(out, db)


def to_logs(m: ModelState, g: np.ndarray) -> np.ndarray:
    """Raw derivatives of lengths, a² and β to those of their logarithms."""
    n_l = len(m.kernel.lengths)
    tail = np.concatenate([m.kernel.lengths, [m.kernel.amp2], [m.beta] if m.kind == "real" else []])
    out = g.copy()
    out[len(g) - len(tail) :] *= tail
    assert n_l >= 1
    return out


def optimal_qv(m: ModelState, s: Stats, k: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Mean and covariance of the best q(v)."""
    k = kzz(m) if k is None else k
    mi, _ = _inv(k + m.beta * s.g)
    return m.beta * k @ mi @ s.h, k @ mi @ k
