"""Uncollapsed bounds with explicit q(v) and q(z), and one round of their E steps."""

from __future__ import annotations

import numpy as np

from ..exec.passes import Adjoints, Stats
from ..functions.special import hazard, log_ndtr
from ..model import ModelState
from .gaussian import _inv, kzz, prior


def conditional_moments(m: ModelState, kx: np.ndarray, kd: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mean and variance of latent values given the inducing targets."""
    ki, _ = _inv(kzz(m))
    return kx @ ki @ v, kd - ((kx @ ki) * kx).sum(1)


def expected_loglik(y: np.ndarray, mu: np.ndarray, var: np.ndarray, beta: float) -> np.ndarray:
    return 0.5 * np.log(beta / (2 * np.pi)) - 0.5 * beta * (y - mu) ** 2 - 0.5 * beta * var


def kl(mean: np.ndarray, cov: np.ndarray, k: np.ndarray) -> float:
    ki, lk = _inv(k)
    _, lc = _inv(cov)
    return 0.5 * float((ki * cov).sum() + mean @ ki @ mean - len(mean) + lk - lc)


def gaussian_value(m: ModelState, s: Stats, mean: np.ndarray, cov: np.ndarray, with_prior_constant: bool = False) -> float:
    """From the same sums as the collapsed bound: one statistics pass."""
    k = kzz(m)
    ki, _ = _inv(k)
    b, a = m.beta, ki @ mean
    data = 0.5 * s.n * np.log(b / (2 * np.pi)) - 0.5 * b * (s.s - 2 * s.h @ a + a @ s.g @ a) - 0.5 * b * (s.c - (ki * s.g).sum() + (ki @ cov @ ki * s.g).sum())
    return float(data - kl(mean, cov, k) + prior(m, with_prior_constant))


def gaussian_adjoints(m: ModelState, s: Stats, mean: np.ndarray, cov: np.ndarray) -> tuple[Adjoints, np.ndarray, float]:
    """Derivatives at fixed q(v): the M step's."""
    k = kzz(m)
    ki, _ = _inv(k)
    b, a = m.beta, ki @ mean
    ks = ki @ cov @ ki
    dg = -0.5 * b * np.outer(a, a) + 0.5 * b * (ki - ks)
    da = b * s.h - b * s.g @ a  # ∂/∂(Ki mean)
    dki = np.outer(da, mean) - 0.5 * np.outer(mean, mean) - 0.5 * cov + 0.5 * b * s.g - b * (s.g @ ki @ cov)
    dki = (dki + dki.T) / 2
    dk = -ki @ dki @ ki - 0.5 * ki
    db = 0.5 * s.n / b - 0.5 * (s.s - 2 * s.h @ a + a @ s.g @ a) - 0.5 * (s.c - (ki * s.g).sum() + (ks * s.g).sum())
    return Adjoints(dg, b * a, -0.5 * b), dk, float(db)


def z_moments(y: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """E z, E z², entropy of N(u, 1) cut at 0 on y's side."""
    t = 2 * y - 1
    ez = u + t * hazard(t * u)
    ez2 = 1 + u * ez
    return ez, ez2, log_ndtr(t * u) + 0.5 * np.log(2 * np.pi) + 0.5 * (ez2 - 2 * u * ez + u * u)


def probit_value(m: ModelState, s: Stats, hz: np.ndarray, z2: float, entropy: float, mean: np.ndarray, cov: np.ndarray) -> float:
    """hz = Σ k E z, z2 = Σ E z², with β = 1."""
    k = kzz(m)
    ki, _ = _inv(k)
    a = ki @ mean
    data = -0.5 * s.n * np.log(2 * np.pi) - 0.5 * (z2 - 2 * hz @ a + a @ s.g @ a) - 0.5 * (s.c - (ki * s.g).sum() + (ki @ cov @ ki * s.g).sum())
    return float(data + entropy - kl(mean, cov, k) + prior(m))
