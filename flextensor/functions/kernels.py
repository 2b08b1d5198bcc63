"""Covariance functions: grams, vector-Jacobian products, and the same functions as Columns over arrays."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

NAMES = ("linear", "rbf", "ard", "matern12", "matern32", "matern52")


class Kernel:
    """k(x, z) with amplitude a² and lengths; ``rbf`` and the Matérn family share one length unless given several."""

    def __init__(self, name: str, lengths, amp2: float = 1.0):
        if name not in NAMES:
            raise ValueError(f"unknown kernel {name}")
        self.name, self.lengths, self.amp2 = name, np.atleast_1d(np.asarray(lengths, float)), float(amp2)

    def with_params(self, lengths, amp2) -> Kernel:
        return Kernel(self.name, lengths, amp2)

    def _scaled_sq(self, x: np.ndarray, z: np.ndarray) -> np.ndarray:
        a, b = x / self.lengths, z / self.lengths
        q = a @ (-2 * b.T)
        q += (a * a).sum(1)[:, None]
        q += (b * b).sum(1)
        return np.maximum(q, 0.0, out=q)

    def _shape(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(k / a², its derivative by the squared scaled distance); ``q`` is used up."""
        if self.name in ("rbf", "ard"):
            q *= -0.5
            e = np.exp(q, out=q)
            return e, -0.5 * e
        r = np.sqrt(q)
        if self.name == "matern12":
            e = np.exp(-r)
            return e, np.where(r > 0, -0.5 * e / np.where(r > 0, r, 1), 0.0)
        s = np.sqrt(3.0 if self.name == "matern32" else 5.0) * r
        e = np.exp(-s)
        if self.name == "matern32":
            return (1 + s) * e, -1.5 * e
        return (1 + s + s * s / 3) * e, -5 / 6 * (1 + s) * e

    def gram(self, x: np.ndarray, z: np.ndarray) -> np.ndarray:
        if self.name == "linear":
            return self.amp2 * (x / self.lengths**2) @ z.T
        k = self._shape(self._scaled_sq(x, z))[0] if self.name not in ("rbf", "ard") else self._bell(x, z)
        k *= self.amp2
        return k

    def _bell(self, x: np.ndarray, z: np.ndarray) -> np.ndarray:
        q = self._scaled_sq(x, z)
        q *= -0.5
        return np.exp(q, out=q)

    def bell(self, x: np.ndarray, z: np.ndarray, which) -> np.ndarray:
        """k / a² of ``rbf`` and ``ard`` over the inputs ``which`` alone, given their columns of x and z."""
        return Kernel(self.name, self.lengths[which] if len(self.lengths) > 1 else self.lengths)._bell(x, z)

    def unit(self, x: np.ndarray, z: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
        """(k / a², its derivative by the squared scaled distance, if it has one): what ``vjp`` needs once more."""
        if self.name == "linear":
            return (x / self.lengths**2) @ z.T, None
        return self._shape(self._scaled_sq(x, z))

    def diag(self, x: np.ndarray) -> np.ndarray:
        if self.name == "linear":
            return self.amp2 * ((x / self.lengths) ** 2).sum(1)
        return np.full(len(x), self.amp2)

    def vjp(self, x: np.ndarray, z: np.ndarray, g: np.ndarray, unit: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """Σ g ∘ dk by x, z, the lengths and a²; ``unit`` if it is known already."""
        l2 = self.lengths**2
        if self.name == "linear":
            dx, dz = self.amp2 * (g @ z) / l2, self.amp2 * (g.T @ x) / l2
            dl = -2 * (x * dx).sum(0) / self.lengths
            da = float((dx * x).sum() / self.amp2)
        else:
            k, d = unit or self.unit(x, z)
            h = g * d
            h *= self.amp2
            da = float(g.ravel() @ k.ravel())
        return self._spread(x, z, h, da) if self.name != "linear" else self._ends(dx, dz, dl, da)

    def bell_vjp(self, x: np.ndarray, z: np.ndarray, g: np.ndarray, k: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """``vjp`` of ``rbf`` and ``ard`` from their kernel rows k; ``g`` is used up."""
        g *= k
        return self._spread(x, z, g, None, -0.5)

    def _ends(self, dx: np.ndarray, dz: np.ndarray, dl: np.ndarray, da: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        dl = np.atleast_1d(dl)
        return dx, dz, dl if len(self.lengths) > 1 else np.array([dl.sum()]), da

    def _spread(self, x: np.ndarray, z: np.ndarray, h: np.ndarray, da: float | None, scale: float = 1.0) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """Derivatives from ``scale`` times h, those by the squared scaled distances; a bell's by a² is the sum of h over a²."""
        l2 = self.lengths**2
        # a column of ones beside z and x brings the sums of rows and columns with the products
        by_x, by_z = h @ np.column_stack([z, np.ones(len(z))]), h.T @ np.column_stack([x, np.ones(len(x))])
        if da is None:
            da = float(by_z[:, -1].sum()) / self.amp2
        by_x *= scale
        by_z *= scale
        zx, hx, hz = by_x[:, :-1], by_x[:, -1:], by_z[:, -1:]
        dx, dz = 2 * (hx * x - zx) / l2, 2 * (hz * z - by_z[:, :-1]) / l2
        spread = (hx * x * x).sum(0) - 2 * (x * zx).sum(0) + (hz * z * z).sum(0)
        return self._ends(dx, dz, -2 * spread / (l2 * self.lengths), da)

    def diag_vjp(self, x: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """Σ g · d diag by x, the lengths and a²."""
        if self.name != "linear":
            return np.zeros_like(x), np.zeros(len(self.lengths)), float(g.sum())
        q = x / self.lengths**2
        dx = 2 * self.amp2 * g[:, None] * q
        dl = -(dx * x).sum(0) / self.lengths
        return dx, dl if len(self.lengths) > 1 else np.array([dl.sum()]), float((g * (x * q).sum(1)).sum())


def kernel_expr(name: str, x: Column, z: Column, lengths: Column, amp2: float = 1.0) -> Column:
    """k(x, z) over array<double> Columns of equal size."""
    scaled = F.zip_with(F.zip_with(x, z, lambda a, b: a - b), lengths, lambda d, s: d / s)
    q = F.aggregate(scaled, F.lit(0.0), lambda acc, d: acc + d * d)
    if name == "linear":
        xs, zs = F.zip_with(x, lengths, lambda a, s: a / s), F.zip_with(z, lengths, lambda a, s: a / s)
        return F.lit(amp2) * F.aggregate(F.zip_with(xs, zs, lambda a, b: a * b), F.lit(0.0), lambda acc, d: acc + d)
    if name in ("rbf", "ard"):
        return F.lit(amp2) * F.exp(-0.5 * q)
    r = F.sqrt(q)
    if name == "matern12":
        return F.lit(amp2) * F.exp(-r)
    s = r * float(np.sqrt(3.0 if name == "matern32" else 5.0))
    return F.lit(amp2) * ((1 + s) if name == "matern32" else (1 + s + s * s / 3)) * F.exp(-s)
