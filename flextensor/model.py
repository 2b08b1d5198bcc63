"""Model state: factors, inducing points, kernel and noise; initialisation and persistence."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.kernels import Kernel
from .sampling import portable_hash
from .tensor import TensorFrame


@dataclass(frozen=True)
class ModelState:
    factors: tuple[np.ndarray, ...]
    inducing: np.ndarray
    kernel: Kernel
    beta: float = 1.0
    lam: np.ndarray | None = None
    kind: str = "real"
    trace: list = field(default_factory=list, compare=False)

    @property
    def ranks(self) -> list[int]:
        return [u.shape[1] for u in self.factors]

    def inputs(self, index: np.ndarray) -> np.ndarray:
        """Concatenated factor rows of cells; an index unseen in training (beyond the factors) has the prior mean 0."""
        parts = []
        for k, u in enumerate(self.factors):
            i = index[:, k]
            known = (i >= 0) & (i < len(u))
            if known.all():
                parts.append(u[i])
                continue
            parts.append(np.where(known[:, None], u[np.where(known, i, 0)], 0.0))
        return np.hstack(parts)

    def pack(self, learn_kernel: bool = True) -> np.ndarray:
        """The free parameters; lengths, a² and β by their logarithms."""
        parts = [u.ravel() for u in self.factors] + [self.inducing.ravel()]
        if learn_kernel:
            parts += [np.log(self.kernel.lengths), [np.log(self.kernel.amp2)]]
            if self.kind == "real":
                parts.append([np.log(self.beta)])
        return np.concatenate(parts)

    def unpack(self, v: np.ndarray, learn_kernel: bool = True) -> ModelState:
        at, factors = 0, []
        for u in self.factors:
            factors.append(v[at : at + u.size].reshape(u.shape))
            at += u.size
        z = v[at : at + self.inducing.size].reshape(self.inducing.shape)
        at += self.inducing.size
        kernel, beta = self.kernel, self.beta
        if learn_kernel:
            n = len(kernel.lengths)
            logs = np.clip(v[at : at + n + 1], -12, 12)
            kernel = kernel.with_params(np.exp(logs[:n]), float(np.exp(logs[n])))
            if self.kind == "real":
                beta = float(np.exp(np.clip(v[at + n + 1], -12, 12)))
        return replace(self, factors=tuple(factors), inducing=z, kernel=kernel, beta=beta)


def init_model(t: TensorFrame, ranks: int | list[int] = 3, p: int = 100, kernel: str = "rbf", seed: int = 0, scale: float = 0.5, beta: float = 1.0) -> ModelState:
    """Factors from a normal seeded by mode; inducing points are the inputs of the p cells of smallest hash."""
    ranks = [ranks] * len(t.dims) if isinstance(ranks, int) else list(ranks)
    factors = tuple(np.random.default_rng([seed, k]).normal(0, scale, (d, r)) for k, (d, r) in enumerate(zip(t.dims, ranks, strict=True)))
    n_len = sum(ranks) if kernel == "ard" else 1
    state = ModelState(factors, np.zeros((p, sum(ranks))), Kernel(kernel, np.ones(n_len), 1.0), beta, np.zeros(p), t.kind)
    h = portable_hash(*(F.col(m) for m in t.modes), seed=seed + 17)
    rows = t.df.select(*t.modes).orderBy(h, *t.modes).limit(p).collect()
    z = state.inputs(np.array([[r[m] for m in t.modes] for r in rows], np.int64).reshape(-1, len(t.dims)))
    if len(z) < p:  # fewer cells than points: the rest around those there are
        rng = np.random.default_rng([seed, 99])
        z = np.vstack([z, rng.normal(0, scale, (p - len(z), sum(ranks)))])
    return replace(state, inducing=z + np.random.default_rng([seed, 98]).normal(0, 0.01, z.shape))


def save_model(spark: SparkSession, m: ModelState, path: str) -> None:
    rows = [(k + 1, i, [float(x) for x in u]) for k, f in enumerate(m.factors) for i, u in enumerate(f)]
    spark.createDataFrame(rows, "mode int, idx long, factor array<double>").write.mode("overwrite").parquet(f"{path}/factors")
    points = [(j, [float(x) for x in z]) for j, z in enumerate(m.inducing)]
    spark.createDataFrame(points, "j int, point array<double>").write.mode("overwrite").parquet(f"{path}/inducing")
    lam = None if m.lam is None else [float(x) for x in m.lam]
    spark.createDataFrame([(m.kernel.name, [float(x) for x in m.kernel.lengths], m.kernel.amp2, m.beta, m.kind, lam)], "kernel string, lengths array<double>, amp2 double, beta double, kind string, lam array<double>").write.mode("overwrite").parquet(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> ModelState:
    by: dict[int, list] = {}
    for r in spark.read.parquet(f"{path}/factors").orderBy("mode", "idx").toLocalIterator():
        by.setdefault(r.mode, []).append(r.factor)
    z = np.array([r.point for r in spark.read.parquet(f"{path}/inducing").orderBy("j").collect()])
    p = spark.read.parquet(f"{path}/params").first()
    return ModelState(tuple(np.array(by[k]) for k in sorted(by)), z, Kernel(p.kernel, p.lengths, p.amp2), p.beta, None if p.lam is None else np.array(p.lam), p.kind)


def factor_table(spark: SparkSession, factors: tuple[np.ndarray, ...]) -> DataFrame:
    rows = [(k + 1, i, [float(x) for x in u]) for k, f in enumerate(factors) for i, u in enumerate(f)]
    return spark.createDataFrame(rows, "mode int, idx long, factor array<double>")
