"""Posterior prediction of cells, continuous and binary."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .bounds.gaussian import kzz
from .exec import passes
from .functions.special import ndtr
from .model import ModelState
from .session import ship_package
from .tensor import TensorFrame


class Predictor:
    """The p×p pieces of the predictive equations."""

    def __init__(self, m: ModelState, stats: passes.Stats, jitter: bool = True):
        k = kzz(m, jitter)
        self.m, self.ki = m, np.linalg.inv(k)
        self.mi = np.linalg.inv(k + (m.beta if m.kind == "real" else 1.0) * stats.g)
        self.w = m.beta * self.mi @ stats.h if m.kind == "real" else m.lam

    def __call__(self, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(mean or score, latent variance)"""
        x = self.m.inputs(index)
        k = self.m.kernel.gram(x, self.m.inducing)
        return k @ self.w, np.maximum(self.m.kernel.diag(x) - ((k @ (self.ki - self.mi)) * k).sum(1), 0.0)


def predict(train: TensorFrame, m: ModelState, cells: DataFrame) -> DataFrame:
    """``cells`` with mean and var (real) or score, var and prob (binary), and ``cold`` where an index was never trained."""
    spark = cells.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(Predictor(m, passes.suff_stats(train, m)))
    names, modes, kind = cells.columns, train.modes, m.kind
    extra = "mean double, var double" if kind == "real" else "score double, var double, prob double"
    sizes = [len(u) for u in m.factors]

    def run(batches):
        for b in batches:
            index = np.stack([b.column(names.index(c)).to_numpy(zero_copy_only=False).astype(np.int64) for c in modes], 1)
            f, var = shared.value(index)
            more = [f, var] if kind == "real" else [f, var, ndtr(f / np.sqrt(1 + var))]
            cold = ((index < 0) | (index >= np.array(sizes))).any(1)
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(x) for x in more), pa.array(cold)], [*names, *(c.split()[0] for c in extra.split(", ")), "cold"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cells.schema.fields)
    return cells.mapInArrow(run, f"{schema}, {extra}, cold boolean")
