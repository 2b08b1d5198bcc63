"""Anchored placement and mini-batches: what changes when the factors of one mode no longer fit a task.

Cells are range-partitioned by the largest mode, so the factor rows and the gradients of that mode live with its cells:
a factor table (idx, factor) is co-grouped with the cells of a shard, and only the small modes are broadcast and summed key-free.
A hot index is split over several shards by a salt; its partial gradients are summed by key.
"""

from __future__ import annotations

import copy
import time
from collections.abc import Callable
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..bounds import gaussian, probit
from ..functions.kernels import Kernel
from ..model import ModelState
from ..optim.gd import gd
from ..optim.lbfgs import lbfgs
from ..predict import Predictor
from ..sampling import MODULUS, portable_hash, smallest_hashes
from ..session import cut_lineage, ship_package
from ..tensor import TensorFrame
from . import passes


def shard_factors(t: TensorFrame, m: ModelState, mode: int) -> DataFrame:
    """(idx, factor) of one mode as a table."""
    u = m.factors[mode]
    return t.df.sparkSession.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(u)], "idx long, factor array<double>")


def _shards(t: TensorFrame, factors: DataFrame, mode: int, shards: int, salts: int) -> tuple[DataFrame, DataFrame]:
    """Cells and factor rows with the shard both belong to; a cell's salt spreads a hot index over several shards."""
    col = t.modes[mode]
    salt = F.pmod(F.floor(portable_hash(*(F.col(c) for c in t.modes), seed=31) / 256), F.lit(salts)).cast("int")
    cells = t.df.select(*t.modes, "y", F.pmod(F.xxhash64(F.col(col), salt), F.lit(shards)).alias("shard"))
    copies = factors.select("idx", "factor", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    rows = copies.select("idx", "factor", F.pmod(F.xxhash64(F.col("idx"), F.col("salt").cast("int")), F.lit(shards)).alias("shard")).distinct()
    return cells, rows


def _local(m: ModelState, mode: int, cells: pd.DataFrame, rows: pd.DataFrame, names: list[str]) -> tuple[ModelState, np.ndarray, np.ndarray, np.ndarray]:
    """The model with the shard's own rows in the anchored mode, and the cells re-indexed to them."""
    ids = rows["idx"].to_numpy()
    order = np.argsort(ids)
    own = np.stack(rows["factor"].to_numpy()[order]) if len(rows) else np.zeros((0, m.factors[mode].shape[1]))
    index = cells[names].to_numpy(np.int64)
    index[:, mode] = np.searchsorted(ids[order], index[:, mode])
    factors = tuple(own if k == mode else u for k, u in enumerate(m.factors))
    return replace(m, factors=factors), index, cells["y"].to_numpy(float), ids[order]


def anchored_sum(t: TensorFrame, m: ModelState, factors: DataFrame, mode: int, size: int, each: Callable, extra=None, shards: int = 8, salts: int = 1) -> np.ndarray:
    """Σ over shards of ``each(state, index, y)``, state being the model with the shard's own rows, and ``extra`` with it if given."""
    spark = t.df.sparkSession
    ship_package(spark)
    shared, names = spark.sparkContext.broadcast((without(m, mode), extra)), t.modes

    def run(cells: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        if not len(cells):
            return pd.DataFrame({"v": []})
        small, more = shared.value
        local, index, y, _ = _local(small, mode, cells, rows, names)
        return pd.DataFrame({"v": [each(local if more is None else (local, more), index, y).tobytes()]})

    cells, rows = _shards(t, factors, mode, shards, salts)
    out = cells.groupBy("shard").cogroup(rows.groupBy("shard")).applyInPandas(run, "v binary")
    return passes.sum_vectors(out, size)


def without(m: ModelState, mode: int) -> ModelState:
    """The model without the factors of one mode, as it is broadcast."""
    return replace(m, factors=tuple(np.zeros((0, u.shape[1])) if k == mode else u for k, u in enumerate(m.factors)))


def anchored_stats(t: TensorFrame, m: ModelState, factors: DataFrame, mode: int, shards: int = 8, salts: int = 1) -> passes.Stats:
    """The sufficient statistics without ever holding the anchored mode's factors in one place."""
    p = len(m.inducing)
    return passes.Stats.unpack(anchored_sum(t, m, factors, mode, p * (p + 1) // 2 + p + 3, passes.block_stats, None, shards, salts), p)


def anchored_lambda(t: TensorFrame, m: ModelState, lam: np.ndarray, factors: DataFrame, mode: int, shards: int = 8, salts: int = 1) -> tuple[np.ndarray, float]:
    v = anchored_sum(t, m, factors, mode, len(lam) + 1, passes.block_lambda, lam, shards, salts)
    return v[:-1], float(v[-1])


def anchored_gradient(t: TensorFrame, m: ModelState, a: passes.Adjoints, factors: DataFrame, mode: int, shards: int = 8, salts: int = 1) -> tuple[np.ndarray, DataFrame]:
    """([small modes | inducing | lengths | a²] key-free, (idx, grad) of the anchored mode as a table)."""
    spark = t.df.sparkSession
    ship_package(spark)
    small = without(m, mode)
    shared, names = spark.sparkContext.broadcast((small, a)), t.modes
    before = sum(u.size for u in small.factors[:mode])

    def run(cells: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        if not len(cells):
            return pd.DataFrame({"idx": [], "v": []})
        model, adj = shared.value
        local, index, y, ids = _local(model, mode, cells, rows, names)
        g = passes.block_gradient((local, adj), index, y)
        width = local.factors[mode].shape[1]
        own = g[before : before + len(ids) * width].reshape(len(ids), width)
        rest = np.concatenate([g[:before], g[before + len(ids) * width :]])
        touched = np.unique(index[:, mode])
        return pd.DataFrame({"idx": [-1, *ids[touched].tolist()], "v": [rest.tobytes(), *(own[i].tobytes() for i in touched)]})

    cells, rows = _shards(t, factors, mode, shards, salts)
    out = cells.groupBy("shard").cogroup(rows.groupBy("shard")).applyInPandas(run, "idx long, v binary").persist()
    size = sum(u.size for u in small.factors) + m.inducing.size + len(m.kernel.lengths) + 1
    rest = passes.sum_vectors(out.where("idx = -1").select("v"), size)

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"idx": pdf["idx"].iloc[:1], "grad": [np.sum([np.frombuffer(x, float) for x in pdf["v"]], 0).tolist()]})

    parts = out.where("idx >= 0")
    return rest, parts.groupBy("idx").applyInPandas(add, "idx long, grad array<double>")


def ascend(factors: DataFrame, grads: DataFrame, rate: float) -> DataFrame:
    """One step on a sharded factor table, the prior's pull included; rows without cells only feel the prior."""
    j = factors.join(grads, "idx", "left")
    g = F.coalesce(F.col("grad"), F.transform("factor", lambda x: F.lit(0.0)))
    return j.select("idx", F.zip_with("factor", g, lambda u, d: u + rate * (d - u)).alias("factor"))


def table_dot(a: DataFrame, b: DataFrame, col: str = "grad") -> float:
    """The dot product of two sharded vectors: what a two-loop recursion over tables needs."""
    x = a.select("idx", F.col(col).alias("x")).join(b.select("idx", F.col(col).alias("z")), "idx")
    return float(x.agg(F.sum(F.aggregate(F.zip_with("x", "z", lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v))).first()[0] or 0.0)


class Sharded:
    """A parameter vector of which one part is an array on the driver and the other a table (idx, v array<double>). It has what the
    optimisers ask of a vector, so these run on it as they are."""

    __array_ufunc__ = None  # products with numpy numbers come here

    def __init__(self, small: np.ndarray, table: DataFrame):
        self.small, self.table = small, table

    def _plus(self, other: Sharded, c: float) -> Sharded:
        z = other.table.select("idx", F.col("v").alias("w"))
        table = self.table.join(z, "idx").select("idx", F.zip_with("v", "w", lambda x, y: x + c * y).alias("v"))
        return Sharded(self.small + c * other.small, cut_lineage(table))

    def __add__(self, other: Sharded) -> Sharded:
        return self._plus(other, 1.0)

    def __sub__(self, other: Sharded) -> Sharded:
        return self._plus(other, -1.0)

    def __mul__(self, c: float) -> Sharded:
        return Sharded(self.small * float(c), self.table.select("idx", F.transform("v", lambda x: x * float(c)).alias("v")))

    __rmul__ = __mul__

    def __truediv__(self, c: float) -> Sharded:
        return self * (1 / float(c))

    def __matmul__(self, other: Sharded) -> float:
        return float(self.small @ other.small) + table_dot(self.table, other.table, "v")

    def copy(self) -> Sharded:
        return self

    def abs_sum(self) -> float:
        own = self.table.agg(F.sum(F.aggregate("v", F.lit(0.0), lambda s, x: s + F.abs(x)))).first()[0]
        return float(np.abs(self.small).sum()) + float(own or 0.0)


def start_factors(t: TensorFrame, mode: int, rank: int, seed: int = 0, scale: float = 0.5) -> DataFrame:
    """(idx, v): a normal of each index by its hash, made where it is used."""

    def uniform(r: int, which: int):
        return (F.floor(portable_hash(F.col("idx"), F.lit(mode), F.lit(r), F.lit(which), seed=seed + 51) / 64) + 0.5) / (MODULUS // 64)

    normal = lambda r: scale * F.sqrt(-2 * F.log(uniform(r, 0))) * F.cos(2 * np.pi * uniform(r, 1))
    return t.df.sparkSession.range(t.dims[mode]).select(F.col("id").alias("idx")).select("idx", F.array(*(normal(r) for r in range(rank))).alias("v"))


def init_anchored(t: TensorFrame, mode: int, ranks: int | list[int] = 3, p: int = 100, kernel: str = "ard", seed: int = 0) -> tuple[ModelState, DataFrame]:
    """(model without the anchored mode's factors, their table); inducing points are the inputs of p cells of small hash."""
    ranks = [ranks] * len(t.dims) if isinstance(ranks, int) else list(ranks)
    table = cut_lineage(start_factors(t, mode, ranks[mode], seed))
    few = smallest_hashes(t.df.select(*t.modes), t.modes, p, seed + 17).join(table.withColumnRenamed("idx", t.modes[mode]), t.modes[mode]).orderBy(*t.modes).toPandas()
    local = TensorFrame(t.df, tuple(0 if k == mode else d for k, d in enumerate(t.dims)), t.kind)
    factors = tuple(np.random.default_rng([seed, k]).normal(0, 0.5, (d, r)) for k, (d, r) in enumerate(zip(local.dims, ranks, strict=True)))
    own = replace(ModelState(factors, np.zeros((p, sum(ranks))), Kernel(kernel, np.ones(sum(ranks) if kernel == "ard" else 1)), 1.0, np.zeros(p), t.kind), factors=tuple(np.stack(few["v"]) if k == mode else u for k, u in enumerate(factors)))
    index = few[t.modes].to_numpy(np.int64)
    index[:, mode] = np.arange(len(index))
    z, rng = own.inputs(index), np.random.default_rng([seed, 98])
    if len(z) < p:
        z = np.vstack([z, rng.normal(0, 0.5, (p - len(z), z.shape[1]))])
    return replace(own, factors=factors, inducing=z + rng.normal(0, 0.01, z.shape)), table


def evaluate_anchored(t: TensorFrame, m: ModelState, table: DataFrame, mode: int, lam_iter: int = 30, shards: int = 8, salts: int = 1) -> tuple[float, Sharded, ModelState]:
    """(bound, gradient, model with its λ) with the factors of one mode in a table (idx, v)."""
    factors = table.withColumnRenamed("v", "factor")
    m = without(m, mode)
    s = anchored_stats(t, m, factors, mode, shards, salts)
    if m.kind == "real":
        a, dk, db = gaussian.adjoints(m, s)
        value = gaussian.value(m, s)
    else:
        lam, _, trace = probit.fixed_point(t, m, s, m.lam, max_iter=lam_iter, run=lambda t, m, x: anchored_lambda(t, m, x, factors, mode, shards, salts))
        m = replace(m, lam=lam)
        a, dk = probit.adjoints(m, s, lam)
        value, db = trace[-1], None
    rest, own = anchored_gradient(t, m, a, factors, mode, shards, salts)
    small = gaussian.to_logs(m, gaussian.finish(m, rest, dk, db))
    grads = table.join(own, "idx", "left").select("idx", F.when(F.col("grad").isNull(), F.transform("v", lambda x: -x)).otherwise(F.zip_with("grad", "v", lambda g, x: g - x)).alias("v"))
    return value - 0.5 * table_dot(table, table, "v"), Sharded(small, cut_lineage(grads)), m


def fit_anchored(t: TensorFrame, mode: int, ranks: int | list[int] = 3, p: int = 100, kernel: str = "ard", optimiser: str = "lbfgs", steps: int = 10, rate: float = 0.01, lam_iter: int = 30, shards: int = 8, salts: int = 1, memory: int = 3, seed: int = 0) -> tuple[ModelState, DataFrame]:
    """(model, table of the anchored mode's factors), by L-BFGS or gradient ascent over both parts together."""
    m, table = init_anchored(t, mode, ranks, p, kernel, seed)
    began, trace, warm = time.time(), [], {"lam": m.lam}

    def f(x: Sharded) -> tuple[float, Sharded]:
        value, g, seen = evaluate_anchored(t, replace(m.unpack(x.small), lam=warm["lam"]), x.table, mode, lam_iter, shards, salts)
        warm["lam"] = seen.lam
        return value, g

    log = lambda i, x, v: trace.append((i + 1, time.time() - began, v))
    start = Sharded(m.pack(), table)
    x, _, values = lbfgs(f, start, steps, memory, callback=log) if optimiser == "lbfgs" else gd(f, start, steps, rate, "backtrack" if optimiser == "gd" else optimiser.removeprefix("gd_"), callback=log)
    out = m.unpack(x.small)
    if m.kind == "binary":
        out = evaluate_anchored(t, replace(out, lam=warm["lam"]), x.table, mode, lam_iter, shards, salts)[2]
    return replace(out, trace=[(0, 0.0, values[0]), *trace]), x.table


def predict_anchored(train: TensorFrame, m: ModelState, table: DataFrame, mode: int, cells: DataFrame, shards: int = 8, salts: int = 1) -> DataFrame:
    """``cells`` with mean (score) and var; the anchored mode's rows come by a join, an index without one has the prior mean 0."""
    spark = cells.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(Predictor(without(m, mode), anchored_stats(train, m, table.withColumnRenamed("v", "factor"), mode, shards, salts)))
    names, modes, rank = cells.columns, train.modes, m.ranks[mode]
    joined = cells.join(table.select(F.col("idx").alias(modes[mode]), F.col("v").alias("own_factor")), modes[mode], "left")
    joined = joined.select(*names, F.coalesce("own_factor", F.array(*(F.lit(0.0) for _ in range(rank)))).alias("own_factor"))

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            index = np.stack([b.column(names.index(c)).to_numpy(zero_copy_only=False).astype(np.int64) for c in modes], 1)
            index[:, mode] = np.arange(len(index))
            own = b.column(len(names)).flatten().to_numpy().reshape(-1, rank)
            tool = copy.copy(shared.value)
            tool.m = replace(tool.m, factors=tuple(own if k == mode else u for k, u in enumerate(tool.m.factors)))
            f, var = tool(index)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(names)], pa.array(f), pa.array(var)], [*names, "mean" if tool.m.kind == "real" else "score", "var"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cells.schema.fields)
    return joined.mapInArrow(run, f"{schema}, {'mean' if m.kind == 'real' else 'score'} double, var double")


def mini_batch(t: TensorFrame, share: float, step: int) -> TensorFrame:
    """A hashed sample of the cells, another one each step; scale its statistics by ``scaled``."""
    h = portable_hash(*(F.col(c) for c in t.modes), seed=1000 + step)
    return t.with_df(t.df.where(h < int(MODULUS * share)))


def scaled(s: passes.Stats, share: float) -> passes.Stats:
    """Unbiased statistics of all cells from a sample of ``share`` of them."""
    return passes.Stats(s.g / share, s.h / share, s.s / share, s.c / share, round(s.n / share))
