"""Map passes over cells and their reductions.

A pass maps each partition to ONE vector of partial sums (Arrow in, numpy inside, BLAS per block) and the vectors are
summed without keys: directly where few, through one more level of tasks where their number times their size asks for it. The keyed
reductions, kept for comparison, send a row per (mode, index) of every cell instead.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import RDD
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import Kernel
from ..functions.special import hazard, hazard_and_log
from ..model import ModelState
from ..session import ship_package
from ..tensor import TensorFrame, unpack

MMAP_THRESHOLD, TRIM_THRESHOLD = -3, -1  # parameters of glibc's mallopt
KEPT_BYTES = 128 << 20  # of freed memory that a worker keeps for its next blocks


@lru_cache(1)
def keep_heap() -> None:
    """Blocks' arrays are made and freed many times a second: with this the allocator hands the same memory out again, where else every
    array would come from the system and be zeroed page by page. For workers; nothing changes where the allocator isn't glibc's."""
    try:
        mallopt = ctypes.CDLL(None).mallopt
    except (AttributeError, OSError):
        return
    mallopt(MMAP_THRESHOLD, 32 << 20)
    mallopt(TRIM_THRESHOLD, KEPT_BYTES)


BLOCK_BYTES = 1 << 20  # so that a block's kernel rows stay in a core's cache
DRIVER_BYTES = 256 << 20
FEW_BYTES = 4 << 20  # of vectors that the driver adds itself, so that its heap isn't filled pass by pass


def blocks(batches: Iterator[pa.RecordBatch], modes: int, p: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(index n×K, y n) in blocks whose n×p kernel rows fit BLOCK_BYTES."""
    most = max(256, BLOCK_BYTES // (8 * max(1, p)))
    for b in batches:
        index = np.stack([b.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(modes)], 1) if b.num_rows else np.zeros((0, modes), np.int64)
        y = b.column(modes).to_numpy(zero_copy_only=False).astype(float)
        for lo in range(0, len(y), most):
            yield index[lo : lo + most], y[lo : lo + most]


def sum_vectors(vectors: DataFrame, size: int) -> np.ndarray:
    """The sum of one packed vector per partition: the key-free reduction."""
    parts = vectors.rdd.getNumPartitions()
    if parts * size * 8 > DRIVER_BYTES and parts > 16:
        groups = max(2, int(np.sqrt(parts)))

        def add(batches):
            total = np.zeros(size)
            for b in batches:
                for x in b.column(0):
                    total += np.frombuffer(x.as_buffer(), float)
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["v"])

        vectors = vectors.repartition(groups).mapInArrow(add, "v binary")
    total = np.zeros(size)
    for r in vectors.toLocalIterator() if parts * size * 8 > DRIVER_BYTES else vectors.collect():
        total += np.frombuffer(r.v, float)
    return total


def sum_slices(rows: DataFrame, size: int, width: int, tasks: int) -> np.ndarray:
    """The vector of ``size`` whose slices of ``width`` numbers are the sums of ``rows`` (slice, at, v): v holds numbers (or, with
    places in ``at``, numbers for these places of the slice) as bytes. Slices are added in tasks; the driver gets each once."""

    def add(batches):
        totals = {}
        for b in batches:
            for i, at, v in zip(b.column(0), b.column(1), b.column(2), strict=True):
                part = np.frombuffer(v.as_buffer(), float)
                k = i.as_py()
                if k not in totals:
                    totals[k] = np.zeros(min(width, size - k * width))
                if at.is_valid:
                    places = np.frombuffer(at.as_buffer(), np.int64)
                    each = len(part) // max(1, len(places))
                    totals[k].reshape(-1, each)[places] += part.reshape(-1, each)
                else:
                    totals[k] += part
        for k, x in totals.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([x.tobytes()], pa.binary())], ["slice", "v"])

    out = np.zeros(size)
    sums = rows.repartition(tasks, "slice").mapInArrow(add, "slice long, v binary")
    if size * 8 > DRIVER_BYTES // 4:
        for r in sums.toLocalIterator():
            out[r["slice"] * width : (r["slice"] + 1) * width] = np.frombuffer(r["v"], float)
        return out
    got = sums.toArrow()  # the driver's JVM passes the bytes on and makes no rows of them
    for k, v in zip(got.column("slice").to_pylist(), got.column("v"), strict=True):
        out[k * width : (k + 1) * width] = np.frombuffer(v.as_buffer(), float)
    return out


SLICE = 1 << 19  # numbers of a vector that travel in one row; longer vectors are cut


PACKED = "slice long, at binary, v binary"


def packed(total: np.ndarray, width: int) -> Iterator[pa.RecordBatch]:
    """A task's vector by slices."""
    for k, lo in enumerate(range(0, len(total), width)):
        yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([None], pa.binary()), pa.array([total[lo : lo + width].tobytes()], pa.binary())], ["slice", "at", "v"])


def sum_packed(rows: DataFrame, size: int, width: int) -> np.ndarray:
    """The sum of one packed vector per partition: the key-free reduction. Few short vectors are added on the driver."""
    if size > width or rows.rdd.getNumPartitions() * size * 8 > DRIVER_BYTES:
        return sum_slices(rows, size, width, min(16, -(-size // width)))
    out = np.zeros(size)
    for r in rows.collect():
        out += np.frombuffer(r["v"], float)
    return out


def sum_rdd(rows: RDD, size: int, width: int) -> np.ndarray:
    """The vector of ``size`` from ``rows`` (slice, numbers) of its slices of ``width``: added on the driver while few and short, in tasks
    else."""
    out = np.zeros(size)
    if size <= width and rows.getNumPartitions() * size * 8 <= FEW_BYTES:
        for _, v in rows.collect():
            out += v
        return out
    sums = rows.reduceByKey(np.add, min(16, -(-size // width)))
    for k, v in sums.toLocalIterator() if size * 8 > DRIVER_BYTES // 4 else sums.collect():
        out[k * width : (k + 1) * width] = v
    return out


def slices(total: np.ndarray, width: int) -> Iterator[tuple[int, np.ndarray]]:
    for k, lo in enumerate(range(0, len(total), width)):
        yield k, total[lo : lo + width]


def map_sum(t: TensorFrame, size: int, p: int, state, each: Callable | None = None, add: Callable | None = None) -> np.ndarray:
    """Σ over blocks of ``each(state, index, y)``, a vector of ``size``; for long vectors, of which a block touches little,
    ``add(total, state, index, y)`` adds to the task's sum in place."""
    spark = t.df.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(state)
    modes, width = len(t.dims), SLICE

    def task(cells) -> np.ndarray:
        keep_heap()
        total = np.zeros(size)
        for index, y in cells:
            if add is not None:
                add(total, shared.value, index, y)
            else:
                total += each(shared.value, index, y)
        return total

    def run(batches):
        yield from packed(task(blocks(batches, modes, p)), width)

    if t.packed is not None:
        most = max(256, BLOCK_BYTES // (8 * max(1, p)))

        def cut(rows):
            for index, y in map(unpack, rows):
                for lo in range(0, len(y), most):
                    yield index[lo : lo + most], y[lo : lo + most]

        out = sum_rdd(t.packed.mapPartitions(lambda rows: slices(task(cut(rows)), width)), size, width)
        shared.destroy()
        return out

    out = sum_packed(t.df.select(*t.modes, "y").mapInArrow(run, PACKED), size, width)
    shared.destroy()
    return out


class Stats:
    """G = Σ k kᵀ, h = Σ k y, s = Σ y², c = Σ k(x, x), n."""

    def __init__(self, g: np.ndarray, h: np.ndarray, s: float, c: float, n: int):
        self.g, self.h, self.s, self.c, self.n = g, h, s, c, n

    @classmethod
    def unpack(cls, v: np.ndarray, p: int) -> Stats:
        g = np.zeros((p, p))
        tri = np.triu_indices(p)
        m = len(tri[0])
        g[tri] = v[:m]
        g = g + np.triu(g, 1).T
        return cls(g, v[m : m + p], float(v[m + p]), float(v[m + p + 1]), int(round(v[m + p + 2])))


@lru_cache(8)
def upper(p: int) -> np.ndarray:
    """Places of the upper triangle in a flat p × p matrix."""
    i, j = np.triu_indices(p)
    return i * p + j


TABLE_BYTES = 32 << 20  # of a task, for the kernel's parts of the modes with few indices
_TABLES: list = []  # (model, their tables): of the last model only


def _parts(m: ModelState) -> tuple[list[slice], list[int], dict[int, np.ndarray]]:
    """(each mode's columns of the inputs, modes by their sizes, the kernel's part by index of those whose tables fit TABLE_BYTES)."""
    if not _TABLES or _TABLES[0] is not m:
        ends = np.cumsum([0, *m.ranks])
        at = [slice(lo, hi) for lo, hi in zip(ends, ends[1:], strict=False)]
        order = sorted(range(len(at)), key=lambda k: len(m.factors[k]))
        tables, left = {}, TABLE_BYTES // (8 * max(1, len(m.inducing)))
        for k in order:
            if (left := left - len(m.factors[k])) >= 0:
                tables[k] = m.kernel.bell(m.factors[k], m.inducing[:, at[k]], at[k])
        _TABLES[:] = m, (at, order, tables)
    return _TABLES[1]


def unit_rows(m: ModelState, index: np.ndarray) -> np.ndarray:
    """k / a² of a bell for cells with known indices. It is the product of its modes' bells: those of modes with few indices come from
    tables, that of the largest mode is made once for each run of an index in the block, and one over the rest for each cell."""
    at, order, tables = _parts(m)
    out, rest = None, [k for k in order if k not in tables]
    if rest:
        i = index[:, rest[-1]]
        new = np.append(True, i[1:] != i[:-1])
        if 2 * np.count_nonzero(new) <= len(i):
            k = rest.pop()
            out = m.kernel.bell(m.factors[k][i[new]], m.inducing[:, at[k]], at[k])[np.cumsum(new) - 1]
    if rest:
        cols = np.concatenate([np.arange(at[k].start, at[k].stop) for k in rest])
        part = m.kernel.bell(np.hstack([m.factors[k][index[:, k]] for k in rest]), m.inducing[:, cols], cols)
        out = part if out is None else np.multiply(out, part, out=out)
    for k, table in tables.items():
        part = table[index[:, k]]
        out = part if out is None else np.multiply(out, part, out=out)
    return out


def kernel_rows(m: ModelState, index: np.ndarray) -> np.ndarray:
    """The kernel of cells against the inducing points."""
    known = len(index) > 0 and index.min() >= 0 and all(index[:, k].max() < len(u) for k, u in enumerate(m.factors))
    if not known or m.kernel.name not in ("rbf", "ard"):
        return m.kernel.gram(m.inputs(index), m.inducing)
    k = unit_rows(m, index)
    k *= m.kernel.amp2
    return k


def block_stats(m: ModelState, index: np.ndarray, y: np.ndarray, k: np.ndarray | None = None) -> np.ndarray:
    k = kernel_rows(m, index) if k is None else k
    c = m.kernel.diag(m.inputs(index) if m.kernel.name == "linear" else index).sum()
    return np.concatenate([(k.T @ k).ravel()[upper(len(m.inducing))], k.T @ y, [y @ y, c, len(y)]])


def suff_stats(t: TensorFrame, m: ModelState) -> Stats:
    p = len(m.inducing)
    return Stats.unpack(map_sum(t, p * (p + 1) // 2 + p + 3, p, m, block_stats), p)


def input_stats(rows: DataFrame, points: np.ndarray, kernel: Kernel) -> Stats:
    """The sums over rows (x array<double>, y) that bring their inputs with them: no factor leaves its row."""
    spark = rows.sparkSession
    ship_package(spark)
    p = len(points)
    size = p * (p + 1) // 2 + p + 3
    shared = spark.sparkContext.broadcast((points, kernel))
    most, width = max(256, BLOCK_BYTES // (8 * max(1, p))), SLICE

    def run(batches):
        total = np.zeros(size)
        z, kern = shared.value
        for b in batches:
            y = b.column(1).to_numpy(zero_copy_only=False).astype(float)
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(len(y), z.shape[1])
            for lo in range(0, len(y), most):
                xs, ys = x[lo : lo + most], y[lo : lo + most]
                k = kern.gram(xs, z)
                total += np.concatenate([(k.T @ k).ravel()[upper(p)], k.T @ ys, [ys @ ys, kern.diag(xs).sum(), len(ys)]])
        yield from packed(total, width)

    out = sum_packed(rows.select("x", "y").mapInArrow(run, PACKED), size, width)
    shared.destroy()
    return Stats.unpack(out, p)


def block_lambda(state, index: np.ndarray, y: np.ndarray, k: np.ndarray | None = None) -> np.ndarray:
    """Σ k t ρ and Σ log Φ(t u) for t = 2y - 1, u = kᵀλ."""
    m, lam = state
    k = kernel_rows(m, index) if k is None else k
    t = 2 * y - 1
    rho, log_phi = hazard_and_log(t * (k @ lam))
    return np.append(k.T @ (t * rho), log_phi.sum())


def lambda_pass(t: TensorFrame, m: ModelState, lam: np.ndarray) -> tuple[np.ndarray, float]:
    v = map_sum(t, len(lam) + 1, len(lam), (m, lam), block_lambda)
    return v[:-1], float(v[-1])


def block_stats_lambda(state, index: np.ndarray, y: np.ndarray) -> np.ndarray:
    """``block_stats`` and ``block_lambda`` from one set of kernel rows."""
    m, lam = state
    k = kernel_rows(m, index)
    return np.concatenate([block_stats(m, index, y, k), block_lambda(state, index, y, k)])


def stats_lambda_pass(t: TensorFrame, m: ModelState, lam: np.ndarray) -> tuple[Stats, tuple[np.ndarray, float]]:
    """``suff_stats`` and ``lambda_pass`` in one pass."""
    p = len(lam)
    size = p * (p + 1) // 2 + p + 3
    v = map_sum(t, size + p + 1, p, (m, lam), block_stats_lambda)
    return Stats.unpack(v[:size], p), (v[size:-1], float(v[-1]))


class Adjoints:
    """Derivatives of the bound by G, h and c, and for binary data the λ whose likelihood term each cell adds."""

    def __init__(self, dg: np.ndarray, dh: np.ndarray, dc: float, lam: np.ndarray | None = None):
        self.dg, self.dh, self.dc, self.lam = dg, dh, dc, lam


def cell_gradients(m: ModelState, a: Adjoints, index: np.ndarray, y: np.ndarray, logs: list | None = None):
    """(dx per cell, dz, dlengths, da²) of the data terms; ``logs`` gets Σ log Φ(t u) of binary ones."""
    x, bell = m.inputs(index), m.kernel.name in ("rbf", "ard")
    if bell:
        k = kernel_rows(m, index)
    else:
        unit = m.kernel.unit(x, m.inducing)
        k = m.kernel.amp2 * unit[0]
    g = k @ (2 * a.dg)
    if a.lam is None:
        g += y[:, None] * a.dh
    else:
        t = 2 * y - 1
        if logs is None:
            rho = hazard(t * (k @ a.lam))
        else:
            rho, log_phi = hazard_and_log(t * (k @ a.lam))
            logs.append(float(log_phi.sum()))
        g += np.multiply.outer(t * rho, a.lam)
    dx, dz, dl, da = m.kernel.bell_vjp(x, m.inducing, g, k) if bell else m.kernel.vjp(x, m.inducing, g, unit)
    ex, el, ea = m.kernel.diag_vjp(x, np.full(len(y), a.dc))
    return dx + ex, dz, dl + el, da + ea


def add_gradient_log(total: np.ndarray, state, index: np.ndarray, y: np.ndarray) -> None:
    """``add_gradient``, and Σ log Φ(t u) in the last place."""
    logs = []
    add_gradient(total[:-1], state, index, y, logs)
    total[-1] += sum(logs)


def add_gradient(total: np.ndarray, state, index: np.ndarray, y: np.ndarray, logs: list | None = None) -> None:
    """Adds the cells' gradient to ``total`` in place: a block touches its own indices, however long the factors are."""
    if not len(y):
        return
    m, a = state
    dx, dz, dl, da = cell_gradients(m, a, index, y, logs)
    lo, at = 0, 0
    for k, u in enumerate(m.factors):
        r = u.shape[1]
        places = index[:, k, None] * r + np.arange(r)
        np.add.at(total[lo : lo + u.size], places.ravel(), dx[:, at : at + r].ravel())
        lo, at = lo + u.size, at + r
    total[lo:] += np.concatenate([dz.ravel(), dl, [da]])


def block_gradient(state, index: np.ndarray, y: np.ndarray) -> np.ndarray:
    m = state[0]
    total = np.zeros(sum(u.size for u in m.factors) + m.inducing.size + len(m.kernel.lengths) + 1)
    add_gradient(total, state, index, y)
    return total


def gradient_pass(t: TensorFrame, m: ModelState, a: Adjoints) -> np.ndarray:
    """[factors | inducing | lengths | a²], key-free: whole vectors are summed."""
    size = sum(u.size for u in m.factors) + m.inducing.size + len(m.kernel.lengths) + 1
    return map_sum(t, size, len(m.inducing), (m, a), add=add_gradient)


def gradient_log_pass(t: TensorFrame, m: ModelState, a: Adjoints) -> tuple[np.ndarray, float]:
    """``gradient_pass`` and Σ log Φ at the adjoints' λ in one pass."""
    size = sum(u.size for u in m.factors) + m.inducing.size + len(m.kernel.lengths) + 2
    v = map_sum(t, size, len(m.inducing), (m, a), add=add_gradient_log)
    return v[:-1], float(v[-1])


def _keyed_rows(t: TensorFrame, m: ModelState, a: Adjoints, combine: bool) -> DataFrame:
    """(mode, idx, grad array): a row for every cell and mode, or for every index a block touches with ``combine``."""
    spark = t.df.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast((m, a))
    modes, p = len(t.dims), len(m.inducing)

    def run(batches):
        model, adj = shared.value
        for index, y in blocks(batches, modes, p):
            if not len(y):
                continue
            dx, _, _, _ = cell_gradients(model, adj, index, y)
            at = 0
            for k, u in enumerate(model.factors):
                g, i = dx[:, at : at + u.shape[1]], index[:, k]
                at += u.shape[1]
                if combine:
                    keys, inv = np.unique(i, return_inverse=True)
                    g, i = np.stack([np.bincount(inv, g[:, j], len(keys)) for j in range(g.shape[1])], 1), keys
                ends = np.arange(len(i) + 1, dtype=np.int32) * g.shape[1]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), k + 1, np.int32)), pa.array(i), pa.ListArray.from_arrays(ends, g.ravel())], ["mode", "idx", "grad"])

    return t.df.select(*t.modes, "y").mapInArrow(run, "mode int, idx long, grad array<double>")


def keyed_gradient(t: TensorFrame, m: ModelState, a: Adjoints, combine: bool = False) -> DataFrame:
    """(mode, idx, pos, grad): the factor gradient by a keyed shuffle."""
    rows = _keyed_rows(t, m, a, combine).select("mode", "idx", F.posexplode("grad").alias("pos", "g"))
    return rows.groupBy("mode", "idx", "pos").agg(F.sum("g").alias("grad"))


def keyed_raw_gradient(t: TensorFrame, m: ModelState, a: Adjoints) -> dict[tuple[int, int], np.ndarray]:
    """The keyed reduction without any combining before the shuffle."""
    rdd = _keyed_rows(t, m, a, False).rdd.map(lambda r: ((r["mode"], r["idx"]), list(r["grad"])))
    return {k: np.array(v) for k, v in rdd.groupByKey().mapValues(lambda gs: [sum(c) for c in zip(*gs, strict=True)]).collect()}


def keyed_to_vector(df: DataFrame, m: ModelState) -> np.ndarray:
    out = [np.zeros_like(u) for u in m.factors]
    for r in df.toLocalIterator():
        out[r["mode"] - 1][r["idx"], r["pos"]] = r["grad"]
    return np.concatenate([u.ravel() for u in out])
