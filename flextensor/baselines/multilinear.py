"""CP (ALS, on balanced cells, nonnegative), its large-scale form, HOSVD and Tucker (HOOI).

Sparse work is keyed DataFrame aggregation: MTTKRP broadcasts the other modes' factors and sums per index, so the
Khatri-Rao product never exists; r×r systems are solved on the driver. The large-scale CP keeps its factors as tables.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sampling import MODULUS, portable_hash
from ..session import cut_lineage, ship_package
from ..tensor import TensorFrame, unpack


@dataclass(frozen=True)
class CP:
    factors: tuple[np.ndarray, ...]

    def __call__(self, index: np.ndarray) -> np.ndarray:
        out = 1.0
        for k, u in enumerate(self.factors):
            out = out * u[index[:, k]]
        return out.sum(1)


@dataclass(frozen=True)
class Tucker:
    core: np.ndarray
    factors: tuple[np.ndarray, ...]

    def __call__(self, index: np.ndarray) -> np.ndarray:
        k = len(self.factors)
        letters = "abcdefgh"[:k]
        return np.einsum(letters + "," + ",".join("z" + x for x in letters) + "->z", self.core, *(u[index[:, j]] for j, u in enumerate(self.factors)))


def predict_cells(model, cells: DataFrame, modes: list[str], name: str = "mean") -> DataFrame:
    """``cells`` with the model's value; indices beyond the factors give 0."""
    ship_package(cells.sparkSession)
    shared = cells.sparkSession.sparkContext.broadcast(model)
    names = cells.columns

    def run(batches):
        for b in batches:
            index = np.stack([b.column(names.index(m)).to_numpy(zero_copy_only=False).astype(np.int64) for m in modes], 1)
            sizes = np.array([len(u) for u in shared.value.factors])
            known = ((index >= 0) & (index < sizes)).all(1)
            v = np.where(known, shared.value(np.where(known[:, None], index, 0)), 0.0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(v)], [*names, name])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cells.schema.fields)
    return cells.mapInArrow(run, f"{schema}, {name} double")


def keyed_sums(t: TensorFrame, shared_value, k: int, width: int, each) -> DataFrame:
    """(idx, pos, v): per index of mode k the sums of ``each(value, index columns, y)``, rows of ``width`` numbers a cell. Each task
    combines its own cells first."""
    ship_package(t.df.sparkSession)
    shared = t.df.sparkSession.sparkContext.broadcast(shared_value)
    modes = len(t.dims)

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            index = [b.column(j).to_numpy(zero_copy_only=False).astype(np.int64) for j in range(modes)]
            v = each(shared.value, index, b.column(modes).to_numpy(zero_copy_only=False).astype(float))
            keys, inv = np.unique(index[k], return_inverse=True)
            sums = np.stack([np.bincount(inv, v[:, r], len(keys)) for r in range(width)], 1)
            ends = np.arange(len(keys) + 1, dtype=np.int32) * width
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.ListArray.from_arrays(ends, sums.ravel())], ["idx", "g"])

    rows = t.df.select(*t.modes, "y").mapInArrow(run, "idx long, g array<double>")
    return rows.select("idx", F.posexplode("g").alias("pos", "v")).groupBy("idx", "pos").agg(F.sum("v").alias("v"))


SLICE_BYTES = 8 << 20
WHOLE_BYTES = 128 << 20  # a task holds a mode's sums whole up to this size
CELLS_AT_ONCE = 200_000


def by_slices(keys: np.ndarray, sums: np.ndarray, most: int):
    """Rows (slice, at, v) of sorted ``keys`` and their sums, cut at every ``most`` indices."""
    cuts = np.searchsorted(keys, np.arange(keys[0] // most, keys[-1] // most + 2) * most)
    for lo, hi in zip(cuts, cuts[1:], strict=False):
        if hi > lo:
            at = keys[lo] // most
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([(keys[lo:hi] - at * most).tobytes()], pa.binary()), pa.array([sums[lo:hi].tobytes()], pa.binary())], ["slice", "at", "v"])


def dense_sums(t: TensorFrame, shared_value, k: int, width: int, each) -> np.ndarray:
    """``keyed_sums`` as an array, index × width: tasks send sums by slices of the mode and the slices are added in tasks, so that the
    driver gets each number once and no row of its own."""
    from ..exec.passes import PACKED, SLICE, keep_heap, slices, sum_rdd, sum_slices

    ship_package(t.df.sparkSession)
    shared = t.df.sparkSession.sparkContext.broadcast(shared_value)
    modes, d = len(t.dims), t.dims[k]
    if t.packed is not None and d * width * 8 <= WHOLE_BYTES:

        def whole(rows):
            keep_heap()
            total = np.zeros(d * width)
            for index, y in map(unpack, rows):
                v = each(shared.value, list(index.T), y)
                np.add.at(total, (index[:, k, None] * width + np.arange(width)).ravel(), v.ravel())
            yield from slices(total, SLICE)

        out = sum_rdd(t.packed.mapPartitions(whole), d * width, SLICE)
        shared.destroy()
        return out.reshape(d, width)
    most = max(1, SLICE_BYTES // (8 * width))  # indices of a slice

    def send(index, v):
        keys, inv = np.unique(index, return_inverse=True)
        yield from by_slices(keys, np.stack([np.bincount(inv, v[:, r], len(keys)) for r in range(width)], 1), most)

    def run(batches):
        held, n = [], 0
        for b in batches:
            if not b.num_rows:
                continue
            index = [b.column(j).to_numpy(zero_copy_only=False).astype(np.int64) for j in range(modes)]
            held.append((index[k], each(shared.value, index, b.column(modes).to_numpy(zero_copy_only=False).astype(float))))
            n += b.num_rows
            if n * width > CELLS_AT_ONCE * 9:
                yield from send(*map(np.concatenate, zip(*held, strict=True)))
                held, n = [], 0
        if held:
            yield from send(*map(np.concatenate, zip(*held, strict=True)))

    rows = t.df.select(*t.modes, "y").mapInArrow(run, PACKED)
    out = sum_slices(rows, d * width, most * width, min(16, -(-d // most)))
    shared.destroy()
    return out.reshape(d, width)


def _others(factors, index: list[np.ndarray], k: int):
    out = 1.0
    for j, u in enumerate(factors):
        if j != k:
            out = out * u[index[j]]
    return out


def mttkrp(t: TensorFrame, factors: tuple[np.ndarray, ...], k: int) -> DataFrame:
    """(idx, pos, v): per index of mode k the cells' values times the other modes' factor rows."""
    return keyed_sums(t, factors, k, factors[0].shape[1], lambda us, index, y: y[:, None] * _others(us, index, k))


def dense_mttkrp(t: TensorFrame, factors: tuple[np.ndarray, ...], k: int) -> np.ndarray:
    return dense_sums(t, factors, k, factors[0].shape[1], lambda us, index, y: y[:, None] * _others(us, index, k))


def _start(dims: tuple[int, ...], rank: int, seed: int, positive: bool = False) -> list[np.ndarray]:
    rng = np.random.default_rng(seed)
    return [rng.random((d, rank)) if positive else rng.standard_normal((d, rank)) * 0.5 for d in dims]


def fit_cp(t: TensorFrame, rank: int = 3, sweeps: int = 20, ridge: float = 1e-6, observed_only: bool = False, seed: int = 0) -> CP:
    """Alternating least squares; missing cells are zeros, or with ``observed_only`` left out (rows solved one by one)."""
    if observed_only:
        return _fit_cp_rows(t, rank, sweeps, max(ridge, 1e-3), seed)
    u = _start(t.dims, rank, seed)
    for _ in range(sweeps):
        for k in range(len(u)):
            gram = np.ones((rank, rank))
            for j, x in enumerate(u):
                if j != k:
                    gram = gram * (x.T @ x)
            u[k] = np.linalg.solve(gram + ridge * np.eye(rank), dense_mttkrp(t, tuple(u), k).T).T
    return CP(tuple(u))


def _fit_cp_rows(t: TensorFrame, rank: int, sweeps: int, ridge: float, seed: int) -> CP:
    """Least squares over the selected cells only: one r×r system per index. Its normal equations are sums over cells, so a hot
    index is combined in every task before the shuffle."""
    u = _start(t.dims, rank, seed)
    tri = np.triu_indices(rank)
    n = len(tri[0])
    for _ in range(sweeps):
        for k in range(len(u)):

            def equations(us, index, y, k=k):
                x = _others(us, index, k)
                return np.hstack([x[:, tri[0]] * x[:, tri[1]], x * y[:, None]])

            e = dense_sums(t, tuple(u), k, n + rank, equations)
            g = np.zeros((t.dims[k], rank, rank))
            g[:, tri[0], tri[1]] = g[:, tri[1], tri[0]] = e[:, :n]
            u[k] = np.linalg.solve(g + ridge * np.eye(rank), e[:, n:, None])[:, :, 0]
    return CP(tuple(u))


def table_start(t: TensorFrame, rank: int, seed: int = 0) -> list[DataFrame]:
    """(idx, c_0..c_r-1) of each mode: hashed uniform numbers of the spread of a normal of 0.5."""
    spark = t.df.sparkSession
    at = lambda k, r: (portable_hash(F.col("idx"), F.lit(k), F.lit(r), seed=seed + 41) / MODULUS - 0.5) * np.sqrt(12) * 0.5
    return [spark.range(d).select(F.col("id").alias("idx")).select("idx", *(at(k, r).alias(f"c_{r}") for r in range(rank))) for k, d in enumerate(t.dims)]


def _table_gram(u: DataFrame, rank: int) -> np.ndarray:
    tri = np.triu_indices(rank)
    row = u.agg(*(F.sum(F.col(f"c_{i}") * F.col(f"c_{j}")) for i, j in zip(*tri, strict=True))).first()
    g = np.zeros((rank, rank))
    g[tri] = [x or 0.0 for x in row]
    return g + np.triu(g, 1).T


def sparse_cp_tables(t: TensorFrame, rank: int = 3, sweeps: int = 20, ridge: float = 1e-6, seed: int = 0, start: list[DataFrame] | None = None) -> list[DataFrame]:
    """CP for large sparse tensors, missing cells being zeros. Factors are tables of one column per component and never meet in one
    place: cells join the other modes' rows, components are multiplied column by column, and each index sums its own, so the
    Khatri-Rao product is never formed. Only r×r grams reach the driver. Indices without cells have no row: their factor is 0."""
    names = [f"c_{r}" for r in range(rank)]
    u = list(start or table_start(t, rank, seed))
    grams = [_table_gram(x, rank) for x in u]
    cells = t.df.select(*t.modes, "y")
    for _ in range(sweeps):
        for k, m in enumerate(t.modes):
            met = cells.select("*", *(F.col("y").alias(c) for c in names))
            gram = np.ones((rank, rank))
            for j, other in enumerate(t.modes):
                if j != k:
                    rows = u[j].select(F.col("idx").alias(other), *(F.col(c).alias(f"x{c}") for c in names))
                    met = met.join(rows, other).select(*t.modes, *((F.col(c) * F.col(f"x{c}")).alias(c) for c in names))
                    gram = gram * grams[j]
            sums = met.groupBy(F.col(m).alias("idx")).agg(*(F.sum(c).alias(c) for c in names))
            inv = np.linalg.inv(gram + ridge * np.eye(rank))
            mix = [sum((F.col(names[i]) * float(inv[i, r]) for i in range(rank)), F.lit(0.0)).alias(names[r]) for r in range(rank)]
            u[k] = cut_lineage(sums.select("idx", *mix))
            grams[k] = _table_gram(u[k], rank)
    return u


def predict_tables(tables: list[DataFrame], cells: DataFrame, modes: list[str], name: str = "mean") -> DataFrame:
    """``cells`` with the value of factors kept as tables: one join a mode, no factor on the driver."""
    names = tables[0].columns[1:]
    out = cells.select("*", *(F.lit(1.0).alias(f"p{c}") for c in names))
    for m, u in zip(modes, tables, strict=True):
        rows = u.select(F.col("idx").alias(m), *(F.col(c).alias(f"x{c}") for c in names))
        out = out.join(rows, m, "left").select(*cells.columns, *((F.col(f"p{c}") * F.coalesce(F.col(f"x{c}"), F.lit(0.0))).alias(f"p{c}") for c in names))
    return out.select(*cells.columns, sum((F.col(f"p{c}") for c in names), F.lit(0.0)).alias(name))


def fit_sparse_cp(t: TensorFrame, rank: int = 3, sweeps: int = 20, seed: int = 0) -> CP:
    """``sparse_cp_tables`` with its factors gathered, for modes that fit the driver."""
    out = []
    for d, u in zip(t.dims, sparse_cp_tables(t, rank, sweeps, seed=seed), strict=True):
        got, x = u.toArrow(), np.zeros((d, rank))  # no row of the table becomes one on the driver
        for r, c in enumerate(u.columns[1:]):
            x[got["idx"].to_numpy(), r] = got[c].to_numpy()
        out.append(x)
    return CP(tuple(out))


def fit_nncp(t: TensorFrame, rank: int = 3, sweeps: int = 30, seed: int = 0) -> CP:
    """Nonnegative CP by multiplicative updates; negative values count as zero."""
    u = _start(t.dims, rank, seed, True)
    positive = lambda us, index, y, k: np.maximum(y, 0.0)[:, None] * _others(us, index, k)
    for _ in range(sweeps):
        for k in range(len(u)):
            gram = np.ones((rank, rank))
            for j, x in enumerate(u):
                if j != k:
                    gram = gram * (x.T @ x)
            u[k] = u[k] * dense_sums(t, tuple(u), k, rank, partial(positive, k=k)) / (u[k] @ gram + 1e-12)
    return CP(tuple(u))


def unfolding_gram(t: TensorFrame, k: int) -> np.ndarray:
    """The gram of the mode-k unfolding, for small modes: a task has all cells of a column, which agree in all other modes, and adds the
    products of their pairs to its own gram; no pair becomes a row of a table."""
    from ..exec.passes import PACKED, SLICE, packed, sum_packed

    d, cells = t.dims[k], _by_column(t, k)

    def run(batches):
        held = [[c.to_numpy(zero_copy_only=False) for c in b.columns] for b in batches if b.num_rows]
        if not held:
            return
        idx, y, col = map(np.concatenate, zip(*held, strict=True))
        order = np.argsort(col, kind="stable")
        idx, y, col = idx[order].astype(np.int64), y[order], col[order]
        g, at = np.zeros(d * d), np.arange(len(col))  # the cells that have one of their column r places further on
        np.add.at(g, idx * d + idx, y * y)
        r = 0
        while True:
            r += 1
            at = at[: np.searchsorted(at, len(col) - r)]
            at = at[col[at] == col[at + r]]
            if not len(at):
                break
            v, a, b = y[at] * y[at + r], idx[at], idx[at + r]
            np.add.at(g, a * d + b, v)
            np.add.at(g, b * d + a, v)
        yield from packed(g, SLICE)

    out = sum_packed(cells.mapInArrow(run, PACKED), d * d, SLICE)
    cells.unpersist()
    return out.reshape(d, d)


def core_of(t: TensorFrame, factors: list[np.ndarray]) -> np.ndarray:
    """Σ y times the outer product of the cells' factor rows: a key-free sum."""
    from ..exec.passes import map_sum

    shape = tuple(u.shape[1] for u in factors)
    letters = "abcdefgh"[: len(factors)]
    spec = "z," + ",".join("z" + x for x in letters) + "->" + letters

    def each(us, index, y):
        return np.einsum(spec, y, *(u[index[:, j]] for j, u in enumerate(us))).ravel() if len(y) else np.zeros(int(np.prod(shape)))

    return map_sum(t, int(np.prod(shape)), 16, tuple(factors), each).reshape(shape)


def _leading(g: np.ndarray, r: int) -> np.ndarray:
    _, v = np.linalg.eigh(g)
    return v[:, ::-1][:, :r]


GRAM_SIDE = 2_000  # modes up to this size have their whole gram on the driver


def range_finder(t: TensorFrame, k: int, r: int, extra: int = 10, powers: int = 2, seed: int = 0) -> np.ndarray:
    """Leading left vectors of the mode-k unfolding by a randomised range: the unfolding times a random matrix of Khatri-Rao
    form is one MTTKRP; a power step and the small gram inside the range are sums over the unfolding's columns, whose cells a task has
    together: the range is broadcast, and no row of it becomes a row of a table."""
    s = min(t.dims[k], r + extra)
    rng = np.random.default_rng([seed, k])
    q, _ = np.linalg.qr(dense_mttkrp(t, tuple(rng.standard_normal((d, s)) for d in t.dims), k))
    by_column = _by_column(t, k)
    for _ in range(powers):
        q, _ = np.linalg.qr(_power_step(by_column, q, t.dims[k]))
    g = _range_gram(by_column, q)
    by_column.unpersist()
    return q @ _leading(g, r)


COLUMN_CELLS = 400_000  # about so many cells a task, with whole columns of the unfolding


def _by_column(t: TensorFrame, k: int) -> DataFrame:
    """(idx, y, col): the cells of mode k dealt by the other modes, whose hash tells the columns of the unfolding apart in a task."""
    others = [(F.col(x), d) for j, (x, d) in enumerate(zip(t.modes, t.dims, strict=True)) if j != k]
    n, col, size = t.df.count(), F.lit(0).cast("long"), 1
    for x, d in others:
        col, size = col * d + x, size * d
    if size >= 2**62:  # too many columns for a number each
        col = F.xxhash64(*(x for x, _ in others))
    cells = t.df.select(F.col(t.modes[k]).alias("idx"), "y", col.alias("col"))
    return cells.repartition(max(4, -(-n // COLUMN_CELLS)), "col").persist()


def _columns(batches, q: np.ndarray):
    """(idx, y, column of each cell, columns × width: the columns' products with the range) of a task's cells."""
    held = [[c.to_numpy(zero_copy_only=False) for c in b.columns] for b in batches if b.num_rows]
    if not held:
        return None
    idx, y, col = map(np.concatenate, zip(*held, strict=True))
    names, inv = np.unique(col, return_inverse=True)
    w = np.empty((len(names), q.shape[1]))
    for j in range(q.shape[1]):
        w[:, j] = np.bincount(inv, y * q[idx, j], len(names))
    return idx, y, inv, w


def _power_step(cells: DataFrame, q: np.ndarray, d: int) -> np.ndarray:
    """The unfolding times its transpose times ``q``."""
    from ..exec.passes import PACKED, sum_slices

    ship_package(cells.sparkSession)
    shared, width = cells.sparkSession.sparkContext.broadcast(q), q.shape[1]
    most = max(1, SLICE_BYTES // (8 * width))

    def run(batches):
        got = _columns(batches, shared.value)
        if got is None:
            return
        idx, y, inv, w = got
        keys, at = np.unique(idx, return_inverse=True)
        yield from by_slices(keys, np.stack([np.bincount(at, y * w[inv, j], len(keys)) for j in range(width)], 1), most)

    out = sum_slices(cells.mapInArrow(run, PACKED), d * width, most * width, min(16, -(-d // most)))
    shared.destroy()
    return out.reshape(d, width)


def _range_gram(cells: DataFrame, q: np.ndarray) -> np.ndarray:
    """qᵀ A Aᵀ q of the unfolding A."""
    from ..exec.passes import PACKED, packed, sum_packed

    ship_package(cells.sparkSession)
    shared, width = cells.sparkSession.sparkContext.broadcast(q), q.shape[1]

    def run(batches):
        got = _columns(batches, shared.value)
        if got is not None:
            yield from packed((got[3].T @ got[3]).ravel(), width * width)

    out = sum_packed(cells.mapInArrow(run, PACKED), width * width, width * width)
    shared.destroy()
    return out.reshape(width, width)


def fit_hosvd(t: TensorFrame, ranks: int | list[int] = 3, gram_side: int = GRAM_SIDE) -> Tucker:
    """Leading vectors of each unfolding, by its gram or, for modes over ``gram_side``, by a randomised range."""
    ranks = [ranks] * len(t.dims) if isinstance(ranks, int) else ranks
    u = [_leading(unfolding_gram(t, k), min(r, d)) if d <= gram_side else range_finder(t, k, min(r, d)) for k, (r, d) in enumerate(zip(ranks, t.dims, strict=True))]
    return Tucker(core_of(t, u), tuple(u))


def projected_gram(t: TensorFrame, u: list[np.ndarray], k: int) -> np.ndarray:
    """Rows of the mode-k unfolding projected on the other modes' factors: d_k × Π r."""
    width = int(np.prod([x.shape[1] for j, x in enumerate(u) if j != k]))

    def outer(us, index, y):
        v = y[:, None]
        for j, x in enumerate(us):
            if j != k:
                v = (v[:, :, None] * x[index[j]][:, None, :]).reshape(len(v), -1)
        return v

    return dense_sums(t, tuple(u), k, width, outer)


def fit_tucker(t: TensorFrame, ranks: int | list[int] = 3, sweeps: int = 5, seed: int = 0) -> Tucker:
    """Alternating truncated SVDs (HOOI)."""
    ranks = [ranks] * len(t.dims) if isinstance(ranks, int) else ranks
    rng = np.random.default_rng(seed)
    u = [np.linalg.qr(rng.standard_normal((d, min(r, d))))[0] for d, r in zip(t.dims, ranks, strict=True)]
    for _ in range(sweeps):
        for k in range(len(u)):
            x = projected_gram(t, u, k)
            left, _, _ = np.linalg.svd(x, full_matrices=False)
            u[k] = left[:, : u[k].shape[1]]
    return Tucker(core_of(t, u), tuple(u))


def mode_product(t: TensorFrame, matrix: DataFrame, k: int) -> DataFrame:
    """Cells of the product with a matrix (j, i, w) at mode k: a join on i_k and a sum per new cell."""
    m = t.modes[k]
    others = [x for x in t.modes if x != m]
    joined = t.df.join(matrix.withColumnRenamed("i", m), m)
    return joined.groupBy(*others, F.col("j").alias(m)).agg(F.sum(F.col("y") * F.col("w")).alias("y")).select(*t.modes, "y")


def mode_means(t: TensorFrame, smooth: float = 1.0) -> DataFrame:
    """(mode, idx, n, score): smoothed log-odds (binary) or shrunk means (real) of each index."""
    keys = F.explode(F.array(*(F.struct(F.lit(k + 1).alias("mode"), F.col(m).alias("idx")) for k, m in enumerate(t.modes)))).alias("e")
    g = t.df.select("y", keys).groupBy("e.mode", "e.idx").agg(F.count("*").alias("n"), F.sum("y").alias("s"))
    if t.kind == "binary":
        return g.select("mode", "idx", "n", F.log((F.col("s") + smooth) / (F.col("n") - F.col("s") + smooth)).alias("score"))
    return g.select("mode", "idx", "n", (F.col("s") / (F.col("n") + smooth)).alias("score"))
