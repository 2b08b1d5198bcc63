"""Sparse tensors as long DataFrames: one row per selected cell, i_1..i_K and y."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import cut_lineage, ship_package

AGGREGATES = {
    "sum": F.sum,
    "count": lambda v: F.count("*").cast("double"),
    "max": F.max,
    "avg": F.avg,
    "log1p_sum": lambda v: F.log1p(F.sum(v)),
    "log_sum": lambda v: F.log(F.sum(v)),
    "log1p_count": lambda v: F.log1p(F.count("*").cast("double")),
    "presence": lambda v: F.lit(1.0),
}


@dataclass(frozen=True)
class TensorFrame:
    """Cells, the sizes of the modes and the kind of values (``real`` or ``binary``)."""

    df: DataFrame
    dims: tuple[int, ...]
    kind: str = "real"
    packed: RDD | None = field(default=None, compare=False)  # the cells as arrays, where they are kept for many passes

    @property
    def modes(self) -> list[str]:
        return [f"i_{k + 1}" for k in range(len(self.dims))]

    def with_df(self, df: DataFrame) -> TensorFrame:
        return replace(self, df=df, packed=None)

    def select_cells(self, chosen: Column | DataFrame) -> TensorFrame:
        """An arbitrary subset: by a predicate or by a table of cells."""
        if isinstance(chosen, Column):
            return self.with_df(self.df.where(chosen))
        return self.with_df(self.df.join(chosen.select(*self.modes).distinct(), self.modes, "left_semi"))

    def distribute(self, parts: int) -> TensorFrame:
        """Cells dealt over ``parts`` tasks and kept for the passes that follow: as rows for joins, and as arrays for numpy, so that
        no pass turns rows into arrays again."""
        return self._keep(parts, [*self.modes, "y"])

    def distribute_marked(self, parts: int) -> TensorFrame:
        """``distribute`` of cells with ``marks``, of which ``marked`` takes some."""
        return self._keep(parts, [*self.modes, "y", "marks"])

    def _keep(self, parts: int, names: list[str]) -> TensorFrame:
        ship_package(self.df.sparkSession)
        df = self.df.select(*names).repartition(parts, *self.modes).persist(StorageLevel.MEMORY_AND_DISK)
        packed = df.mapInArrow(partial(pack, modes=len(self.dims)), ", ".join(f"{m} binary" for m in names)).rdd.persist(StorageLevel.MEMORY_AND_DISK)
        packed.count()
        return replace(self, df=df, packed=packed)

    def marked(self, bits: int) -> TensorFrame:
        """The cells of ``distribute_marked`` that have one of ``bits``, where they lie."""
        packed = self.packed.map(partial(with_marks, bits=bits)).filter(lambda row: len(row[-1])).persist(StorageLevel.MEMORY_AND_DISK)
        packed.count()
        df = self.df.where(F.col("marks").bitwiseAND(F.lit(bits)) != 0).select(*self.modes, "y")
        return replace(self, df=df, packed=packed)

    def release(self) -> None:
        """Drops what ``distribute`` keeps."""
        if self.packed is not None:
            self.packed.unpersist()
        self.df.unpersist()

    def density(self) -> float:
        total = 1.0
        for d in self.dims:
            total *= d
        return self.df.count() / total


PACK = 1 << 14  # cells of a packed row
SORT = 1 << 20  # cells that are put in order together


def pack(batches: Iterator[pa.RecordBatch], modes: int) -> Iterator[pa.RecordBatch]:
    """Rows (i_1.., y and what follows it) to rows of their arrays' bytes: indices as 32 bits where these do, y as 64, marks as 32. Cells
    are put in the order of the mode of largest indices, so that those of one index lie together."""
    held, n = [], 0

    def rows() -> Iterator[pa.RecordBatch]:
        columns = list(map(np.concatenate, zip(*held, strict=True)))
        index, y, more = columns[:modes], columns[modes], columns[modes + 1 :]
        kind = np.int32 if all(i.max() < 2**31 for i in index) else np.int64
        order = np.argsort(max(index, key=lambda i: i.max()), kind="stable")
        index, y = [i.astype(kind)[order] for i in index], y.astype(float)[order]
        more = [x.astype(np.int32)[order] for x in more]
        for lo in range(0, len(y), PACK):
            yield pa.RecordBatch.from_arrays([pa.array([x[lo : lo + PACK].tobytes()], pa.binary()) for x in (*index, y, *more)], names)

    for b in batches:
        if b.num_rows:
            names = b.schema.names
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            n += b.num_rows
            if n >= SORT:
                yield from rows()
                held, n = [], 0
    if held:
        yield from rows()


def unpack(row) -> tuple[np.ndarray, np.ndarray]:
    """(index n×K, y n) of a packed row."""
    y = np.frombuffer(row[-1], float)
    kind = np.int32 if len(row[0]) == 4 * len(y) else np.int64
    return np.stack([np.frombuffer(x, kind) for x in row[:-1]], 1).astype(np.int64), y


def with_marks(row, bits: int) -> tuple[bytes, ...]:
    """A packed row's cells that have one of ``bits`` in their marks."""
    keep = np.frombuffer(row[-1], np.int32) & bits != 0
    y = np.frombuffer(row[-2], float)
    kind = np.int32 if len(row[0]) == 4 * len(y) else np.int64
    return (*(np.frombuffer(x, kind)[keep].tobytes() for x in row[:-2]), y[keep].tobytes())


def merge_cells(df: DataFrame, modes: list[Column | str], value: Column, agg: str) -> DataFrame:
    """Raw rows to one row per cell; rows with a null index or value are unobserved."""
    keys = [(F.col(m) if isinstance(m, str) else m).alias(f"m_{k + 1}") for k, m in enumerate(modes)]
    names = [f"m_{k + 1}" for k in range(len(modes))]
    rows = df.select(*keys, value.cast("double").alias("v")).dropna()
    return rows.groupBy(*names).agg(AGGREGATES[agg](F.col("v")).alias("y"))


ONE_TASK_KEYS = 1_000_000  # up to so many keys of a mode are numbered in one task
BROADCAST_KEYS = 200_000  # up to so many go to the cells' tasks, so that no cell moves


def number_keys(keys: DataFrame, big: bool) -> DataFrame:
    """(raw, idx) of distinct ``raw``: dense ids in their order; ``big`` numbers range partitions side by side instead of in one window."""
    if not big:
        return keys.select("raw", (F.row_number().over(Window.orderBy("raw")) - 1).cast("long").alias("idx"))
    ranged = cut_lineage(keys.repartitionByRange("raw").withColumn("part", F.spark_partition_id()))
    counts = ranged.groupBy("part").agg(F.count("*").alias("n"))
    offsets = counts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("offset"))
    local = F.row_number().over(Window.partitionBy("part").orderBy("raw")) - 1
    return ranged.withColumn("at", local).join(F.broadcast(offsets), "part").select("raw", (F.col("offset") + F.col("at")).cast("long").alias("idx"))


def dictionary(cells: DataFrame, name: str, big: bool = False) -> DataFrame:
    """(raw, idx): dense ids in the order of the raw keys."""
    return number_keys(cells.select(F.col(name).alias("raw")).distinct(), big)


def dense_index(cells: DataFrame, n_modes: int, most: int = ONE_TASK_KEYS) -> tuple[DataFrame, list[DataFrame], tuple[int, ...]]:
    """Cells with dense i_k, the dictionaries and the mode sizes. Raw rows are merged once, keys are read from the merged cells and
    each mode's are numbered by the way its size asks for; short dictionaries are broadcast."""
    cells = cut_lineage(cells)
    dicts, dims, out = [], [], cells
    for k in range(1, n_modes + 1):
        keys = cells.select(F.col(f"m_{k}").alias("raw")).distinct()
        n = keys.count()
        d = cut_lineage(number_keys(keys, n > most))
        dicts.append(d)
        dims.append(n)
        named = d.select(F.col("raw").alias(f"m_{k}"), F.col("idx").alias(f"i_{k}"))
        out = out.join(F.broadcast(named) if n <= BROADCAST_KEYS else named, f"m_{k}")
    return out.select(*(f"i_{k + 1}" for k in range(n_modes)), "y"), dicts, tuple(dims)


def build_tensor(df: DataFrame, modes: list[Column | str], value: Column, agg: str = "sum", kind: str = "real", dims: tuple[int, ...] | None = None) -> TensorFrame:
    """A tensor from any table. Give ``dims`` where the modes are dense ids already."""
    cells = merge_cells(df, modes, value, agg)
    if dims is not None:
        return TensorFrame(cells.select(*(F.col(f"m_{k + 1}").cast("long").alias(f"i_{k + 1}") for k in range(len(modes))), "y"), dims, kind)
    out, _, sizes = dense_index(cells, len(modes))
    return TensorFrame(out, sizes, kind)
