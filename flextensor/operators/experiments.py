"""The experiment harnesses: accuracy over folds and test sets, iteration times, reductions, scaling and ablations (rows only)."""

from __future__ import annotations

import sys
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import metrics, sampling, workloads
from ..baselines import kron, multilinear
from ..bounds import gaussian
from ..exec import passes, planner
from ..fit import evaluate, fit
from ..model import init_model
from ..predict import predict
from ..session import cut_lineage, free_driver
from ..tensor import TensorFrame
from .relational import Query
from .tensor_queries import folded

TABLE: dict[str, tuple[Query, str | None]] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        TABLE[name] = (f, sql)
        return f

    return add


# methods by how they see missing cells: as zeros, or left out but for a balanced sample of zeros; sweeps and steps are their own
MISSING_AS_ZERO = {
    "cp": lambda t, r: multilinear.fit_cp(t, r),
    "nncp": lambda t, r: multilinear.fit_nncp(t, r),
    "hosvd": lambda t, r: multilinear.fit_hosvd(t, r),
    "tucker": lambda t, r: multilinear.fit_tucker(t, r),
    "krongp": lambda t, r: kron.fit_krongp(t, r),
    "sparse_cp": lambda t, r: multilinear.fit_sparse_cp(t, r),
    "blockkron": lambda t, r: kron.fit_blockkron(t, r, None, side(t)),
    "mixkron": lambda t, r: kron.fit_mixkron(t, r, block=side(t)),
}
BALANCED = {"cp2": lambda t, r: multilinear.fit_cp(t, r, observed_only=True)}
SMALL = ("flexgp", "cp2", "cp", "nncp", "hosvd", "tucker", "krongp", "mixkron")
LARGE = ("flexgp", "sparse_cp", "blockkron", "mixkron")


BLOCK_CELLS = 16  # of a sub-tensor, on the average at least: with fewer its factors would have nothing to go by


def side(t: TensorFrame) -> list[int]:
    """Sub-tensors of about 16 indices a mode or, in sparse tensors, as many as it takes for ``BLOCK_CELLS`` cells: their fits have only the
    indices with cells."""
    n, each = t.df.count(), 16.0
    while True:
        sides = [min(int(each), d) for d in t.dims]
        if sides == list(t.dims) or n * np.prod([b / d for b, d in zip(sides, t.dims, strict=True)]) >= BLOCK_CELLS:
            return sides
        each *= 1.05


AT_ONCE = 6  # fits whose jobs share the cluster
FITS_BYTES = 192 << 20  # of the driver, for the vectors of all fits at once
VECTORS = 12  # as long as all factors, that a fit holds
TASK_CELLS = 1_000_000  # about so many cells a task
FEW_CELLS = 100_000  # a task of fewer isn't worth its start
CELLS_AT_ONCE = 1_000_000  # folds of larger tensors are prepared one after another, and FEW_AT_ONCE fits fill the cluster
FEW_AT_ONCE = 2
INDICES_AT_ONCE = 100_000  # with longer factors the driver is freed after each fit


def at_once(t: TensorFrame, rank: int) -> int:
    """How many fits may hold their factors on the driver side by side."""
    return max(1, min(AT_ONCE, FITS_BYTES // (8 * VECTORS * rank * sum(t.dims))))


def side_by_side(f: Callable, jobs: list[tuple], most: int = AT_ONCE) -> list:
    """``f`` of each job: their many small Spark jobs fill the gaps of one another."""
    with ThreadPoolExecutor(most) as pool:
        return list(pool.map(lambda job: f(*job), jobs))


def score(t: TensorFrame, balanced: TensorFrame, test: DataFrame, method: str, rank: int = 3, p: int = 100, steps: int | None = None) -> DataFrame:
    """``test`` with ``score`` by a method fitted on the nonzeros ``t`` or on ``balanced``, which holds sampled zeros as well. FlexGP is
    fitted until its bound settles, or for ``steps``."""
    if method == "flexgp":
        out = predict(balanced, fit(balanced, ranks=rank, p=p, steps=sys.maxsize if steps is None else steps), test)
        return out.withColumnRenamed("mean", "score") if t.kind == "real" else out
    model = BALANCED[method](balanced, rank) if method in BALANCED else MISSING_AS_ZERO[method](t, rank)
    return multilinear.predict_cells(model, test, t.modes, "score")


def measure(t: TensorFrame, scored: DataFrame, by: list[str]) -> DataFrame:
    return (metrics.mse(scored, "y", "score", by) if t.kind == "real" else metrics.auc(scored, "y", "score", by)).toDF(*by, "value")


def folds_table(t: TensorFrame, methods: tuple[str, ...], folds: int = 5, **how) -> DataFrame:
    """(method, fold, value): MSE (real) or AUC (binary) on each fold's nonzeros and its share of zeros. The other folds train, with
    as many zeros as nonzeros for the methods on balanced cells; all test zeros stay out of training."""
    all_ = sampling.kfold(t, folds).persist()
    t, n = t.with_df(all_.select(*t.modes, "y")), all_.count()
    zeros = sampling.fold_zeros(t, folds).persist()
    parts = max(4, -(-n // TASK_CELLS), min(t.df.sparkSession.sparkContext.defaultParallelism, n // FEW_CELLS))
    marked = sampling.balanced_folds(t.with_df(all_), folds, zeros)
    whole = None if marked is None else t.with_df(marked).distribute_marked(parts)

    def prepare(i: int):
        test = all_.where(F.col("fold") == i).select(*t.modes, "y").unionByName(zeros.where(F.col("fold") == i).select(*t.modes, "y")).persist()
        if whole is not None:
            return i, whole.marked(1 << i), whole.marked(1 << i | 1 << folds + i), test
        train = t.with_df(all_.where(F.col("fold") != i).select(*t.modes, "y")).distribute(parts)
        held = zeros.select(*t.modes).unionByName(test.select(*t.modes))
        return i, train, sampling.balanced_sample(train, exclude=held).distribute(parts), test

    def run(m: str, i: int, train: TensorFrame, balanced: TensorFrame, test: DataFrame):
        v = measure(t, score(train, balanced, test, m, **how), []).first()[0]
        free_driver(t.df.sparkSession)
        return m, i, None if v is None else float(v)

    most, rows = min(at_once(t, how.get("rank", 3)), AT_ONCE if n <= CELLS_AT_ONCE else FEW_AT_ONCE), []
    for some in [range(folds)] if n <= CELLS_AT_ONCE else [[i] for i in range(folds)]:
        ready = side_by_side(prepare, [(i,) for i in some], most)
        rows += side_by_side(run, [(m, *r) for m in methods for r in ready], most)
        for _, train, balanced, test in ready:
            for x in (train, balanced):
                x.release()
            test.unpersist()
    if whole is not None:
        whole.release()
    all_.unpersist()
    zeros.unpersist()
    return t.df.sparkSession.createDataFrame(rows, "method string, fold int, value double")


def _w12(name: str):
    def run(spark, d):
        """Mean, SD and standard error over five folds of each method, and the paired t-test of FlexGP against it."""
        table = folds_table(workloads.TENSORS[name](spark, d), SMALL)
        stats = metrics.fold_stats(table, "value", ["method"])
        tests = [metrics.paired_t(table, "flexgp", m).select(F.col("against").alias("method"), "t", "p") for m in SMALL[1:]]
        for x in tests[1:]:
            tests[0] = tests[0].unionByName(x)
        return stats.join(tests[0], "method", "left")

    TABLE[f"q_w12_folds_{name}"] = (run, None)


for _name in ("w1", "w2a", "w3", "w4"):
    _w12(_name)


def test_sets(t: TensorFrame, reps: int, n_zero: int = 1800) -> tuple[TensorFrame, TensorFrame, DataFrame]:
    """(nonzeros to train, these with balanced zeros, test sets): no test cell trains."""
    train, tests = sampling.train_and_tests(t, reps=reps, n_zero=n_zero)
    tests, parts = tests.persist(), max(8, -(-train.df.count() // TASK_CELLS))
    train = train.distribute(parts)
    return train, sampling.balanced_sample(train, exclude=tests.select(*t.modes).distinct()).distribute(parts), tests


def sets_table(t: TensorFrame, methods: tuple[str, ...], rank: int, reps: int = 50, n_zero: int = 1800, **how) -> DataFrame:
    """(method, mean, sd, se, sets): measures over test sets of 200 held-out nonzeros and ``n_zero`` zeros."""
    t = t.with_df(t.df.persist())
    train, balanced, tests = test_sets(t, reps, n_zero)
    t.df.unpersist()

    def run(m: str) -> DataFrame:
        v = measure(t, score(train, balanced, tests.select("rep", *t.modes, "y"), m, rank, **how), ["rep"])
        out = cut_lineage(metrics.fold_stats(v.withColumn("method", F.lit(m)), "value", ["method"]).withColumnRenamed("folds", "sets"))
        if sum(t.dims) > INDICES_AT_ONCE:
            free_driver(t.df.sparkSession)
        return out

    parts = side_by_side(run, [(m,) for m in methods], at_once(t, rank))
    for x in (train, balanced):
        x.release()
    tests.unpersist()
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _w11(name: str, rank: int, n_zero: int):
    def run(spark, d):
        t = workloads.w6(spark, d, None) if name == "w6" else workloads.TENSORS[name](spark, d)
        return sets_table(t, LARGE, rank, n_zero=n_zero)

    TABLE[f"q_w11_sets_{name}"] = (run, None)


for _name, _rank, _zero in (("w5", 3, 1800), ("w6", 3, 1800), ("w7", 5, 2000)):
    _w11(_name, _rank, _zero)


@query("q_w14_balanced")
def _(spark, d):
    """CP with all missing cells as zeros against CP on balanced cells: AUC over 50 test sets."""
    return sets_table(workloads.w6(spark, d, None), ("cp", "cp2"), 3)


@query("q_w14_optimisers")
def _(spark, d):
    """Bounds after the same number of steps of gradient ascent and L-BFGS."""
    t = workloads.planted(folded(spark, d)).distribute(4)
    rows = [(o, float(fit(t, p=15, steps=10, optimiser=o).trace[-1][2])) for o in ("gd", "lbfgs")]
    return spark.createDataFrame(rows, "optimiser string, bound double")


def seconds(f) -> float:
    began = time.time()
    f()
    return time.time() - began


@query("q_w10_reductions")
def _(spark, d):
    """Seconds of one factor gradient by each reduction, on the folded 100 × 100 × 100 tensor."""
    t = workloads.w10(spark, d).distribute(8)
    m = init_model(t, 3, 20)
    a = gaussian.adjoints(m, passes.suff_stats(t, m))[0]
    rows = [
        ("keyfree", seconds(lambda: passes.gradient_pass(t, m, a))),
        ("keyed", seconds(lambda: passes.keyed_gradient(t, m, a).count())),
        ("keyed_combined", seconds(lambda: passes.keyed_gradient(t, m, a, True).count())),
    ]
    return spark.createDataFrame(rows, "reduction string, seconds double")


@query("q_w9_scaling")
def _(spark, d):
    """Seconds of one evaluation by number of tasks the cells are dealt over, against the cost model's operations per task."""
    t = workloads.w5(spark, d)
    t = t.with_df(cut_lineage(t.df))
    m, n, took = init_model(t, 3, 100, "ard"), t.df.count(), {}
    for tasks in (8, 4, 2, 1):
        part = t.distribute(tasks)
        if not took:
            evaluate(part, m)  # starts every worker, so that no time has that in it
        took[tasks] = seconds(lambda part=part: evaluate(part, m))
        part.release()
    rows = [(k, took[k], took[1] / took[k], planner.cost_model(n, list(t.dims), [3, 3, 3], 100, k).flops_per_task) for k in sorted(took)]
    return spark.createDataFrame(rows, "tasks int, seconds double, speed double, flops_per_task double")


@query("q_w13_iterations")
def _(spark, d):
    """Seconds of one iteration of each large-scale method on the bibliography tensor of all words."""
    t = sampling.balanced_sample(workloads.w6(spark, d, None)).distribute(8)
    m = init_model(t, 3, 100, "ard")
    ones = t.with_df(t.df.where("y > 0"))
    rows = [
        ("flexgp", seconds(lambda: evaluate(t, m, lam_iter=10))),
        ("sparse_cp", seconds(lambda: multilinear.sparse_cp_tables(ones, 3, 1))),
        ("blockkron", seconds(lambda: kron.fit_blockkron(ones, 3, None, side(ones), 1, 4))),
    ]
    return spark.createDataFrame(rows, "method string, seconds double")


@query("q_plan_exchanges")
def _(spark, d):
    """Rows that cross an exchange per gradient: one vector a task against one row per cell and mode."""
    t = folded(spark, d).distribute(4)
    m = init_model(t, 2, 6)
    a = gaussian.adjoints(m, passes.suff_stats(t, m))[0]
    n = t.df.count()
    keyed = passes._keyed_rows(t, m, a, False).count()
    return spark.createDataFrame([("keyfree", t.df.rdd.getNumPartitions()), ("keyed", keyed), ("cells", n)], "reduction string, rows bigint")


@query("q_udaf_auc", "SELECT fold, round(auc, 8) AS auc FROM (WITH sc AS (SELECT event_id % 5 AS fold, floor(value) AS score, CASE WHEN event_type = 'click' THEN 1 ELSE 0 END AS yb FROM events), r AS (SELECT fold, yb, rank() OVER (PARTITION BY fold ORDER BY score) + (count(*) OVER (PARTITION BY fold, score) - 1) / 2 AS r FROM sc) SELECT fold, (sum(r) FILTER (WHERE yb = 1) - count(*) FILTER (WHERE yb = 1) * (count(*) FILTER (WHERE yb = 1) + 1) / 2) / (count(*) FILTER (WHERE yb = 1) * count(*) FILTER (WHERE yb = 0)) AS auc FROM r GROUP BY fold)")
def _(spark, d):
    """A grouped-aggregate UDF: one group must fit a task; ``metrics.auc`` is the form without that limit."""

    @F.pandas_udf("double")
    def auc_udaf(s: pd.Series, y: pd.Series) -> float:
        r, n = s.rank(), int(y.sum())
        return float((r[y > 0].sum() - n * (n + 1) / 2) / (n * (len(y) - n))) if 0 < n < len(y) else float("nan")

    e = spark.read.parquet(f"{d}/events.parquet").select((F.col("event_id") % 5).alias("fold"), F.floor("value").cast("double").alias("s"), (F.col("event_type") == "click").cast("double").alias("y"))
    return e.groupBy("fold").agg(auc_udaf("s", "y").alias("auc")).select("fold", F.round("auc", 8).alias("auc"))


@query("q_calibration")
def _(spark, d):
    t = workloads.planted(folded(spark, d), True).distribute(4)
    m = fit(t, p=10, steps=3)
    return metrics.calibration(predict(t, m, t.df.select(*t.modes, "y")))


@query("q_log_predictive")
def _(spark, d):
    t = workloads.planted(folded(spark, d), True).distribute(4)
    m = fit(t, p=10, steps=3)
    return metrics.log_predictive(predict(t, m, t.df.select(*t.modes, "y")))


