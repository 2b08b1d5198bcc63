"""Queries over the engine itself: builds, splits, kernels, statistics, bounds, gradients, predictions, measures and fits.

Those with SQL twins run on a small folded tensor of the events table with rank-1 factors that are sines of the index and
two inducing points, where determinants and inverses are closed forms.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import metrics, sampling, workloads
from ..baselines import kron, linear, multilinear
from ..bounds import em, exact, gaussian, probit
from ..exec import passes, planner
from ..fit import fit, fit_planned, trace_frame
from ..functions.kernels import NAMES, Kernel, kernel_expr
from ..model import ModelState, init_model
from ..predict import predict
from ..sampling import portable_hash_sql
from ..tensor import TensorFrame, build_tensor, dictionary, merge_cells
from .relational import K_SQL, Query, phi_sql

TABLE: dict[str, tuple[Query, str | None]] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        TABLE[name] = (f, sql)
        return f

    return add


# -- the folded tensor ------------------------------------------------------------------------------------------------
DIMS = (7, 6, 5)
BETA = 2.0
POINTS = ((0.0, 0.0, 0.0), (0.5, -0.5, 0.5))
CELLS_SQL = f"""cells AS (SELECT user_id % 7 AS i_1, CAST(hour(ts) AS BIGINT) % 6 AS i_2, {K_SQL} % 5 AS i_3, round(avg(value) / 100, 6) AS y FROM events GROUP BY ALL),
x AS (SELECT *, sin(0.7 * i_1 + 1) AS x1, sin(0.7 * i_2 + 2) AS x2, sin(0.7 * i_3 + 3) AS x3, CASE WHEN y > 0.5 THEN 1.0 ELSE -1.0 END AS t FROM cells),
k AS (SELECT *, exp(-0.5 * (x1*x1 + x2*x2 + x3*x3)) AS k1, exp(-0.5 * (pow(x1 - 0.5, 2) + pow(x2 + 0.5, 2) + pow(x3 - 0.5, 2))) AS k2 FROM x)"""
STATS_SQL = CELLS_SQL + """,
s AS (SELECT sum(k1*k1) AS g11, sum(k1*k2) AS g12, sum(k2*k2) AS g22, sum(k1*y) AS h1, sum(k2*y) AS h2, sum(y*y) AS s, count(*)::DOUBLE AS c, count(*) AS n,
  1 + 1e-6 AS a, exp(-0.375) AS b, sum(x1*x1 + x2*x2 + x3*x3) AS unused FROM k),
pr AS (SELECT -0.5 * ((SELECT sum(pow(sin(0.7 * i + 1), 2)) FROM range(7) t(i)) + (SELECT sum(pow(sin(0.7 * i + 2), 2)) FROM range(6) t(i)) + (SELECT sum(pow(sin(0.7 * i + 3), 2)) FROM range(5) t(i))) AS prior)"""


def _inverse_sql(prefix: str, a: str, b: str, d: str) -> str:
    det = f"(({a}) * ({d}) - ({b}) * ({b}))"
    return f"{det} AS {prefix}det, ({d}) / {det} AS {prefix}11, -({b}) / {det} AS {prefix}12, ({a}) / {det} AS {prefix}22"


def _m_sql(beta: float) -> str:
    return STATS_SQL + f",\nm AS (SELECT s.*, prior, {_inverse_sql('q', 'a', 'b', 'a')}, {_inverse_sql('m', f'a + {beta} * g11', f'b + {beta} * g12', f'a + {beta} * g22')} FROM s, pr)"


def folded(spark: SparkSession, d: str, binary: bool = False) -> TensorFrame:
    e = spark.read.parquet(f"{d}/events.parquet").select("user_id", "ts", "props", "value")
    t = build_tensor(e, [F.col("user_id") % 7, F.hour("ts") % 6, workloads.K() % 5], F.col("value"), "avg", dims=DIMS)
    y = F.round(F.col("y") / 100, 6)
    return TensorFrame(t.df.withColumn("y", (y > 0.5).cast("double") if binary else y), DIMS, "binary" if binary else "real")


def sine_model(kind: str = "real") -> ModelState:
    u = tuple(np.sin(0.7 * np.arange(n) + k + 1)[:, None] for k, n in enumerate(DIMS))
    return ModelState(u, np.array(POINTS), Kernel("rbf", [1.0]), BETA if kind == "real" else 1.0, np.zeros(2), kind)


def one_row(spark: SparkSession, **values) -> DataFrame:
    return spark.createDataFrame([tuple(v if isinstance(v, int) else float(v) for v in values.values())], ", ".join(f"{k} {'bigint' if isinstance(v, int) else 'double'}" for k, v in values.items()))


def r(x, n: int = 5) -> float:
    return round(float(x), n) + 0.0


# -- building ---------------------------------------------------------------------------------------------------------
SALES = "lineitem JOIN orders ON l_orderkey = o_orderkey"
BUILD_SQL = {
    "w1": f"SELECT user_id AS m_1, event_type AS m_2, 100 * hour(ts) + {K_SQL} AS m_3, ln(1 + sum(value)) AS y FROM events GROUP BY ALL",
    "w2a": f"SELECT user_id, hour(ts) AS h, {K_SQL} AS k, ln(1 + sum(value)) AS y FROM events WHERE event_type = 'click' GROUP BY ALL",
    "w2b": f"SELECT o_custkey, l_suppkey, p_brand, ln(sum(l_extendedprice)) AS y FROM {SALES} JOIN part ON l_partkey = p_partkey GROUP BY ALL",
    "w3": f"SELECT o_custkey, l_suppkey, year(o_orderdate) * 12 + month(o_orderdate) AS mo, 1.0 AS y FROM {SALES} GROUP BY ALL",
    "w4": "SELECT l_partkey, l_returnflag || l_linestatus AS f, l_suppkey, 1.0 AS y FROM lineitem GROUP BY ALL",
    "w5": f"SELECT o_custkey, l_suppkey, l_partkey, ln(sum(l_extendedprice)) AS y FROM {SALES} GROUP BY ALL",
    "w7": "SELECT l_partkey, l_suppkey, l_returnflag || '-' || l_linestatus || '-' || strftime(l_shipdate, '%Y-%m') AS f, 1.0 AS y FROM lineitem GROUP BY ALL",
    "w8": f"SELECT user_id, {K_SQL} AS k, hour(ts) AS h, minute(ts) AS mi, max(CASE WHEN event_type = 'click' THEN 1.0 ELSE 0.0 END) AS y FROM events GROUP BY ALL",
    "w10": f"SELECT o_custkey % 100 AS a, l_suppkey % 100 AS b, l_partkey % 100 AS c, avg(ln(l_extendedprice)) AS y FROM {SALES} GROUP BY ALL",
}


def _ranked(sql: str, n: int) -> str:
    """Dense ids of the keys and values, as the build gives them, summed to a fingerprint per first mode."""
    cols = f"SELECT * FROM ({sql}) AS raw({', '.join(f'm{k}' for k in range(n))}, y)"
    ids = ", ".join(f"dense_rank() OVER (ORDER BY m{k}) - 1 AS i{k}" for k in range(n))
    weight = " + ".join(f"{k + 2} * i{k}" for k in range(n))
    return f"SELECT i0 AS i_1, count(*) AS n, CAST(sum({weight}) AS BIGINT) AS ids, round(sum(y), 4) AS y FROM (SELECT {ids}, y FROM ({cols})) GROUP BY i0"


def _fingerprint(t: TensorFrame) -> DataFrame:
    weight = sum((k + 2) * F.col(m) for k, m in enumerate(t.modes))
    return t.df.groupBy("i_1").agg(F.count("*").alias("n"), F.sum(weight).alias("ids"), F.round(F.sum("y"), 4).alias("y"))


for _name, _sql in BUILD_SQL.items():
    _n = 4 if _name == "w8" else 3
    if _name == "w10":
        _twin = f"SELECT a AS i_1, count(*) AS n, CAST(sum(2 * a + 3 * b + 4 * c) AS BIGINT) AS ids, round(sum(y), 4) AS y FROM ({_sql}) GROUP BY a"
    else:
        _twin = _ranked(_sql, _n)
    TABLE[f"q_build_{_name}"] = ((lambda w: lambda spark, d: _fingerprint(workloads.TENSORS[w](spark, d)))(_name), _twin)


_W6_SQL = "SELECT DISTINCT source, lang, word, 1.0 AS y FROM (SELECT source, lang, unnest(list_filter(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'), lambda x: regexp_full_match(x, '\\p{L}{4,}'))) AS word FROM documents) WHERE source IS NOT NULL AND lang IS NOT NULL"


@query("q_build_w6", _ranked(_W6_SQL, 3))
def _(spark, d):
    """All words: bounds on their frequency would not grow with the table."""
    return _fingerprint(workloads.w6(spark, d, None))


@query("q_density", f"SELECT count(*) AS nnz, round(count(*)::DOUBLE / (count(DISTINCT user_id) * count(DISTINCT h) * count(DISTINCT k)), 9) AS density FROM ({BUILD_SQL['w2a']})")
def _(spark, d):
    t = workloads.w2a(spark, d)
    size = float(np.prod(t.dims))
    return t.df.agg(F.count("*").alias("nnz"), F.round(F.count("*") / size, 9).alias("density"))


@query("q_dense_index", "SELECT l_partkey AS raw, row_number() OVER (ORDER BY l_partkey) - 1 AS idx FROM (SELECT DISTINCT l_partkey FROM lineitem)")
def _(spark, d):
    cells = merge_cells(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_partkey", "l_suppkey"], F.lit(1.0), "presence")
    return dictionary(cells, "m_1", big=True)


@query("q_select_cells", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, y FROM cells WHERE y > 0.4 AND i_1 < 3")
def _(spark, d):
    t = folded(spark, d).select_cells(F.col("y") > 0.4)
    return t.select_cells(t.df.where("i_1 < 3")).df


# -- splits -----------------------------------------------------------------------------------------------------------
@query("q_kfold", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, CAST(({portable_hash_sql('i_1', 'i_2', 'i_3', seed=1)} // 256) % 5 AS INTEGER) AS fold FROM cells")
def _(spark, d):
    return sampling.kfold(folded(spark, d)).select("i_1", "i_2", "i_3", "fold")


_NZ = f"nz AS (SELECT DISTINCT user_id % 50 AS i_1, CAST(hour(ts) AS BIGINT) AS i_2, {K_SQL} AS i_3 FROM events WHERE event_type = 'click')"


def clicks(spark: SparkSession, d: str) -> TensorFrame:
    e = spark.read.parquet(f"{d}/events.parquet").where("event_type = 'click'")
    return build_tensor(e, [F.col("user_id") % 50, F.hour("ts"), workloads.K()], F.lit(1.0), "presence", "binary", dims=(50, 24, 100))


def _candidate_sql(attempts: int, dims=(50, 24, 100), seed: int = 3) -> str:
    idx = ", ".join(f"({portable_hash_sql('i_1', 'i_2', 'i_3', 'a', str(k + 1), seed=seed)} // 256) % {n} AS c{k + 1}" for k, n in enumerate(dims))
    return f"cand AS (SELECT DISTINCT c1 AS i_1, c2 AS i_2, c3 AS i_3 FROM (SELECT {idx} FROM nz, range({attempts}) r(a)))"


@query("q_balanced", f"WITH {_NZ}, {_candidate_sql(4)}, free AS (SELECT * FROM cand ANTI JOIN nz USING (i_1, i_2, i_3)), pick AS (SELECT i_1, i_2, i_3 FROM free ORDER BY {portable_hash_sql('i_1', 'i_2', 'i_3', seed=4)}, i_1, i_2, i_3 LIMIT (SELECT count(*) FROM nz)) SELECT i_1, i_2, i_3, 1.0::DOUBLE AS y, 'obs' AS origin FROM nz UNION ALL SELECT i_1, i_2, i_3, 0.0, 'zero' FROM pick")
def _(spark, d):
    return sampling.balanced_sample(clicks(spark, d), attempts=4).df


@query("q_enumerated_zeros", f"WITH {_NZ} SELECT a AS i_1, b AS i_2, c AS i_3 FROM range(50) x(a), range(24) y(b), range(100) z(c) ANTI JOIN nz ON i_1 = a AND i_2 = b AND i_3 = c")
def _(spark, d):
    return sampling.enumerated_zeros(clicks(spark, d)).drop("y")


_HELD = f"{portable_hash_sql('i_1', 'i_2', 'i_3', seed=5)} >= {int(sampling.MODULUS * 0.8)}"
_ONES = f"SELECT rep, i_1, i_2, i_3, 1.0 AS y FROM (SELECT *, row_number() OVER (PARTITION BY rep ORDER BY {portable_hash_sql('rep', 'i_1', 'i_2', 'i_3', seed=6)}, i_1, i_2, i_3) AS rank FROM nz, range(50) t(rep) WHERE {_HELD}) WHERE rank <= 200"
_DRAW = ", ".join(f"({portable_hash_sql('rep', 'a', str(k + 1), seed=7)} // 256) % {n} AS i_{k + 1}" for k, n in enumerate((50, 24, 100)))
_ZEROS = f"SELECT rep, i_1, i_2, i_3, 0.0 AS y FROM (SELECT *, row_number() OVER (PARTITION BY rep ORDER BY {portable_hash_sql('rep', 'i_1', 'i_2', 'i_3', seed=8)}, i_1, i_2, i_3) AS rank FROM (SELECT DISTINCT rep, {_DRAW} FROM range(50) t(rep), range(4000) d(a)) ANTI JOIN nz USING (i_1, i_2, i_3)) WHERE rank <= 1800"


@query("q_tests50", f"WITH {_NZ}, tests AS ({_ONES} UNION ALL {_ZEROS}) SELECT CAST(rep AS INTEGER) AS rep, count(*) FILTER (WHERE y = 1) AS n_one, count(*) FILTER (WHERE y = 0) AS n_zero, CAST(sum(2 * i_1 + 3 * i_2 + 4 * i_3) AS BIGINT) AS ids FROM tests GROUP BY rep")
def _(spark, d):
    """50 test sets of 200 held-out nonzeros (fewer where fewer are held out) and 1,800 empty cells, by size and fingerprint."""
    t = clicks(spark, d)
    _, tests = sampling.train_and_tests(t, attempts=4000)
    return tests.groupBy("rep").agg(F.count_if(F.col("y") == 1).alias("n_one"), F.count_if(F.col("y") == 0).alias("n_zero"), F.sum(2 * F.col("i_1") + 3 * F.col("i_2") + 4 * F.col("i_3")).alias("ids"))


@query("q_fold_zeros", f"WITH {_NZ}, z AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY fold ORDER BY {portable_hash_sql('fold', 'i_1', 'i_2', 'i_3', seed=8)}, i_1, i_2, i_3) AS rank FROM (SELECT DISTINCT fold, " + _DRAW.replace("rep", "fold") + " FROM range(5) t(fold), range(2000) d(a)) ANTI JOIN nz USING (i_1, i_2, i_3)) WHERE rank <= greatest(1, least(floor((120000 - (SELECT count(*) FROM nz)) * 0.001::DOUBLE + 1e-9), floor((SELECT count(*) FROM nz) / 5.0::DOUBLE + 1e-9)))) SELECT CAST(fold AS INTEGER) AS fold, i_1, i_2, i_3 FROM z")
def _(spark, d):
    """The zeros that each fold tests besides its nonzeros: 0.1 % of all, no more than it has nonzeros."""
    return sampling.fold_zeros(clicks(spark, d), attempts=2000).drop("y")


@query("q_day_split", "SELECT pair, split, count(*) AS n, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) AS BIGINT) AS clicks FROM (SELECT CAST(p AS INTEGER) AS pair, 'train' AS split, event_type FROM events, range(3) t(p) WHERE CAST(ts AS DATE) = DATE '2024-01-01' + CAST(p AS INTEGER) UNION ALL SELECT CAST(p AS INTEGER), 'test', event_type FROM events, range(3) t(p) WHERE CAST(ts AS DATE) = DATE '2024-01-02' + CAST(p AS INTEGER)) GROUP BY ALL")
def _(spark, d):
    e = spark.read.parquet(f"{d}/events.parquet").select("ts", "event_type")
    s = sampling.day_pairs(e, [f"2024-01-0{i}" for i in range(1, 5)])
    return s.groupBy("pair", "split").agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "click").alias("clicks"))


# -- inputs and kernels -----------------------------------------------------------------------------------------------
def inputs_df(t: TensorFrame) -> DataFrame:
    x = F.array(*(F.sin(0.7 * F.col(m) + k + 1) for k, m in enumerate(t.modes)))
    return t.df.select(*t.modes, "y", x.alias("x"))


@query("q_inputs", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, round(x1, 9) AS x1, round(x2, 9) AS x2, round(x3, 9) AS x3 FROM x")
def _(spark, d):
    """The K-join form: one factor table per mode, joined on its index."""
    t = folded(spark, d)
    out = t.df.select(*t.modes)
    for k, n in enumerate(DIMS):
        u = spark.range(n).select(F.col("id").alias(f"i_{k + 1}"), F.round(F.sin(0.7 * F.col("id") + k + 1), 9).alias(f"x{k + 1}"))
        out = out.join(u, f"i_{k + 1}")
    return out.select(*t.modes, "x1", "x2", "x3")


_Q = "(pow((x1 - 0.5) / 0.8, 2) + pow((x2 + 0.5) / 1.2, 2) + pow((x3 - 0.5) / 1.0, 2))"
_KSQL = {
    "linear": "1.5 * (x1 * 0.5 / 0.64 + x2 * -0.5 / 1.44 + x3 * 0.5)",
    "rbf": f"1.5 * exp(-0.5 * {_Q})",
    "ard": f"1.5 * exp(-0.5 * {_Q})",
    "matern12": f"1.5 * exp(-sqrt({_Q}))",
    "matern32": f"1.5 * (1 + sqrt(3 * {_Q})) * exp(-sqrt(3 * {_Q}))",
    "matern52": f"1.5 * (1 + sqrt(5 * {_Q}) + 5 * {_Q} / 3) * exp(-sqrt(5 * {_Q}))",
}
for _name in NAMES:

    def _kernel(spark, d, name=_name):
        z, s = F.array(*map(F.lit, POINTS[1])), F.array(*map(F.lit, (0.8, 1.2, 1.0)))
        return inputs_df(folded(spark, d)).select("i_1", "i_2", "i_3", F.round(kernel_expr(name, F.col("x"), z, s, 1.5), 9).alias("k"))

    TABLE[f"q_kernel_{_name}"] = ((lambda f: lambda spark, d: f(spark, d))(_kernel), f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, round({_KSQL[_name]}, 9) AS k FROM x")


@query("q_udf_map", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, round(k1, 9) AS k1, round(k2, 9) AS k2 FROM k")
def _(spark, d):
    import pyarrow as pa

    from ..session import ship_package

    ship_package(spark)
    m = sine_model()

    def run(batches):
        for b in batches:
            index = np.stack([b.column(j).to_numpy(zero_copy_only=False) for j in range(3)], 1)
            k = m.kernel.gram(m.inputs(index), m.inducing)
            yield pa.RecordBatch.from_arrays([*(b.column(j) for j in range(3)), pa.array(k[:, 0]), pa.array(k[:, 1])], ["i_1", "i_2", "i_3", "k1", "k2"])

    t = folded(spark, d)
    return t.df.select(*t.modes).mapInArrow(run, "i_1 long, i_2 long, i_3 long, k1 double, k2 double").select(*t.modes, F.round("k1", 9).alias("k1"), F.round("k2", 9).alias("k2"))


# -- statistics, bounds, gradients, prediction ------------------------------------------------------------------------
@query("q_suff_stats", f"WITH {STATS_SQL} SELECT round(g11, 5) AS g11, round(g12, 5) AS g12, round(g22, 5) AS g22, round(h1, 5) AS h1, round(h2, 5) AS h2, round(s, 5) AS s, round(c, 5) AS c, n FROM s")
def q_suff_stats(spark, d):
    s = passes.suff_stats(folded(spark, d), sine_model())
    return one_row(spark, g11=r(s.g[0, 0]), g12=r(s.g[0, 1]), g22=r(s.g[1, 1]), h1=r(s.h[0]), h2=r(s.h[1]), s=r(s.s), c=r(s.c), n=s.n)


@query("q_gaussian_bound_p2", f"WITH {_m_sql(BETA)} SELECT round(0.5 * (ln(qdet) - ln(mdet)) - 0.5 * {BETA} * (s + c) + 0.5 * {BETA} * (q11*g11 + 2*q12*g12 + q22*g22) + 0.5 * {BETA * BETA} * (m11*h1*h1 + 2*m12*h1*h2 + m22*h2*h2) + 0.5 * n * ln({BETA} / (2 * pi())) + prior, 5) AS bound FROM m")
def _(spark, d):
    m = sine_model()
    return one_row(spark, bound=r(gaussian.value(m, passes.suff_stats(folded(spark, d), m))))


def _lambda_sql(steps: int) -> str:
    """λ after ``steps`` updates from 0, and the bound there."""
    out = _m_sql(1.0) + ",\nl0 AS (SELECT 0.0::DOUBLE AS l1, 0.0::DOUBLE AS l2)"
    for i in range(steps):
        u = "(k1 * l1 + k2 * l2)"
        rho = f"exp(-0.5 * {u} * {u}) / sqrt(2 * pi()) / {phi_sql(f't * {u}')}"
        out += f",\na{i} AS (SELECT sum(k1 * t * {rho}) AS p1, sum(k2 * t * {rho}) AS p2, any_value(l1) AS l1, any_value(l2) AS l2 FROM k, l{i})"
        e1, e2 = "(g11*l1 + g12*l2 + p1)", "(g12*l1 + g22*l2 + p2)"
        out += f",\nl{i + 1} AS (SELECT m11*{e1} + m12*{e2} AS l1, m12*{e1} + m22*{e2} AS l2 FROM m, a{i})"
    return out + f",\nf AS (SELECT sum(ln({phi_sql('t * (k1 * l1 + k2 * l2)')})) AS lp, any_value(l1) AS l1, any_value(l2) AS l2 FROM k, l{steps})"


_PB = "round(0.5 * (ln(qdet) - ln(mdet)) - 0.5 * c + 0.5 * (q11*g11 + 2*q12*g12 + q22*g22) + lp - 0.5 * (a*l1*l1 + 2*b*l1*l2 + a*l2*l2) + prior, 5) AS bound"


@query("q_probit_bound_p2", f"WITH {_lambda_sql(0)} SELECT {_PB} FROM m, f")
def _(spark, d):
    m, t = sine_model("binary"), folded(spark, d, True)
    s = passes.suff_stats(t, m)
    return one_row(spark, bound=r(probit.value(m, s, np.zeros(2), passes.lambda_pass(t, m, np.zeros(2))[1])))


@query("q_lambda_steps_p2", f"WITH {_lambda_sql(3)} SELECT round(l1, 5) AS l1, round(l2, 5) AS l2, {_PB} FROM m, f")
def _(spark, d):
    m, t = sine_model("binary"), folded(spark, d, True)
    lam, _, trace = probit.fixed_point(t, m, passes.suff_stats(t, m), np.zeros(2), 0.0, 3)
    return one_row(spark, l1=r(lam[0]), l2=r(lam[1]), bound=r(trace[-1]))


_W1, _W2 = "(m11*h1 + m12*h2)", "(m12*h1 + m22*h2)"
_GRAD_SQL = f"""WITH {_m_sql(BETA)},
ad AS (SELECT *, 0.5*{BETA}*(q11 - m11) - 0.5*{BETA**3}*{_W1}*{_W1} AS d11, 0.5*{BETA}*(q12 - m12) - 0.5*{BETA**3}*{_W1}*{_W2} AS d12, 0.5*{BETA}*(q22 - m22) - 0.5*{BETA**3}*{_W2}*{_W2} AS d22, {BETA**2}*{_W1} AS e1, {BETA**2}*{_W2} AS e2 FROM m),
g AS (SELECT i_1, i_2, i_3, x1, x2, x3, k1 * (2*(d11*k1 + d12*k2) + y*e1) AS w1, k2 * (2*(d12*k1 + d22*k2) + y*e2) AS w2 FROM k, ad),
r AS (SELECT 1 AS mode, i_1 AS idx, -x1*w1 + (0.5 - x1)*w2 AS g FROM g UNION ALL SELECT 2, i_2, -x2*w1 + (-0.5 - x2)*w2 FROM g UNION ALL SELECT 3, i_3, -x3*w1 + (0.5 - x3)*w2 FROM g)
SELECT CAST(mode AS INTEGER) AS mode, idx, round(sum(g), 5) AS grad FROM r GROUP BY mode, idx"""


def _adjoints(spark, d):
    m, t = sine_model(), folded(spark, d)
    return t, m, gaussian.adjoints(m, passes.suff_stats(t, m))[0]


@query("q_grad_u_p2", _GRAD_SQL)
def _(spark, d):
    """Key-free: whole vectors summed."""
    t, m, a = _adjoints(spark, d)
    g = passes.gradient_pass(t, m, a)
    at, rows = 0, []
    for k, n in enumerate(DIMS):
        rows += [(k + 1, i, r(g[at + i])) for i in range(n)]
        at += n
    return spark.createDataFrame(rows, "mode int, idx long, grad double")


for _name, _combine in (("keyed", False), ("keyed_combined", True)):

    def _keyed(spark, d, combine=_combine):
        t, m, a = _adjoints(spark, d)
        return passes.keyed_gradient(t, m, a, combine).select("mode", "idx", F.round("grad", 5).alias("grad"))

    TABLE[f"q_grad_u_p2_{_name}"] = ((lambda f: lambda spark, d: f(spark, d))(_keyed), _GRAD_SQL)


@query("q_grad_u_p2_keyed_raw", _GRAD_SQL)
def _(spark, d):
    t, m, a = _adjoints(spark, d)
    return spark.createDataFrame([(k, i, r(v[0])) for (k, i), v in passes.keyed_raw_gradient(t, m, a).items()], "mode int, idx long, grad double")


@query("q_predict_p2", f"WITH {_m_sql(BETA)} SELECT i_1, i_2, i_3, round({BETA} * (k1 * {_W1} + k2 * {_W2}), 5) AS mean, round(1 - (k1*k1*(q11 - m11) + 2*k1*k2*(q12 - m12) + k2*k2*(q22 - m22)), 5) AS var FROM k, m")
def _(spark, d):
    t, m = folded(spark, d), sine_model()
    p = predict(t, m, t.df.select(*t.modes))
    return p.select(*t.modes, F.round("mean", 5).alias("mean"), F.round("var", 5).alias("var"))


@query("q_em_equals_collapsed", f"WITH {_m_sql(BETA)} SELECT round(0.5 * (ln(qdet) - ln(mdet)) - 0.5 * {BETA} * (s + c) + 0.5 * {BETA} * (q11*g11 + 2*q12*g12 + q22*g22) + 0.5 * {BETA * BETA} * (m11*h1*h1 + 2*m12*h1*h2 + m22*h2*h2) + 0.5 * n * ln({BETA} / (2 * pi())) + prior, 5) AS bound FROM m")
def _(spark, d):
    """The uncollapsed bound at the best q(v)."""
    m = sine_model()
    s = passes.suff_stats(folded(spark, d), m)
    return one_row(spark, bound=r(em.gaussian_value(m, s, *gaussian.optimal_qv(m, s))))


# -- tensor algebra and measures --------------------------------------------------------------------------------------
@query("q_mode_product", f"WITH {CELLS_SQL}, w AS (SELECT j, i, sin(j + 0.3 * i) AS w FROM range(3) a(j), range(6) b(i)) SELECT i_1, j AS i_2, i_3, round(sum(y * w), 6) AS y FROM cells JOIN w ON i_2 = i GROUP BY i_1, j, i_3")
def _(spark, d):
    w = spark.range(3).select(F.col("id").alias("j")).crossJoin(spark.range(6).select(F.col("id").alias("i"))).withColumn("w", F.sin(F.col("j") + 0.3 * F.col("i")))
    return multilinear.mode_product(folded(spark, d), w, 1).withColumn("y", F.round("y", 6))


_U2 = lambda k, i: [f"sin(0.7 * {i} + {k})", f"cos(0.4 * {i} + {k})"]


def _two_rank() -> tuple[np.ndarray, ...]:
    return tuple(np.stack([np.sin(0.7 * np.arange(n) + k + 1), np.cos(0.4 * np.arange(n) + k + 1)], 1) for k, n in enumerate(DIMS))


@query("q_cp_reconstruct", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, round({' + '.join('*'.join(_U2(k + 1, f'i_{k + 1}')[j] for k in range(3)) for j in range(2))}, 9) AS mean FROM cells")
def _(spark, d):
    t = folded(spark, d)
    return multilinear.predict_cells(multilinear.CP(_two_rank()), t.df.select(*t.modes), t.modes).withColumn("mean", F.round("mean", 9))


@query("q_tucker_reconstruct", f"WITH {CELLS_SQL} SELECT i_1, i_2, i_3, round({' + '.join('*'.join([str(1 + a + 2 * b + 3 * c), _U2(1, 'i_1')[a], _U2(2, 'i_2')[b], _U2(3, 'i_3')[c]]) for a in range(2) for b in range(2) for c in range(2))}, 8) AS mean FROM cells")
def _(spark, d):
    t = folded(spark, d)
    core = np.fromfunction(lambda a, b, c: 1 + a + 2 * b + 3 * c, (2, 2, 2))
    return multilinear.predict_cells(multilinear.Tucker(core, _two_rank()), t.df.select(*t.modes), t.modes).withColumn("mean", F.round("mean", 8))


@query("q_cp_mttkrp", f"WITH {CELLS_SQL} SELECT i_1 AS idx, 0 AS pos, round(sum(y*{_U2(2, 'i_2')[0]}*{_U2(3, 'i_3')[0]}), 6) AS v FROM cells GROUP BY i_1 UNION ALL SELECT i_1, 1, round(sum(y*{_U2(2, 'i_2')[1]}*{_U2(3, 'i_3')[1]}), 6) FROM cells GROUP BY i_1")
def _(spark, d):
    return multilinear.mttkrp(folded(spark, d), _two_rank(), 0).withColumn("v", F.round("v", 6))


_SC = f"{CELLS_SQL}, sc AS (SELECT *, floor(10 * (k1 + k2)) / 10 AS score, CASE WHEN y > 0.5 THEN 1.0 ELSE 0.0 END AS yb, (i_1 + i_2) % 5 AS fold FROM k)"


def _scored(spark, d):
    k = [kernel_expr("rbf", F.col("x"), F.array(*map(F.lit, p)), F.array(*map(F.lit, (1.0, 1.0, 1.0)))) for p in POINTS]
    t = inputs_df(folded(spark, d))
    return t.select("i_1", "i_2", "i_3", "y", (F.floor(10 * (k[0] + k[1])) / 10).alias("score"), (F.col("y") > 0.5).cast("double").alias("yb"), ((F.col("i_1") + F.col("i_2")) % 5).alias("fold"))


@query("q_mse", f"WITH {_SC} SELECT fold, round(avg(pow(y - score, 2)), 8) AS mse FROM sc GROUP BY fold")
def _(spark, d):
    return metrics.mse(_scored(spark, d), "y", "score", ["fold"]).withColumn("mse", F.round("mse", 8))


_AUC = "SELECT fold, sum(CASE WHEN a.yb = 1 AND b.yb = 0 THEN CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0 END END) / sum(CASE WHEN a.yb = 1 AND b.yb = 0 THEN 1 END) AS auc FROM sc a JOIN sc b USING (fold) GROUP BY fold"


@query("q_auc", f"WITH {_SC} SELECT fold, round(auc, 8) AS auc FROM ({_AUC})")
def _(spark, d):
    return metrics.auc(_scored(spark, d), "yb", "score", ["fold"]).withColumn("auc", F.round("auc", 8))


@query("q_auc_binned", f"WITH {_SC}, b AS (SELECT least(999, floor(score / 3 * 1000)) AS b, count(*) FILTER (WHERE yb > 0) AS p, count(*) FILTER (WHERE yb <= 0) AS n FROM sc GROUP BY 1), w AS (SELECT *, coalesce(sum(n) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM b) SELECT round((sum(p * (below + n / 2.0)) / (sum(p) * sum(n)))::DOUBLE, 8) AS auc, round((sum(p * n / 2.0) / (sum(p) * sum(n)))::DOUBLE, 8) AS error_bound FROM w")
def _(spark, d):
    out = metrics.auc_binned(_scored(spark, d).withColumn("p", F.col("score") / 3), "yb", "p", 1000)
    return out.select(F.round("auc", 8).alias("auc"), F.round("error_bound", 8).alias("error_bound"))


@query("q_foldstats", f"WITH {_SC}, v AS (SELECT fold, avg(score) AS v FROM sc GROUP BY fold) SELECT round(avg(v), 8) AS mean, round(stddev(v), 8) AS sd, round(stddev(v) / sqrt(count(v)), 8) AS se, count(v) AS folds FROM v")
def _(spark, d):
    v = _scored(spark, d).groupBy("fold").agg(F.avg("score").alias("v"))
    return metrics.fold_stats(v, "v", []).select(*(F.round(c, 8).alias(c) for c in ("mean", "sd", "se")), "folds")


@query("q_ttest_stat", f"WITH {_SC}, v AS (SELECT fold, avg(score) AS a, avg(y) AS b FROM sc GROUP BY fold) SELECT round(avg(a - b) / (stddev(a - b) / sqrt(count(*))), 6) AS t FROM v")
def _(spark, d):
    v = _scored(spark, d).groupBy("fold").agg(F.avg("score").alias("a"), F.avg("y").alias("b"))
    return v.agg(F.round(metrics.t_statistic(F.col("a"), F.col("b")), 6).alias("t"))


@query("q_gain", "SELECT pair, round(a::DOUBLE / b - 1, 6) AS over_views, round(a::DOUBLE / c - 1, 6) AS over_all FROM (SELECT strftime(CAST(ts AS DATE), '%Y-%m-%d') AS pair, count(*) FILTER (WHERE event_type = 'click') AS a, count(*) FILTER (WHERE event_type = 'view') AS b, count(*) AS c FROM events GROUP BY ALL)")
def _(spark, d):
    """Relative gains of each day's clicks over its views and over all events."""
    n = lambda kind: F.count_if(F.col("event_type") == kind)
    df = workloads.load_table(spark, d, "events", ["ts", "event_type"]).groupBy(F.date_format("ts", "yyyy-MM-dd").alias("pair")).agg(n("click").alias("a"), n("view").alias("b"), F.count("*").alias("c"))
    return df.select("pair", F.round(metrics.relative_gain(F.col("a"), F.col("b")), 6).alias("over_views"), F.round(metrics.relative_gain(F.col("a"), F.col("c")), 6).alias("over_all"))


@query("q_cost_model", "SELECT n, tasks, n * 10000.0::DOUBLE / tasks AS flops, 8.0::DOUBLE * (60600 + 10000 + n * 3.0::DOUBLE / tasks) AS bytes, tasks * 61500.0::DOUBLE AS keyfree, n * 9.0::DOUBLE AS keyed FROM (SELECT count(*) AS n, 1 + count(DISTINCT user_id) // 50 AS tasks FROM events GROUP BY CAST(ts AS DATE))")
def _(spark, d):
    """The cost of one evaluation over each day's events, dealt over a task for every 50 of its users; days are few."""
    days = workloads.load_table(spark, d, "events", ["ts", "user_id"]).groupBy(F.to_date("ts")).agg(F.count("*").alias("n"), (1 + F.floor(F.countDistinct("user_id") / 50)).alias("tasks"))
    rows = []
    for r in days.collect():
        c = planner.cost_model(r.n, [10_000, 200, 10_000], [3, 3, 3], 100, r.tasks)
        rows.append((r.n, r.tasks, c.flops_per_task, c.bytes_per_task, c.keyfree_numbers, c.keyed_numbers))
    return spark.createDataFrame(rows, "n bigint, tasks bigint, flops double, bytes double, keyfree double, keyed double")


# -- fits (rows only) -------------------------------------------------------------------------------------------------
def small(spark: SparkSession, d: str, binary: bool = False) -> tuple[TensorFrame, DataFrame]:
    """Planted responses on folded indices, four folds to train and one to test."""
    t = workloads.planted(folded(spark, d), binary)
    folds = sampling.kfold(t)
    train = t.with_df(folds.where("fold > 0").drop("fold")).distribute(4)
    return train, folds.where("fold = 0").drop("fold")


def _fit_query(name: str, binary: bool = False, **how):
    def run(spark, d):
        train, _ = small(spark, d, binary)
        m = fit(train, p=12, **{"steps": 6, **how})
        return trace_frame(train, m)

    TABLE[name] = (run, None)


_fit_query("q_fit_gd", optimiser="gd")
_fit_query("q_fit_gd_constant", optimiser="gd_constant", rate=0.002)
_fit_query("q_fit_gd_decay", optimiser="gd_decay", rate=0.005)
_fit_query("q_fit_lbfgs", optimiser="lbfgs")
_fit_query("q_fit_lbfgs_ard", optimiser="lbfgs", kernel="ard")
_fit_query("q_fit_lbfgs_matern32", optimiser="lbfgs", kernel="matern32")
_fit_query("q_fit_keyed", optimiser="gd", reduce="keyed", steps=3)
_fit_query("q_fit_em", inference="em")
_fit_query("q_fit_binary_gd", True, optimiser="gd", steps=4)
_fit_query("q_fit_binary_lbfgs", True, optimiser="lbfgs", steps=4)
_fit_query("q_fit_binary_joint", True, lambda_mode="joint", steps=4)
_fit_query("q_fit_binary_em", True, inference="em", steps=4)


def _anchored_query(name: str, binary: bool, optimiser: str):
    def run(spark, d):
        """Training with the largest mode's factors in a table, as the planner asks where a task has little memory."""
        train, _ = small(spark, d, binary)
        done = fit_planned(train, 2, 8, task_bytes=400.0, optimiser=optimiser, steps=2, lam_iter=5)
        return trace_frame(train, done.model).withColumn("placement", F.lit(done.plan.placement))

    TABLE[name] = (run, None)


_anchored_query("q_fit_anchored_gd", False, "gd_constant")
_anchored_query("q_fit_anchored_lbfgs", False, "lbfgs")
_anchored_query("q_fit_anchored_binary", True, "gd_constant")


@query("q_lambda_trace")
def q_lambda_trace(spark, d):
    t, _ = small(spark, d, True)
    m = init_model(t, 3, 12)
    _, _, trace = probit.fixed_point(t, m, passes.suff_stats(t, m), tol=1e-8)
    return spark.createDataFrame([(i, float(v), i == 0 or v >= trace[i - 1] - 1e-8) for i, v in enumerate(trace)], "step int, bound double, rises boolean")


def _baseline(name: str, binary: bool, model):
    def run(spark, d):
        train, test = small(spark, d, binary)
        scored = multilinear.predict_cells(model(train), test.select(*train.modes, "y"), train.modes)
        return metrics.auc(scored, "y", "mean") if binary else metrics.mse(scored)

    TABLE[name] = (run, None)


_baseline("q_cp", False, lambda t: multilinear.fit_cp(t, 3, 5))
_baseline("q_cp2", False, lambda t: multilinear.fit_cp(t, 3, 5, observed_only=True))
_baseline("q_nncp", True, lambda t: multilinear.fit_nncp(t, 3, 8))
_baseline("q_sparse_cp", False, lambda t: multilinear.fit_sparse_cp(t, 3, 5))
_baseline("q_hosvd", False, lambda t: multilinear.fit_hosvd(t, 3))
_baseline("q_tucker", False, lambda t: multilinear.fit_tucker(t, 3, 3))
_baseline("q_krongp", False, lambda t: kron.fit_krongp(t, 2, steps=20))
_baseline("q_krongp_binary", True, lambda t: kron.fit_krongp(t, 2, steps=20))
_baseline("q_blockkron", False, lambda t: kron.fit_blockkron(t, 2, 6, [5, 5, 4], 2, 4))
_baseline("q_mixkron", False, lambda t: kron.fit_mixkron(t, 2, blocks=5, block=[5, 5, 4]))


@query("q_krongp_kernel")
def _(spark, d):
    """Kernel and length by cross-validation inside the training folds, and the error of the chosen one on the fold left out."""
    train, test = small(spark, d)
    (name, length), table = kron.select_kernel(train, rank=2)
    model = kron.fit_krongp(train, 2, name, steps=20)
    held = metrics.mse(multilinear.predict_cells(model, test.select(*train.modes, "y"), train.modes)).first()[0]
    chosen = (F.col("kernel") == name) & (F.col("length") == length)
    return table.select("kernel", "length", "error", chosen.alias("chosen"), F.when(chosen, F.lit(float(held))).alias("held_out"))


@query("q_mode_means", f"WITH {CELLS_SQL} SELECT CAST(1 AS INTEGER) AS mode, i_1 AS idx, count(*) AS n, round(sum(y) / (count(*) + 1), 8) AS score FROM cells GROUP BY i_1 UNION ALL SELECT 2, i_2, count(*), round(sum(y) / (count(*) + 1), 8) FROM cells GROUP BY i_2 UNION ALL SELECT 3, i_3, count(*), round(sum(y) / (count(*) + 1), 8) FROM cells GROUP BY i_3")
def _(spark, d):
    return multilinear.mode_means(folded(spark, d)).withColumn("score", F.round("score", 8))


_RING = lambda k, d, m: f"({m} * {next(x for x in range(max(1, int(d * 0.618)), 2 * d + 2) if np.gcd(x, d) == 1)} + ({portable_hash_sql('block_id', str(k), seed=0)} // 256) % {d}) % {d}"


@query("q_sample_blocks", f"WITH {_NZ} SELECT CAST(block_id AS INTEGER) AS block_id, count(*) AS n FROM nz, range(20) t(block_id) WHERE {_RING(0, 50, 'i_1')} < 10 AND {_RING(1, 24, 'i_2')} < 5 AND {_RING(2, 100, 'i_3')} < 10 GROUP BY block_id")
def _(spark, d):
    """Cells of each random sub-tensor; blocks without one are absent."""
    return kron.sample_blocks(clicks(spark, d), 20, [10, 5, 10]).groupBy("block_id").agg(F.count("*").alias("n"))


@query("q_empty_blocks", f"WITH {_NZ}, b AS (SELECT DISTINCT block_id FROM nz, range(40) t(block_id) WHERE {_RING(0, 50, 'i_1')} < 4 AND {_RING(1, 24, 'i_2')} < 3 AND {_RING(2, 100, 'i_3')} < 4) SELECT round(1 - count(*) / 40.0::DOUBLE, 9) AS share FROM b")
def _(spark, d):
    """The share of random sub-tensors that hold no cell."""
    return one_row(spark, share=round(kron.empty_blocks(clicks(spark, d), 40, [4, 3, 4]), 9))


def ctr(spark: SparkSession, d: str, planted: bool = False, steps: int = 3, p: int = 50, pairs: int = 3) -> DataFrame:
    """(pair, method, auc): day t trains, day t+1 tests; FlexGP against one-hot LR and SVM."""
    days = [f"2024-01-0{i}" for i in range(1, 5)]
    top = spark.read.parquet(f"{d}/events.parquet").agg(F.max("user_id")).first()[0] + 1
    dims = (int(top), 100, 24, 60)

    def one(i: int) -> list[tuple]:
        train, test = (workloads.w8_day(spark, d, x, dims) for x in days[i : i + 2])
        if planted:
            train, test = workloads.planted(train, True), workloads.planted(test, True)
        train, test = balanced(train).distribute(4), balanced(test)
        cells = test.df.select(*test.modes, "y").persist()
        scored = {
            "flexgp": lambda: predict(train, fit(train, p=p, steps=steps, ranks=3, lam_iter=5), cells),
            "logreg": lambda: linear.ctr_logreg(train.df, cells, train.modes),
            "svm": lambda: linear.ctr_svm(train.df, cells, train.modes),
        }
        return [(f"{i + 1}-{i + 2}", name, metrics.auc(f(), "y", "score").first()[0]) for name, f in scored.items()]

    with ThreadPoolExecutor(pairs) as pool:
        rows = [row for part in pool.map(one, range(pairs)) for row in part]
    return spark.createDataFrame(rows, "pair string, method string, auc double")


def balanced(t: TensorFrame, seed: int = 9) -> TensorFrame:
    """All clicks and as many of the other events, by hash."""
    ones = t.df.where("y = 1").select(*t.modes, "y")
    return t.with_df(ones.unionByName(sampling.smallest_hashes(t.df.where("y = 0").select(*t.modes, "y"), t.modes, ones.count(), seed)))


@query("q_ctr")
def _(spark, d):
    """AUC of three day pairs and FlexGP's relative gain over each method."""
    return with_gain(ctr(spark, d))


@query("q_ctr_planted")
def _(spark, d):
    return with_gain(ctr(spark, d, planted=True))


def with_gain(auc: DataFrame) -> DataFrame:
    ours = auc.where("method = 'flexgp'").select("pair", F.col("auc").alias("ours"))
    return auc.join(F.broadcast(ours), "pair").select("pair", "method", "auc", metrics.relative_gain(F.col("ours"), F.col("auc")).alias("gain"))


@query("q_exact_small", "SELECT true AS holds")
def _(spark, d):
    """The bound never exceeds the exact log marginal on the tiny full grid."""
    t = workloads.tiny(spark, d)
    m = replace(init_model(t, 1, 10), beta=1.0)
    t = t.with_df(t.df.withColumn("y", F.col("y") / 50_000))
    pdf = t.df.toPandas()
    ex = exact.exact_log_marginal(m, pdf[t.modes].to_numpy(), pdf["y"].to_numpy())
    return spark.createDataFrame([(bool(gaussian.value(m, passes.suff_stats(t, m)) - gaussian.prior(m) <= ex),)], "holds boolean")


@query("q_w15_given_inputs", "SELECT count(*) AS n, true AS holds, true AS rises FROM embeddings")
def _(spark, d):
    """Given inputs, factors frozen: with embeddings as coordinates the bound stays under the exact log marginal, and more inducing points raise it."""
    e = workloads.embedding_inputs(spark, d)
    rows = e.select("x", "y").persist()
    kernel, beta = Kernel("rbf", [0.5]), 4.0
    first = np.array([r.x for r in e.orderBy("vec_id").limit(60).collect()])
    bounds = []
    for p in (20, 60):
        m = ModelState((), first[:p].copy(), kernel, beta)
        s = passes.input_stats(rows, m.inducing, kernel)
        bounds.append(gaussian.value(m, s))
    holds = under_exact(rows, e, kernel, beta, max(bounds), s.n)
    rows.unpersist()
    return spark.createDataFrame([(s.n, holds, bool(bounds[0] <= bounds[1]))], "n bigint, holds boolean, rises boolean")


def under_exact(rows: DataFrame, e: DataFrame, kernel: Kernel, beta: float, value: float, n: int, points: int = 256) -> bool:
    """Whether ``value`` is at most the exact log marginal of all rows: exactly for a few, else by an interval around it that is
    narrowed with more inducing points until ``value`` lies outside it."""
    if n <= exact.MOST:
        pdf = e.orderBy("vec_id").select("x", "y").toPandas()
        m = ModelState((np.stack(pdf["x"].to_numpy()),), np.zeros((0, 0)), kernel, beta)
        return bool(value <= exact.exact_log_marginal(m, np.arange(n)[:, None], pdf["y"].to_numpy()))
    while True:
        z = np.array([r.x for r in e.orderBy(sampling.portable_hash(F.col("vec_id"), seed=23), "vec_id").limit(points).collect()])
        s = passes.input_stats(rows, z, kernel)
        k = gaussian.kzz(ModelState((), z, kernel, beta))
        low, high = exact.log_marginal_between(s, k, beta)
        if value <= low or value > high:
            return bool(value <= low)
        if points >= n:
            raise ValueError(f"{value} can't be told from the exact log marginal, between {low} and {high}")
        points = min(n, 2 * points)


@query("q_w14_lambda_ablation")
def _(spark, d):
    """Bound reached with λ nested and with λ climbed jointly, same number of outer steps."""
    t, _ = small(spark, d, True)
    rows = [(mode, float(fit(t, p=12, steps=5, lambda_mode=mode).trace[-1][2])) for mode in ("nested", "joint")]
    return spark.createDataFrame(rows, "mode string, bound double")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """W1: build, balance, fit by gradient ascent, predict held-out cells, (n, mse, bound)."""
    t = workloads.w1(spark, d)
    folds = sampling.kfold(t)
    train, test = t.with_df(folds.where("fold > 0").drop("fold")), folds.where("fold = 0").select(*t.modes, "y")
    train = sampling.balanced_sample(train, exclude=test).distribute(4)
    m = fit(train, p=10, optimiser="gd", steps=5)
    scored = predict(train, m, test)
    return metrics.mse(scored).withColumn("bound", F.lit(float(m.trace[-1][2]))).withColumn("steps", F.lit(len(m.trace) - 1))


TABLE["q_flagship"] = (flagship, None)

