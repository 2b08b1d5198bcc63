"""Baselines against plain numpy, sampling against brute force, plans, and queries that have no SQL twin."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from flextensor import sampling, workloads
from flextensor.baselines import kron, multilinear
from flextensor.bounds import gaussian
from flextensor.exec import passes
from flextensor.fit import fit
from flextensor.functions.kernels import Kernel
from flextensor.model import init_model
from flextensor.operators import experiments
from flextensor.operators.tensor_queries import clicks, folded
from flextensor.queries import LONG, ORACLES, QUERIES
from flextensor.tensor import TensorFrame, build_tensor

# the long harnesses' parts are tested here; the queries themselves run in the driver's checks


def tensor(spark, dims=(6, 5, 4), n=70, seed=0, binary=False):
    rng = np.random.default_rng(seed)
    cells = rng.permutation(int(np.prod(dims)))[:n]
    index = np.stack(np.unravel_index(cells, dims), 1)
    y = (rng.random(n) > 0.5).astype(float) if binary else rng.normal(size=n)
    pdf = pd.DataFrame({**{f"i_{k + 1}": index[:, k].astype(np.int64) for k in range(len(dims))}, "y": y})
    dense = np.zeros(dims)
    dense[tuple(index.T)] = y
    return TensorFrame(spark.createDataFrame(pdf), dims, "binary" if binary else "real").distribute(3), index, y, dense


def test_sparse_cp_equals_dense_alternating_least_squares(spark):
    t, _, _, dense = tensor(spark)
    start = multilinear.table_start(t, 2)
    u = [x.toPandas().sort_values("idx")[["c_0", "c_1"]].to_numpy() for x in start]
    tables = multilinear.sparse_cp_tables(t, 2, 3, start=start)
    for _ in range(3):
        for k in range(3):
            a, b = (u[j] for j in range(3) if j != k)
            kr = np.einsum("ir,jr->ijr", a, b).reshape(-1, 2)
            u[k] = np.moveaxis(dense, k, 0).reshape(dense.shape[k], -1) @ kr @ np.linalg.inv((a.T @ a) * (b.T @ b) + 1e-6 * np.eye(2))
    for k, x in enumerate(tables):
        pdf = x.toPandas().set_index("idx")
        got = np.zeros_like(u[k])
        got[pdf.index] = pdf[["c_0", "c_1"]].to_numpy()
        assert np.allclose(got, u[k], atol=1e-8)
    cells = t.df.select(*t.modes)
    by_table = multilinear.predict_tables(tables, cells, t.modes).toPandas()
    assert np.allclose(by_table["mean"], multilinear.CP(tuple(u))(by_table[t.modes].to_numpy()), atol=1e-8)


def test_cp_on_selected_cells_equals_row_least_squares(spark):
    t, index, y, _ = tensor(spark)
    u = multilinear._start(t.dims, 2, 0)
    got = multilinear.fit_cp(t, 2, 2, observed_only=True)
    for _ in range(2):
        for k in range(3):
            x = np.prod([u[j][index[:, j]] for j in range(3) if j != k], axis=0)
            for i in range(t.dims[k]):
                own = index[:, k] == i
                u[k][i] = np.linalg.solve(x[own].T @ x[own] + 1e-3 * np.eye(2), x[own].T @ y[own])
    assert all(np.allclose(a, b) for a, b in zip(got.factors, u))


def test_nonnegative_cp_equals_multiplicative_updates(spark):
    t, _, _, dense = tensor(spark, seed=3)
    dense = np.maximum(dense, 0)
    u = multilinear._start(t.dims, 2, 0, True)
    got = multilinear.fit_nncp(t, 2, 2)
    for _ in range(2):
        for k in range(3):
            a, b = (u[j] for j in range(3) if j != k)
            kr = np.einsum("ir,jr->ijr", a, b).reshape(-1, 2)
            u[k] = u[k] * (np.moveaxis(dense, k, 0).reshape(dense.shape[k], -1) @ kr) / (u[k] @ ((a.T @ a) * (b.T @ b)) + 1e-12)
    assert all(np.allclose(a, b) for a, b in zip(got.factors, u))


def test_hosvd_and_tucker_against_dense(spark):
    t, _, _, dense = tensor(spark, (12, 7, 5), 200)
    for k in range(3):
        x = np.moveaxis(dense, k, 0).reshape(dense.shape[k], -1)
        left = np.linalg.svd(x, full_matrices=False)[0][:, :2]
        for got in (multilinear._leading(multilinear.unfolding_gram(t, k), 2), multilinear.range_finder(t, k, 2, powers=3)):
            assert np.allclose(np.abs(np.linalg.svd(left.T @ got)[1]), 1, atol=1e-3)
    whole = multilinear.fit_hosvd(t, [12, 7, 5], gram_side=100)
    grid = np.stack(np.unravel_index(np.arange(dense.size), dense.shape), 1)
    assert np.allclose(whole(grid), dense.ravel(), atol=1e-8)
    assert np.square(multilinear.fit_tucker(t, 3, 6)(grid) - dense.ravel()).sum() <= np.square(multilinear.fit_hosvd(t, 3)(grid) - dense.ravel()).sum() + 1e-9


def test_block_predictor_uses_all_cells(spark):
    t, index, y, _ = tensor(spark, n=90)
    rng = np.random.default_rng(1)
    u = [rng.normal(size=(d, 2)) for d in t.dims]
    kernel = Kernel("rbf", [1.0])
    m = kron._regression(t, u, kernel, 90, 0.1, 0)  # as many points as cells: the exact product-kernel GP
    k = kron._product_gram(u, kernel, index, index)
    assert np.allclose(m(index), k @ np.linalg.solve(k + 0.1 * np.eye(len(y)), y), atol=1e-3)
    few = kron._regression(t, u, kernel, 10, 0.1, 0)
    z = few.index
    kz, kx = kron._product_gram(u, kernel, z, z) + 1e-6 * np.eye(10), kron._product_gram(u, kernel, index, z)
    assert np.allclose(few.weights, np.linalg.solve(0.1 * kz + kx.T @ kx + 1e-9 * np.eye(10), kx.T @ y))


def test_kernel_is_chosen_inside_the_training_cells(spark):
    t, index, y, _ = tensor(spark)
    (name, length), table = kron.select_kernel(t, ("rbf", "matern12"), (0.5, 1.0), rank=2, steps=2)
    fold = {tuple(r[m] for m in t.modes): r.fold for r in sampling.kfold(t, 3, seed=21).collect()}
    fold = np.array([fold[tuple(i)] for i in index])
    want = {}
    for k in ("rbf", "matern12"):
        for x in (0.5, 1.0):
            e = 0.0
            for f in range(3):
                dense = np.zeros(t.dims)
                dense[tuple(index[fold != f].T)] = y[fold != f]
                e += ((kron.fit_dense(dense, 2, Kernel(k, [x]), 2, 0.1, 0.1, False, 0)(index[fold == f]) - y[fold == f]) ** 2).sum()
            want[k, x] = e / len(y)
    got = {(r.kernel, r.length): r.error for r in table.collect()}
    assert got == pytest.approx(want) and (name, length) == min(want, key=lambda k: (want[k], k))


def test_blocks_equal_their_definition(spark, data):
    t = clicks(spark, data)
    got = {tuple(r) for r in kron.sample_blocks(t, 6, [10, 5, 10]).select("block_id", *t.modes, "l_1", "l_2", "l_3").collect()}
    cells = [tuple(r) for r in t.df.select(*t.modes).collect()]

    def hash_of(*xs):
        h = 0
        for x in xs:
            h = (h + x) % sampling.MODULUS * sampling.MULTIPLIER % sampling.MODULUS + sampling.INCREMENT
            h %= sampling.MODULUS
        return (h * sampling.MULTIPLIER + sampling.INCREMENT) % sampling.MODULUS

    want = set()
    for b in range(6):
        for c in cells:
            place = []
            for k, d in enumerate(t.dims):
                step = next(s for s in range(max(1, int(d * 0.618)), 2 * d + 2) if np.gcd(s, d) == 1)
                place.append((c[k] * step + hash_of(b, k) // 256 % d) % d)
            if all(p < n for p, n in zip(place, (10, 5, 10))):
                want.add((b, *c, *place))
    assert got == want


def test_mixture_finds_two_groups():
    rng = np.random.default_rng(0)
    x = np.vstack([rng.normal(-3, 1, (200, 2)), rng.normal(3, 1, (200, 2))])
    m = kron.Mixture(6, 2, 1.0, rng)
    for i in range(60):
        batch = x[rng.permutation(400)[:100]]
        m.update(batch, m.responsibilities(batch), 4.0, (2 + i) ** -0.7)
    own = m.responsibilities(x).argmax(1)
    assert len(set(own[:200]) & set(own[200:])) == 0
    for v, want in ((1.0, -0.5772156649), (0.1, -10.4237549404), (7.5, 1.9467574666)):
        assert kron.digamma(np.array([v]))[0] == pytest.approx(want, abs=1e-6)


def test_test_sets_and_fold_zeros(spark, data):
    t = clicks(spark, data)
    train, tests = sampling.train_and_tests(t, reps=5, n_one=20, n_zero=50)
    tests = tests.toPandas()
    cells, held = {tuple(r) for r in t.df.select(*t.modes).collect()}, {tuple(r) for r in train.df.select(*t.modes).collect()}
    for _, g in tests.groupby("rep"):
        ones, zeros = ({tuple(r) for r in g[g.y == y][t.modes].itertuples(index=False)} for y in (1.0, 0.0))
        assert len(ones) == 20 and len(zeros) == 50 and ones <= cells - held and not zeros & cells
    assert len({frozenset(map(tuple, g[t.modes].to_numpy())) for _, g in tests.groupby("rep")}) == 5
    z = sampling.fold_zeros(t).toPandas()
    assert set(z.fold) == set(range(5)) and not {tuple(r) for r in z[t.modes].itertuples(index=False)} & cells
    n = len(cells)
    assert (z.groupby("fold").size() == max(1, min(int((120_000 - n) * 0.001), n // 5))).all()
    with pytest.raises(ValueError):
        sampling.empty_cells(TensorFrame(t.df, (1, 1, 1), "binary"), 1, 5)


def test_smallest_hashes(spark):
    df = spark.range(5000).select((F.col("id") % 71).alias("i_1"), F.floor(F.col("id") / 71).alias("i_2"))
    h = sampling.portable_hash(F.col("i_1"), F.col("i_2"), seed=2)
    want = {tuple(r) for r in df.orderBy(h, "i_1", "i_2").limit(777).collect()}
    assert {tuple(r) for r in sampling.smallest_hashes(df, ["i_1", "i_2"], 777, 2).collect()} == want
    assert sampling.smallest_hashes(df, ["i_1", "i_2"], 9999, 2).count() == 5000


def test_modes_beyond_one_task_are_numbered_alike(spark, data):
    import flextensor.tensor as T

    lines = spark.read.parquet(f"{data}/lineitem.parquet")
    args = (["l_partkey", "l_suppkey", "l_returnflag"], F.lit(1.0), "count")
    small = build_tensor(lines, *args)
    cells = T.merge_cells(lines, *args)
    out, _, dims = T.dense_index(cells, 3, most=10)
    assert dims == small.dims and sorted(map(tuple, out.collect())) == sorted(map(tuple, small.df.collect()))


def test_gradient_ascent_takes_the_step_of_the_gradient(spark, data):
    t = workloads.planted(folded(spark, data)).distribute(3)
    m = init_model(t, 2, 6)
    s = passes.suff_stats(t, m)
    a, dk, db = gaussian.adjoints(m, s)
    g = gaussian.to_logs(m, gaussian.finish(m, passes.gradient_pass(t, m, a), dk, db))
    got = fit(t, m, optimiser="gd_constant", rate=1e-3, steps=1)
    assert np.allclose(got.pack(), m.pack() + 1e-3 * g, rtol=1e-6, atol=1e-9)


@pytest.mark.parametrize("binary", [False, True])
def test_sharded_factors_equal_the_dense_path(spark, data, binary):
    from dataclasses import replace

    from flextensor.exec import anchored
    from flextensor.fit import evaluate, fit_planned

    t = workloads.planted(folded(spark, data), binary).distribute(3)
    m, table = anchored.init_anchored(t, 0, 2, 6)
    own = np.array([r.v for r in table.orderBy("idx").collect()])
    dense = replace(m, factors=(own, *m.factors[1:]))
    value, g, _ = evaluate(t, dense, lam_iter=30)
    got, h, _ = anchored.evaluate_anchored(t, m, table, 0, 30, 3, 2)
    n = own.size
    assert got == pytest.approx(value, rel=1e-7)
    assert np.allclose(np.array([r.v for r in h.table.orderBy("idx").collect()]).ravel(), g[:n], atol=1e-5) and np.allclose(h.small, g[n:], atol=1e-5)
    x = anchored.Sharded(m.pack(), table)
    assert x @ h == pytest.approx(float(np.concatenate([own.ravel(), m.pack()]) @ g), rel=1e-5, abs=1e-5)
    done = fit_planned(t, 2, 6, task_bytes=400.0, optimiser="lbfgs", steps=1, lam_iter=5)
    assert done.plan.placement == "anchored" and done.model.trace[-1][2] >= done.model.trace[0][2]
    cells = t.df.select(*t.modes, "y")
    assert done.predict(t, cells).count() == cells.count()
    assert fit_planned(t, 2, 6, steps=1, lam_iter=3).plan.placement == "any"


def test_fold_harness(spark, data):
    rows = experiments.folds_table(clicks(spark, data), ("flexgp", "cp2", "krongp"), 3, rank=2, p=10, steps=2).collect()
    assert len(rows) == 9 and all(0 <= r.value <= 1 for r in rows)


def test_set_harness(spark, data):
    t = clicks(spark, data)
    rows = experiments.sets_table(t, ("flexgp", "sparse_cp"), 2, reps=4, n_zero=100, p=10, steps=1).collect()
    assert {r.method for r in rows} == {"flexgp", "sparse_cp"} and all(r.sets == 4 for r in rows)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - set(LONG)))
def test_queries_without_a_twin_run(spark, data, name):
    assert len(QUERIES[name](spark, data).toPandas()) > 0


def test_sums_of_a_large_mode_reach_the_driver_in_slices(spark, monkeypatch):
    from flextensor.exec import passes

    cells = spark.range(4_000).select((F.col("id") % 700).alias("i_1"), (F.col("id") % 11).alias("i_2"), (F.col("id") % 13 / 7.0).alias("y")).repartition(5)
    t = TensorFrame(cells, (705, 11))
    u = tuple(np.random.default_rng(k).normal(size=(d, 3)) for k, d in enumerate(t.dims))
    rows = [np.array(x, float) for x in zip(*cells.collect())]
    for most in (8 << 20, 64 * 24):  # one slice, many
        monkeypatch.setattr(multilinear, "SLICE_BYTES", most)
        monkeypatch.setattr(passes, "SLICE", most // 24)
        for k, other in ((0, 1), (1, 0)):
            want = np.zeros_like(u[k])
            np.add.at(want, rows[k].astype(int), rows[2][:, None] * u[other][rows[other].astype(int)])
            assert np.allclose(multilinear.dense_mttkrp(t, u, k), want)
        got = passes.map_sum(t, 2115, 3, None, lambda _, index, y: np.bincount(index[:, 0] * 3, y, 2115))
        assert np.allclose(got[::3], np.bincount(rows[0].astype(int), rows[2], 705)) and not got[1::3].any()


def test_the_package_ships_once_from_threads(monkeypatch):
    import time
    from concurrent.futures import ThreadPoolExecutor
    from types import SimpleNamespace

    from flextensor import session

    sent = []
    sc = SimpleNamespace(applicationId="app-of-this-test", addPyFile=lambda path: (time.sleep(0.2), sent.append(path)))
    with ThreadPoolExecutor(4) as pool:
        list(pool.map(session.ship_package, [SimpleNamespace(sparkContext=sc)] * 4))
    assert len(sent) == 1
