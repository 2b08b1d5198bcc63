"""What the large runs rely on, on small tensors."""

import resource

import numpy as np
from pyspark.sql import functions as F

from flextensor import sampling
from flextensor.baselines import kron, multilinear
from flextensor.bounds import gaussian, probit
from flextensor.exec import passes
from flextensor.fit import evaluate
from flextensor.functions import special
from flextensor.functions.kernels import Kernel
from flextensor.model import ModelState, init_model
from flextensor.operators import experiments
from flextensor.tensor import TensorFrame


def test_a_blocks_gradient_is_added_in_place():
    rng = np.random.default_rng(0)
    m = ModelState(tuple(rng.normal(size=(d, 2)) for d in (5000, 7)), rng.normal(size=(4, 4)), Kernel("ard", np.ones(4)))
    a = passes.Adjoints(rng.normal(size=(4, 4)), rng.normal(size=4), -0.5)
    index, y = np.stack([rng.integers(0, 5000, 60), rng.integers(0, 7, 60)], 1), rng.normal(size=60)
    total = np.zeros(len(passes.block_gradient((m, a), index, y)))
    for lo in range(0, 60, 25):
        passes.add_gradient(total, (m, a), index[lo : lo + 25], y[lo : lo + 25])
    assert np.allclose(total, passes.block_gradient((m, a), index, y))
    dx = passes.cell_gradients(m, a, index, y)[0]
    assert np.allclose(total[:10000].reshape(5000, 2)[index[0, 0]], dx[index[:, 0] == index[0, 0], :2].sum(0))


def test_large_groups_order_one_bin_only(spark, monkeypatch):
    df = spark.range(900).select((F.col("id") % 3).cast("int").alias("rep"), F.col("id").alias("i_1"), (F.col("id") * 7 % 11).alias("i_2"))
    want = {tuple(r) for r in sampling._first(df, ["i_1", "i_2"], "rep", 120, 3).collect()}
    monkeypatch.setattr(sampling, "SMALL_GROUP", 50)
    got = sampling._first(df, ["i_1", "i_2"], "rep", 120, 3)
    assert got.columns == df.columns and {tuple(r) for r in got.collect()} == want and got.count() == 360
    assert sampling._first(df, ["i_1", "i_2"], "rep", 400, 3).count() == 900


def test_packed_cells_sum_as_rows_do(spark):
    cells = spark.range(500).select((F.col("id") % 13).alias("i_1"), (F.col("id") % 9).alias("i_2"), F.col("id").cast("double").alias("y"))
    rows = TensorFrame(cells, (13, 9))
    kept = rows.distribute(3)
    each = lambda state, index, y: np.bincount(index[:, 0], y, 13) + index.sum() * state
    assert kept.packed is not None and np.allclose(passes.map_sum(kept, 13, 4, 2.0, each), passes.map_sum(rows, 13, 4, 2.0, each))
    kept.release()


def test_kernel_rows_by_modes_equal_the_whole_bell(monkeypatch):
    rng = np.random.default_rng(1)
    dims = (400, 300, 5)
    index = np.stack([np.sort(rng.integers(0, 30, 200)), rng.integers(0, 300, 200), rng.integers(0, 5, 200)], 1)
    for name, lengths in (("ard", 0.5 + rng.random(6)), ("rbf", [0.8])):
        m = ModelState(tuple(rng.normal(size=(d, 2)) for d in dims), rng.normal(size=(7, 6)), Kernel(name, lengths, 1.3), 1.0, rng.normal(size=7), "binary")
        want = m.kernel.gram(m.inputs(index), m.inducing)
        a = passes.Adjoints(rng.normal(size=(7, 7)), rng.normal(size=7), -0.5)
        for most in (1 << 20, 8 * 7 * 310, 8 * 7 * 5, 0):  # tables of all modes, of two, of one, of none
            monkeypatch.setattr(passes, "TABLE_BYTES", most)
            passes._TABLES.clear()
            assert np.allclose(passes.kernel_rows(m, index), want, rtol=1e-12)
            got = passes.cell_gradients(m, a, index, np.ones(200))
            g = want @ (2 * a.dg) + a.dh
            dx, dz, dl, da = m.kernel.vjp(m.inputs(index), m.inducing, g)
            assert np.allclose(got[0], dx) and np.allclose(got[1], dz) and np.allclose(got[2], dl) and np.isclose(got[3], da - 0.5 * 200)


def test_packed_cells_lie_by_the_largest_mode(spark):
    cells = spark.range(3000).select((F.col("id") * 7919 % 1000).alias("i_1"), (F.col("id") % 9).alias("i_2"), F.lit(1.0).alias("y"))
    kept = TensorFrame(cells, (1000, 9)).distribute(2)
    for part in kept.packed.glom().collect():
        at = np.concatenate([np.frombuffer(r[0], np.int64 if len(r[0]) == len(r[2]) else np.int32) for r in part])
        assert (np.diff(at) >= 0).all()
    kept.release()


def test_nonnegative_cp_and_grams_of_kept_cells_and_negative_values(spark):
    rng = np.random.default_rng(2)
    dense = np.where(rng.random((9, 8, 5)) < 0.4, rng.normal(size=(9, 8, 5)), 0.0)
    rows = [(*map(int, i), float(dense[tuple(i)])) for i in np.argwhere(dense)]
    t = TensorFrame(spark.createDataFrame(rows, "i_1 long, i_2 long, i_3 long, y double"), dense.shape)
    kept = t.distribute(3)
    for k in range(3):
        flat = np.moveaxis(dense, k, 0).reshape(dense.shape[k], -1)
        assert np.allclose(multilinear.unfolding_gram(kept, k), flat @ flat.T)
    positive = t.with_df(t.df.where("y > 0"))
    for u, v in zip(multilinear.fit_nncp(kept, 2, 3).factors, multilinear.fit_nncp(positive, 2, 3).factors, strict=True):
        assert np.allclose(u, v)
    kept.release()


def test_the_normal_tail_keeps_its_digits_between_the_middle_and_the_far():
    assert np.isclose(special.ndtr(-4.9), 4.791832765903199e-07, rtol=1e-13)
    assert np.isclose(special.log_ndtr(6.0), -9.865876454243e-10, rtol=1e-9)
    h, log = special.hazard_and_log(np.array([-30.0, -1.0, 0.0, 2.0]))
    assert np.allclose(h[2], np.sqrt(2 / np.pi), rtol=1e-14) and np.isclose(log[2], np.log(0.5), rtol=1e-14) and np.isclose(h[1], 1.5251352761609812, rtol=1e-13)


def test_factors_and_blocks_reach_the_driver_without_rows(spark, monkeypatch):
    cells = spark.range(900).select((F.col("id") % 30).alias("i_1"), (F.col("id") * 7 % 20).alias("i_2"), (F.col("id") % 3).alias("i_3"), F.lit(1.0).alias("y")).distinct()
    t = TensorFrame(cells, (30, 20, 3)).distribute(2)
    monkeypatch.setattr(type(spark.range(0)), "toPandas", None)
    model = multilinear.fit_sparse_cp(t, 2, 1)
    assert [u.shape for u in model.factors] == [(30, 2), (20, 2), (3, 2)] and all(np.abs(u).sum(1).all() for u in model.factors)
    t.release()


def folded_cells(spark):
    cells = spark.range(3000).select((F.col("id") * 7919 % 700).alias("i_1"), (F.col("id") * 31 % 90).alias("i_2"), (F.col("id") * 17 % 11).alias("i_3"), F.lit(1.0).alias("y")).distinct()
    t = TensorFrame(cells, (700, 90, 11), "binary")
    all_ = sampling.kfold(t).persist()
    return t.with_df(all_), sampling.fold_zeros(t.with_df(all_.select(*t.modes, "y"))).persist()


def test_one_draw_gives_every_fold_its_own_zeros(spark):
    t, zeros = folded_cells(spark)
    whole = t.with_df(sampling.balanced_folds(t, 5, zeros)).distribute_marked(3)
    for i in range(5):
        rows = lambda df: sorted(map(tuple, df.select(*t.modes, "y").collect()))
        train = t.with_df(t.df.where(F.col("fold") != i).select(*t.modes, "y"))
        held = zeros.select(*t.modes).unionByName(t.df.where(F.col("fold") == i).select(*t.modes))
        assert rows(whole.marked(1 << i).df) == rows(train.df)
        both = whole.marked(1 << i | 1 << 5 + i)
        assert rows(both.df) == rows(sampling.balanced_sample(train, exclude=held).df)
        each = lambda state, index, y: np.array([len(y), y.sum(), index.sum()], float)
        assert np.allclose(passes.map_sum(both, 3, 4, None, each), passes.map_sum(both.with_df(both.df), 3, 4, None, each))
    whole.release()


def test_a_fold_table_prepares_all_folds_at_once(spark, monkeypatch):
    t, _ = folded_cells(spark)
    t = t.with_df(t.df.drop("fold"))
    with monkeypatch.context() as one_by_one:
        one_by_one.setattr(sampling, "balanced_folds", lambda *a: None)
        want = sorted(map(tuple, experiments.folds_table(t, ("cp2", "hosvd"), 5).collect()))
    monkeypatch.setattr(sampling, "balanced_sample", None)
    got = sorted(map(tuple, experiments.folds_table(t, ("cp2", "hosvd"), 5).collect()))
    assert [r[:2] for r in got] == [r[:2] for r in want] and np.allclose([r[2] for r in got], [r[2] for r in want])


def test_an_evaluation_takes_sums_and_bound_from_the_passes_of_its_steps(spark, monkeypatch):
    t, _ = folded_cells(spark)
    t = t.with_df(t.df.select(*t.modes, F.pmod(F.col("i_1") + F.col("i_2"), F.lit(2)).cast("double").alias("y"))).distribute(2)
    m = init_model(t, 2, 6, "ard")
    s = passes.suff_stats(t, m)
    lam, log_phi, _ = probit.fixed_point(t, m, s, m.lam, 1e-6, 4)
    a, dk = probit.adjoints(m, s, lam)
    want = gaussian.to_logs(m, gaussian.finish(m, passes.gradient_pass(t, m, a), dk, None))
    monkeypatch.setattr(passes, "suff_stats", None)
    monkeypatch.setattr(passes, "gradient_pass", None)
    value, g, seen = evaluate(t, m, lam_iter=4)
    assert np.isclose(value, probit.value(m, s, lam, log_phi)) and np.allclose(g, want) and np.allclose(seen.lam, lam)
    t.release()


def test_blocks_reuse_the_memory_of_those_before(spark):
    def faults(state, index, y):
        before = resource.getrusage(resource.RUSAGE_SELF).ru_minflt
        for _ in range(20):
            np.ones(1 << 19)
        return np.array([resource.getrusage(resource.RUSAGE_SELF).ru_minflt - before], float)

    t = TensorFrame(spark.range(9).select(F.col("id").alias("i_1"), F.col("id").alias("i_2"), F.lit(1.0).alias("y")), (9, 9)).distribute(1)
    assert passes.map_sum(t, 1, 4, None, faults)[0] < 3000  # 20 arrays of 4 MB have 20,480 pages
    t.release()


def test_training_cells_are_dealt_once(spark, monkeypatch):
    t, _ = folded_cells(spark)
    dealt, deal = [], TensorFrame.distribute
    monkeypatch.setattr(experiments, "TASK_CELLS", 200)
    monkeypatch.setattr(TensorFrame, "distribute", lambda t, parts: dealt.append(parts) or deal(t, parts))
    train, balanced, _ = experiments.test_sets(t.with_df(t.df.drop("fold")), 2, 50)
    assert len(dealt) == 2 and dealt[0] == dealt[1] == -(-train.df.count() // 200) > 8
    for x in (train, balanced):
        x.release()


def test_normal_columns_equal_the_arrays(spark):
    x = np.arange(-28, 29) / 10.0
    at = F.col("id") / 10.0 - 2.8
    got = np.array([tuple(r) for r in spark.range(57).orderBy("id").select(special.ndtr_expr(at), special.log_ndtr_expr(at), special.hazard_expr(at)).collect()]).T
    assert np.allclose(got, [special.ndtr(x), special.log_ndtr(x), special.hazard(x)], rtol=1e-9)


def test_a_kronecker_gp_by_slices_equals_the_whole_one(monkeypatch):
    rng = np.random.default_rng(5)
    dims, bell = (30, 12, 7), Kernel("rbf", [1.0])
    index = np.unique(np.stack([rng.integers(0, d, 300) for d in dims], 1), axis=0)
    u = [rng.normal(0, 0.5, (d, 3)) for d in dims]
    monkeypatch.setattr(kron, "SLICE_CELLS", 200)
    for binary, noise in ((False, 0.1), (True, 1.0)):
        y = np.ones(len(index)) if binary else rng.normal(size=len(index))
        dense = np.zeros(dims)
        dense[tuple(index.T)] = y
        target = np.where(dense > 0, 0.8, -0.8) if binary else dense
        _, want, alpha = kron.value_and_grads(u, bell, noise, target)
        z = kron.Slices(dims, index, y, binary)
        dirs, weights, got = kron.bell_step(z, u, bell, noise)
        f = target - noise * alpha
        assert len(z.ranges) > 10 and all(np.allclose(a, b, atol=0.02) for a, b in zip(got, want, strict=True))
        assert np.allclose(kron.mode_apply(dirs, weights), f, atol=1e-3)
        every = np.argwhere(np.ones(dims))
        assert np.allclose(kron.BellModel(tuple(u), tuple(dirs), weights, False)(every), f.ravel(), atol=1e-3)
        if binary:
            s, z.latent = np.where(dense > 0, 1.0, -1.0), (dirs, weights)
            assert np.allclose(np.concatenate([z.dense(*r) for r in z.ranges]), f + s * special.hazard(s * f), atol=1e-3)


def test_bells_of_many_rows_have_few_directions():
    u, bell = np.random.default_rng(6).normal(0, 0.5, (3000, 3)), Kernel("ard", [1.0, 1.2, 0.9])
    dirs, values = kron.bell_directions(u, bell)
    assert dirs.shape[1] < 600 and np.allclose(dirs.T @ dirs, np.eye(dirs.shape[1]), atol=1e-10)
    assert np.allclose((dirs[:200] * values) @ dirs.T, bell.gram(u[:200], u), atol=2e-8)


def test_every_method_has_a_value_in_tensors_of_many_cells(spark):
    cells = spark.range(400).select((F.col("id") * 7919 % 300).alias("i_1"), (F.col("id") * 31 % 200).alias("i_2"), (F.col("id") * 17 % 40).alias("i_3"), F.lit(1.0).alias("y")).distinct()
    t = TensorFrame(cells, (300, 200, 40), "binary")  # 2,400,000 cells
    rows = experiments.folds_table(t, ("krongp",), 2).collect()
    assert len(rows) == 2 and all(r.value is not None and 0 <= r.value <= 1 for r in rows)


def test_every_cell_of_a_sparse_tensor_is_in_one_fitted_sub_tensor(spark):
    t = TensorFrame(spark.range(600).select((F.col("id") * 7919 % 1500).alias("i_1"), (F.col("id") * 31 % 90).alias("i_2"), (F.col("id") * 577 % 2000).alias("i_3"), F.lit(1.0).alias("y")), (1500, 90, 2000), "binary")
    sides = experiments.side(t)
    blocks = kron.all_blocks(t, sides, 3).toPandas()
    assert len(blocks) == 600 and 600 / blocks["block_id"].nunique() > 4
    for k, (b, d) in enumerate(zip(sides, t.dims, strict=True), 1):
        step = (blocks.groupby("block_id")[f"i_{k}"].nunique() <= b).all()
        assert step and blocks[f"l_{k}"].between(0, b - 1).all() and blocks.groupby(["block_id", f"l_{k}"])[f"i_{k}"].nunique().max() == 1
    before = [np.random.default_rng(0).normal(0, 0.5, (1500, 2))]
    met = blocks["i_1"].unique()
    for method in ("blockkron", "mixkron"):
        u = experiments.MISSING_AS_ZERO[method](t, 2).factors[0]
        moved = (u != before[0]).any(1)
        assert moved[met].all() and moved.sum() == len(met)


def test_a_score_comes_from_a_fit_whose_bound_has_settled(spark, monkeypatch):
    cells = spark.range(80).select((F.col("id") % 10).alias("i_1"), (F.col("id") / 10).cast("long").alias("i_2"), F.sin(F.col("id") * 0.7).alias("y"))
    t, seen, fit = TensorFrame(cells, (10, 8)).distribute(1), [], experiments.fit
    monkeypatch.setattr(experiments, "fit", lambda *a, **how: seen.append(fit(*a, **how)) or seen[-1])
    experiments.score(t, t, t.df, "flexgp", 1, 4).count()
    values = [v for *_, v in seen[0].trace]
    assert len(values) > 10 and values[-1] - values[-2] < 1e-7 * max(1.0, abs(values[-2]))
    for u, v in zip(experiments.MISSING_AS_ZERO["cp"](t, 2).factors, multilinear.fit_cp(t, 2, 20).factors, strict=True):
        assert np.allclose(u, v)
    t.release()
