"""The engine on Spark: reductions agree, fits rise, planted structure is recovered, streams equal batches."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from flextensor import metrics, sampling, workloads
from flextensor.baselines import multilinear
from flextensor.bounds import gaussian
from flextensor.exec import passes
from flextensor.fit import fit
from flextensor.model import init_model, load_model, save_model
from flextensor.operators.tensor_queries import folded, sine_model
from flextensor.predict import predict
from flextensor.sources.tables import scratch
from flextensor.tensor import TensorFrame, build_tensor, dictionary, merge_cells


def test_reductions_agree(spark, data):
    t, m = folded(spark, data), sine_model()
    a = gaussian.adjoints(m, passes.suff_stats(t, m))[0]
    free = passes.gradient_pass(t, m, a)[: sum(u.size for u in m.factors)]
    for combine in (False, True):
        assert np.allclose(passes.keyed_to_vector(passes.keyed_gradient(t, m, a, combine), m), free, rtol=1e-9)
    raw = passes.keyed_raw_gradient(t, m, a)
    assert all(np.allclose(v, free[sum(len(u) for u in m.factors[: k - 1]) + i], rtol=1e-9) for (k, i), v in raw.items())


def test_statistics_do_not_depend_on_partitions(spark, data):
    t, m = folded(spark, data), sine_model()
    one, many = (passes.suff_stats(t.with_df(t.df.repartition(n)), m) for n in (1, 40))
    assert np.allclose(one.g, many.g) and np.allclose(one.h, many.h) and one.n == many.n


def test_fit_beats_the_mean_on_planted_values(spark, data):
    t = workloads.planted(folded(spark, data))
    folds = sampling.kfold(t)
    train, test = t.with_df(folds.where("fold > 0")).distribute(4), folds.where("fold = 0")
    m = fit(train, p=25, steps=25)
    values = [v for _, _, v in m.trace]
    assert values[-1] > values[0]
    scored = predict(train, m, test.select(*t.modes, "y"))
    mse = metrics.mse(scored).first()[0]
    var = test.agg(F.var_pop("y")).first()[0]
    assert mse < 0.5 * var
    cp = multilinear.predict_cells(multilinear.fit_cp(train, 3, 10, observed_only=True), test.select(*t.modes, "y"), t.modes)
    assert mse < metrics.mse(cp).first()[0] * 1.5


def test_model_round_trip(spark, data):
    m = init_model(folded(spark, data), 2, 6, "ard")
    path = scratch(spark, "model")
    save_model(spark, m, path)
    n = load_model(spark, path)
    assert all(np.array_equal(a, b) for a, b in zip(m.factors, n.factors)) and np.array_equal(m.inducing, n.inducing) and np.array_equal(m.kernel.lengths, n.kernel.lengths)


def test_cp_recovers_a_planted_tensor(spark):
    rng = np.random.default_rng(0)
    u = [rng.normal(size=(d, 2)) for d in (6, 5, 4)]
    y = np.einsum("ar,br,cr->abc", *u)
    rows = [(a, b, c, float(y[a, b, c])) for a in range(6) for b in range(5) for c in range(4)]
    t = TensorFrame(spark.createDataFrame(rows, "i_1 long, i_2 long, i_3 long, y double"), (6, 5, 4)).distribute(3)
    got = multilinear.fit_cp(t, 2, 40, seed=1)
    assert np.allclose(got(np.array([r[:3] for r in rows])), [r[3] for r in rows], atol=0.05)
    for model in (multilinear.fit_tucker(t, 2), multilinear.fit_hosvd(t, 2)):
        assert np.allclose(model(np.array([r[:3] for r in rows])), [r[3] for r in rows], atol=1e-6)


def test_balanced_zeros_are_zeros(spark, data):
    from flextensor.operators.tensor_queries import clicks

    t = clicks(spark, data)
    held = sampling.enumerated_zeros(t).where("i_1 = 0")
    b = sampling.balanced_sample(t, exclude=held).df
    n = {r.origin: r["count"] for r in b.groupBy("origin").count().collect()}
    assert n["obs"] == n["zero"]
    zeros = b.where("origin = 'zero'")
    assert zeros.join(t.df, t.modes, "left_semi").isEmpty() and zeros.where("i_1 = 0").isEmpty()
    with pytest.raises(ValueError):
        sampling.balanced_sample(TensorFrame(t.df, (1, 1, 1), "binary"))


def test_dictionaries_agree_and_nulls_are_unobserved(spark):
    rows = [("b", 1, 2.0), ("a", 2, 3.0), ("b", 1, 4.0), (None, 1, 5.0), ("c", 3, None)]
    df = spark.createDataFrame(rows, "x string, z int, v double")
    cells = merge_cells(df, ["x", "z"], F.col("v"), "sum")
    assert sorted(map(tuple, cells.collect())) == [("a", 2, 3.0), ("b", 1, 6.0)]
    assert sorted(map(tuple, dictionary(cells, "m_1", True).collect())) == sorted(map(tuple, dictionary(cells, "m_1").collect()))
    assert build_tensor(df, ["x", "z"], F.col("v")).dims == (2, 2)


def test_auc(spark):
    df = lambda rows: spark.createDataFrame(rows, "y double, score double")
    assert metrics.auc(df([(1.0, 0.9), (0.0, 0.1), (1.0, 0.5), (0.0, 0.5)])).first()[0] == 0.875
    assert metrics.auc(df([(1.0, 0.5), (0.0, 0.5)])).first()[0] == 0.5
    assert metrics.auc(df([(1.0, 0.5)])).first()[0] is None
    r = metrics.auc_binned(df([(1.0, 0.9), (0.0, 0.1), (1.0, 0.5), (0.0, 0.5)])).first()
    assert abs(r.auc - 0.875) <= r.error_bound + 1e-12


def test_paired_t(spark):
    rows = [(m, f, v) for m, vs in (("a", (1.0, 2.0, 3.0, 4.1)), ("b", (0.5, 1.4, 2.7, 3.2))) for f, v in enumerate(vs)]
    r = metrics.paired_t(spark.createDataFrame(rows, "method string, fold int, value double"), "a", "b").first()
    assert r.t > 0 and 0 < r.p < 0.05 and r.df == 3


def test_plans(spark, data):
    text = workloads.load_table(spark, data, "lineitem", ["l_suppkey"]).where("l_suppkey > 5")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_suppkey), GreaterThan(l_suppkey,5)]" in text and "ReadSchema: struct<l_suppkey:bigint>" in text
    t = folded(spark, data).distribute(2)
    m = sine_model()
    a = gaussian.adjoints(m, passes.suff_stats(t, m))[0]
    assert "Exchange" in passes.keyed_gradient(t, m, a)._jdf.queryExecution().toString()


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 1
    assert set(e.oracle_sql()) <= set(e.queries())


def test_anchored_placement_equals_the_dense_path(spark, data):
    from flextensor.exec import anchored

    t, m = folded(spark, data), sine_model()
    s = passes.suff_stats(t, m)
    a = gaussian.adjoints(m, s)[0]
    whole = passes.gradient_pass(t, m, a)
    for salts in (1, 3):
        table = anchored.shard_factors(t, m, 0)
        got = anchored.anchored_stats(t, m, table, 0, 5, salts)
        assert np.allclose(got.g, s.g) and np.allclose(got.h, s.h) and got.n == s.n
        rest, own = anchored.anchored_gradient(t, m, a, table, 0, 5, salts)
        assert np.allclose(rest, whole[7:])
        assert all(np.allclose(r.grad, whole[r.idx]) for r in own.collect())
        moved = {r.idx: r.factor[0] for r in anchored.ascend(table, own, 0.1).collect()}
        assert all(np.isclose(moved[i], m.factors[0][i, 0] + 0.1 * (whole[i] - m.factors[0][i, 0])) for i in range(7))
        assert np.isclose(anchored.table_dot(own, own), (whole[:7] ** 2).sum())


def test_mini_batches_are_unbiased(spark, data):
    from flextensor.exec import anchored

    t, m = folded(spark, data), sine_model()
    full = passes.suff_stats(t, m)
    parts = [anchored.scaled(passes.suff_stats(anchored.mini_batch(t, 0.5, i), m), 0.5) for i in range(6)]
    assert abs(np.mean([p.n for p in parts]) / full.n - 1) < 0.2


def test_test_sets_take_the_smallest_hashes_of_many_cells(spark, data):
    from pyspark.sql import Window

    cells = spark.range(60_000).select((F.col("id") % 100).alias("i_1"), (F.col("id") / 100).cast("long").alias("i_2"), F.lit(1.0).alias("y"))
    _, tests = sampling.train_and_tests(TensorFrame(cells, (100, 50_000), "binary"), reps=50)
    held = cells.where(sampling.portable_hash(F.col("i_1"), F.col("i_2"), seed=5) >= int(sampling.MODULUS * 0.8))
    each = held.crossJoin(spark.range(50).select(F.col("id").cast("int").alias("rep")))
    rank = F.row_number().over(Window.partitionBy("rep").orderBy(sampling.portable_hash(F.col("rep"), F.col("i_1"), F.col("i_2"), seed=6), "i_1", "i_2"))
    want = each.withColumn("rank", rank).where("rank <= 200").select("rep", "i_1", "i_2", "y")
    got = tests.where("y = 1")
    assert got.count() == want.count() == 50 * 200 and got.exceptAll(want).isEmpty()


def test_balanced_zeros_of_given_attempts_on_a_nearly_full_grid(spark):
    cells = spark.range(90).select((F.col("id") % 10).alias("i_1"), (F.col("id") / 10).cast("long").alias("i_2"), F.lit(1.0).alias("y"))
    t = TensorFrame(cells, (10, 10), "binary")
    zeros = sampling.balanced_sample(t, attempts=8).df.where("origin = 'zero'")
    assert 0 < zeros.count() <= 10 and zeros.where("i_2 < 9").isEmpty() and zeros.exceptAll(zeros.distinct()).isEmpty()
    some = sampling.empty_cells(t, 2, 50, attempts=500)
    assert 0 < some.count() <= 20 and some.where("i_2 < 9").isEmpty()
    with pytest.raises(ValueError):
        sampling.balanced_sample(t)


def test_whole_tables_of_streams_stay_off_the_driver(spark, data):
    from flextensor.streaming import events as st

    def sinks():
        return {x.name for x in spark.catalog.listTables() if x.name.startswith("sink_")}

    before = sinks()
    got = st.drain(st.sessions(st.event_stream(spark, data)), "complete")
    assert sinks() == before and len(got.inputFiles()) > 0
    want = st.sessions(st.batch_events(spark, data))
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_given_inputs_of_more_rows_than_exact_inference_takes(spark, tmp_path):
    from flextensor.functions.kernels import Kernel
    from flextensor.operators import tensor_queries

    at = [((F.col("id") * m % 101) / 100.0 - 0.5).cast("float") for m in (7, 13, 29, 31, 37, 41, 43, 47)]
    spark.range(3_500).select(F.col("id").alias("vec_id"), F.array(*at).alias("embedding"), F.lit(0).alias("label")).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert tuple(tensor_queries.TABLE["q_w15_given_inputs"][0](spark, str(tmp_path)).first()) == (3_500, True, True)
    e = workloads.embedding_inputs(spark, str(tmp_path))
    rows = e.select("x", "y").persist()
    assert not tensor_queries.under_exact(rows, e, Kernel("rbf", [0.5]), 4.0, 1e9, 3_500)
    rows.unpersist()


@pytest.mark.parametrize("name", ["q_cost_model", "q_datasource", "q_gain", "q_map", "q_phi", "q_sql_surface", "q_udf_scalar"])
def test_results_come_from_the_events(spark, data, tmp_path, name):
    from flextensor.queries import QUERIES

    events = spark.read.parquet(f"{data}/events.parquet")
    events.where("event_id % 3 = 0").write.parquet(f"{tmp_path}/events.parquet")
    assert QUERIES[name](spark, data).exceptAll(QUERIES[name](spark, str(tmp_path))).count() > 0
