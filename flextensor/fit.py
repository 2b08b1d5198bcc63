"""Training: every evaluation is a few passes over cached cells and small algebra on the driver."""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame

from .bounds import em, gaussian, probit
from .exec import anchored, passes
from .exec.planner import Plan, choose
from .functions.special import hazard
from .model import ModelState, init_model
from .optim.gd import gd
from .optim.lbfgs import lbfgs
from .predict import predict
from .tensor import TensorFrame


def _keyed_data_gradient(t: TensorFrame, m: ModelState, a, how: str) -> np.ndarray:
    """The gradient with its factor part reduced by keys; the rest stays a key-free sum."""
    whole = passes.gradient_pass(t, replace(m, factors=tuple(m.factors)), a)
    n_u = sum(u.size for u in m.factors)
    whole[:n_u] = passes.keyed_to_vector(passes.keyed_gradient(t, m, a, combine=how == "keyed_combined"), m)
    return whole


def _maximised(t: TensorFrame, m: ModelState, tol: float, most: int) -> tuple[passes.Stats, np.ndarray]:
    """(sums, λ): the sums come from the pass of the first step."""
    lam = np.zeros(len(m.inducing)) if m.lam is None else m.lam
    s, first = passes.stats_lambda_pass(t, m, lam)
    return s, probit.fixed_point(t, m, s, lam, tol, most, first=first, last=False)[0]


def evaluate(t: TensorFrame, m: ModelState, reduce: str = "keyfree", lam_tol: float = 1e-6, lam_iter: int = 60) -> tuple[float, np.ndarray, ModelState]:
    """(bound, gradient by packed parameters, model with its λ): the collapsed bound, λ maximised inside for binary data."""
    if m.kind == "binary" and reduce == "keyfree":
        s, lam = _maximised(t, m, lam_tol, lam_iter)
        m = replace(m, lam=lam)
        a, dk = probit.adjoints(m, s, lam)
        g, log_phi = passes.gradient_log_pass(t, m, a)
        return probit.value(m, s, lam, log_phi), gaussian.to_logs(m, gaussian.finish(m, g, dk, None)), m
    s = passes.suff_stats(t, m)
    data = passes.gradient_pass if reduce == "keyfree" else lambda t, m, a: _keyed_data_gradient(t, m, a, reduce)
    if m.kind == "real":
        a, dk, db = gaussian.adjoints(m, s)
        return gaussian.value(m, s), gaussian.to_logs(m, gaussian.finish(m, data(t, m, a), dk, db)), m
    lam, _, trace = probit.fixed_point(t, m, s, m.lam, lam_tol, lam_iter)
    m = replace(m, lam=lam)
    a, dk = probit.adjoints(m, s, lam)
    return trace[-1], gaussian.to_logs(m, gaussian.finish(m, data(t, m, a), dk, None)), m


def evaluate_joint(t: TensorFrame, m: ModelState, lam: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(bound at λ, gradient by packed parameters, gradient by λ): nothing is maximised inside."""
    s = passes.suff_stats(t, m)
    g, log_phi = passes.lambda_pass(t, m, lam)
    a, dk = probit.adjoints(m, s, lam)
    grad = gaussian.to_logs(m, gaussian.finish(m, passes.gradient_pass(t, m, a), dk, None))
    return probit.value(m, s, lam, log_phi), grad, probit.lambda_gradient(m, lam, g)


def fit(
    t: TensorFrame,
    model: ModelState | None = None,
    ranks: int | list[int] = 3,
    p: int = 100,
    kernel: str = "ard",
    optimiser: str = "lbfgs",
    steps: int = 30,
    rate: float = 0.01,
    learn_kernel: bool = True,
    lambda_mode: str = "nested",
    inference: str = "collapsed",
    reduce: str = "keyfree",
    seed: int = 0,
    lam_iter: int = 60,
) -> ModelState:
    """A fitted model; ``trace`` holds (iteration, seconds, bound). λ is warm-started, with at most ``lam_iter`` steps an evaluation."""
    m = model or init_model(t, ranks, p, kernel, seed)
    began, trace = time.time(), []
    if inference == "em":
        return fit_em(t, m, steps, rate, learn_kernel)
    log = lambda i, x, v: trace.append((i + 1, time.time() - began, v))
    warm = {"lam": m.lam}
    size = len(m.pack(learn_kernel))

    def whole(g: np.ndarray) -> np.ndarray:
        return g if learn_kernel else g[:size]

    if m.kind == "binary" and lambda_mode == "joint":

        def f(v: np.ndarray):
            value, g, gl = evaluate_joint(t, m.unpack(v[:size], learn_kernel), v[size:])
            return value, np.concatenate([whole(g), gl])

        start = np.concatenate([m.pack(learn_kernel), np.zeros(len(m.inducing))])
    else:

        def f(v: np.ndarray):
            value, g, seen = evaluate(t, replace(m.unpack(v, learn_kernel), lam=warm["lam"]), reduce, lam_iter=lam_iter)
            warm["lam"] = seen.lam
            return value, whole(g)

        start = m.pack(learn_kernel)
    if optimiser == "lbfgs":
        x, _, values = lbfgs(f, start, steps, callback=log)
    else:
        x, _, values = gd(f, start, steps, rate, "backtrack" if optimiser == "gd" else optimiser.removeprefix("gd_"), callback=log)
    out = m.unpack(x[:size], learn_kernel)
    if m.kind == "binary":
        lam = x[size:] if lambda_mode == "joint" else _maximised(t, replace(out, lam=warm["lam"]), 1e-6, lam_iter)[1]
        out = replace(out, lam=lam)
    return replace(out, trace=[(0, 0.0, values[0]), *trace])


@dataclass(frozen=True)
class Fitted:
    """A model as the planner placed it: with all factors, or with one mode's in a table."""

    plan: Plan
    model: ModelState
    mode: int | None = None
    table: DataFrame | None = None

    def predict(self, train: TensorFrame, cells: DataFrame) -> DataFrame:
        if self.table is None:
            return predict(train, self.model, cells)
        return anchored.predict_anchored(train, self.model, self.table, self.mode, cells)


def fit_planned(t: TensorFrame, ranks: int | list[int] = 3, p: int = 100, task_bytes: float = 1e9, salts: int = 1, **how) -> Fitted:
    """Fits with the reduction and placement that the cost model chooses for this tensor: whole key-free gradients while the factors
    fit a task, the largest mode's factors as a table beside its cells beyond that, combined keyed gradients for several huge modes."""
    each = [ranks] * len(t.dims) if isinstance(ranks, int) else list(ranks)
    tasks = t.df.rdd.getNumPartitions()
    plan = choose(t.df.count(), list(t.dims), each, p, tasks, task_bytes)
    if plan.placement != "anchored":
        return Fitted(plan, fit(t, ranks=each, p=p, reduce="keyfree" if plan.reduce == "keyfree" else "keyed_combined", **how))
    mode = max(range(len(each)), key=lambda k: t.dims[k] * each[k])
    model, table = anchored.fit_anchored(t, mode, each, p, shards=tasks, salts=salts, **how)
    return Fitted(plan, model, mode, table)


def block_z(state, index: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Σ k E z, Σ E z², Σ entropy for q(z_j) centred at u_j = k_jᵀ w."""
    m, w = state
    k = m.kernel.gram(m.inputs(index), m.inducing)
    ez, ez2, h = em.z_moments(y, k @ w)
    return np.concatenate([k.T @ ez, [ez2.sum(), h.sum()]])


def block_z_gradient(state, index: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The M step's data gradient: cells bring E z in the place of y."""
    m, a, w = state
    k = m.kernel.gram(m.inputs(index), m.inducing)
    u = k @ w
    t = 2 * y - 1
    return passes.block_gradient((m, a), index, u + t * hazard(t * u))


def fit_em(t: TensorFrame, m: ModelState, steps: int = 30, rate: float = 0.01, learn_kernel: bool = True, inner: int = 3) -> ModelState:
    """Expectation-maximisation on the uncollapsed bounds: q(v) (and q(z), in turn) at fixed parameters, then one gradient step."""
    began, trace = time.time(), []
    p = len(m.inducing)
    size = len(m.pack(learn_kernel))
    w = np.zeros(p)
    for i in range(steps):
        s = passes.suff_stats(t, m)
        k = gaussian.kzz(m)
        if m.kind == "real":
            mean, cov = gaussian.optimal_qv(m, s, k)
            value = em.gaussian_value(m, s, mean, cov)
            a, dk, db = em.gaussian_adjoints(m, s, mean, cov)
            g = gaussian.finish(m, passes.gradient_pass(t, m, a), dk, db)
        else:
            mi = np.linalg.inv(k + s.g)
            for _ in range(inner):  # q(z) from q(v), then q(v) from q(z)
                z = passes.map_sum(t, p + 2, p, (m, w), block_z)
                hz = z[:p]
                w_old, w = w, mi @ hz
            mean, cov = k @ w, k @ mi @ k
            value = em.probit_value(m, s, hz, z[p], z[p + 1], mean, cov)
            sz = passes.Stats(s.g, hz, z[p], s.c, s.n)
            a, dk, _ = em.gaussian_adjoints(replace(m, beta=1.0), sz, mean, cov)
            data = passes.map_sum(t, sum(u.size for u in m.factors) + m.inducing.size + len(m.kernel.lengths) + 1, p, (m, a, w_old), block_z_gradient)
            g = gaussian.finish(m, data, dk, None)
        g = gaussian.to_logs(m, g)[:size]
        trace.append((i, time.time() - began, value))
        m = m.unpack(m.pack(learn_kernel) + rate * g / max(1.0, float(np.linalg.norm(g)) / 10), learn_kernel)
    if m.kind == "binary":
        m = replace(m, lam=w)
    return replace(m, trace=trace)


def trace_frame(t: TensorFrame, m: ModelState) -> DataFrame:
    return t.df.sparkSession.createDataFrame([(int(i), float(s), float(v)) for i, s, v in m.trace], "iteration int, seconds double, bound double")
