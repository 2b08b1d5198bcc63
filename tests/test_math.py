"""The golden example, bounds against brute force, gradients by finite differences, special functions, optimisers."""

from dataclasses import replace

import numpy as np
import pytest

from flextensor.baselines import kron
from flextensor.bounds import em, exact, gaussian, probit
from flextensor.exec import passes
from flextensor.exec.planner import choose, cost_model
from flextensor.functions import special
from flextensor.functions.kernels import NAMES, Kernel
from flextensor.model import ModelState
from flextensor.optim.gd import gd
from flextensor.optim.lbfgs import lbfgs

I = np.array([[0, 0, 0], [0, 1, 1], [1, 0, 1], [1, 1, 0]])  # noqa: E741
Y = np.array([1.0, -0.5, 0.25, 2.0])
YB = np.array([1.0, 0.0, 0.0, 1.0])


def golden(kind="real"):
    u = (np.array([[0.5], [-0.5]]), np.array([[0.25], [-0.75]]), np.array([[1.0], [0.0]]))
    return ModelState(u, np.array([[0.0, 0, 0], [1, -1, 1]]), Kernel("ard", np.ones(3)), 2.0 if kind == "real" else 1.0, np.zeros(2), kind)


def stats(m, index=I, y=Y):
    return passes.Stats.unpack(passes.block_stats(m, index, y), len(m.inducing))


def fixed_point(m, index, y, k, steps=200):
    s, lam = stats(m, index, y), np.zeros(len(k))
    trace = []
    for _ in range(steps):
        v = passes.block_lambda((m, lam), index, y)
        trace.append(probit.value(m, s, lam, v[-1], k))
        lam = np.linalg.solve(k + s.g, s.g @ lam + v[:-1])
    return lam, trace


def test_golden_continuous():
    m = golden()
    s, k = stats(m), gaussian.kzz(m, False)
    assert np.allclose(s.g, [[1.607754800211, 0.759449592628], [0.759449592628, 0.539532785036]], atol=1e-11)
    assert np.allclose([s.s, s.c, *s.h], [5.3125, 4.0, 1.207630739456, 0.796506046431], atol=1e-11)
    assert gaussian.value(m, s, k) == pytest.approx(-10.83758730625771, abs=1e-10)
    a, dk, db = gaussian.adjoints(m, s, k)
    g = gaussian.finish(m, passes.block_gradient((m, a), I, Y), dk, db)
    want = [-0.8374058435, 2.192663428098, -1.094028245463, 1.364817036535, -2.434847939521, -0.224553274378, -0.641365222349, -0.117459307807, 1.254762249691, -0.713892362249, 0.346670516735, 0.404638964208, 1.728926998047, 1.018790355502, 1.030208975313, -2.4044724415521177, -2.447432105904676]
    assert np.allclose(g, want, atol=1e-9)
    mi = np.linalg.inv(k + 2 * s.g)
    kx = m.kernel.gram(m.inputs(np.array([[0, 0, 1]])), m.inducing)[0]
    assert 2 * kx @ mi @ s.h == pytest.approx(0.44261772147, abs=1e-9)
    assert 1 - kx @ (np.linalg.inv(k) - mi) @ kx == pytest.approx(0.4474913695449213, abs=1e-9)


def test_golden_binary():
    m = golden("binary")
    s, k = stats(m, I, YB), gaussian.kzz(m, False)
    v = passes.block_lambda((m, np.zeros(2)), I, YB)
    assert probit.value(m, s, np.zeros(2), v[-1], k) == pytest.approx(-5.466509725483328, abs=1e-10)
    assert np.allclose(v[:-1], [-0.477660971715, 0.087571488687], atol=1e-10)
    lam, trace = fixed_point(m, I, YB, k)
    assert trace[1] == pytest.approx(-5.382486814176128, abs=1e-9)
    assert np.allclose(lam, [-0.320688455108, 0.233242238176], atol=1e-9)
    assert trace[-1] == pytest.approx(-5.380026447958465, abs=1e-9)
    assert all(b >= a - 1e-12 for a, b in zip(trace, trace[1:]))


def toy(kernel="ard", n=12, p=4, seed=0, kind="real"):
    rng = np.random.default_rng(seed)
    dims = (4, 3, 2)
    u = tuple(rng.normal(0, 0.7, (d, 2)) for d in dims)
    index = np.stack([rng.integers(0, d, n) for d in dims], 1)
    size = 6 if kernel in ("ard", "linear") else 1
    m = ModelState(u, rng.normal(0, 0.7, (p, 6)), Kernel(kernel, rng.uniform(0.8, 1.5, size), 1.3), 1.7 if kind == "real" else 1.0, np.zeros(p), kind)
    y = rng.normal(0, 1, n) if kind == "real" else (rng.random(n) > 0.5).astype(float)
    return m, index, y


@pytest.mark.parametrize("kernel", NAMES)
def test_gradient_by_differences(kernel):
    m, index, y = toy(kernel)
    if kernel == "linear":
        m = replace(m, inducing=m.inducing)

    def value(v):
        x = m.unpack(v)
        return gaussian.value(x, stats(x, index, y))

    v0 = m.pack()
    a, dk, db = gaussian.adjoints(m, stats(m, index, y))
    g = gaussian.to_logs(m, gaussian.finish(m, passes.block_gradient((m, a), index, y), dk, db))
    for j in np.random.default_rng(1).choice(len(v0), 14, replace=False):
        e = np.zeros_like(v0)
        e[j] = 1e-5
        assert (value(v0 + e) - value(v0 - e)) / 2e-5 == pytest.approx(g[j], rel=2e-4, abs=2e-5)


def test_binary_gradient_by_differences():
    m, index, y = toy(kind="binary")

    def at(v):
        x = m.unpack(v)
        lam, trace = fixed_point(x, index, y, gaussian.kzz(x), 300)
        return x, lam, trace[-1]

    v0 = m.pack()
    x, lam, _ = at(v0)
    a, dk = probit.adjoints(x, stats(x, index, y), lam)
    g = gaussian.to_logs(x, gaussian.finish(x, passes.block_gradient((x, a), index, y), dk, None))
    for j in (0, 5, 17, 20, 30, len(v0) - 1):
        e = np.zeros_like(v0)
        e[j] = 1e-4
        assert (at(v0 + e)[2] - at(v0 - e)[2]) / 2e-4 == pytest.approx(g[j], rel=1e-3, abs=1e-5)


def test_em_step_gradient_by_differences():
    m, index, y = toy()
    mean, cov = gaussian.optimal_qv(m, stats(m, index, y))

    def value(v):
        x = m.unpack(v)
        return em.gaussian_value(x, stats(x, index, y), mean, cov)

    v0 = m.pack()
    a, dk, db = em.gaussian_adjoints(m, stats(m, index, y), mean, cov)
    g = gaussian.to_logs(m, gaussian.finish(m, passes.block_gradient((m, a), index, y), dk, db))
    for j in range(0, len(v0), 4):
        e = np.zeros_like(v0)
        e[j] = 1e-5
        assert (value(v0 + e) - value(v0 - e)) / 2e-5 == pytest.approx(g[j], rel=2e-4, abs=2e-5)


def test_bounds_and_exact():
    m, index, y = toy(p=6)
    s = stats(m, index, y)
    bound = gaussian.value(m, s)
    x = m.inputs(index)
    k = gaussian.kzz(m)
    kx = m.kernel.gram(x, m.inducing)
    q = kx @ np.linalg.solve(k, kx.T)
    nystrom = exact.log_normal(y, q + np.eye(len(y)) / m.beta) - 0.5 * m.beta * (s.c - np.trace(q)) + gaussian.prior(m)
    assert bound == pytest.approx(nystrom, abs=1e-9)
    assert bound <= exact.exact_log_marginal(m, index, y) + gaussian.prior(m) + 1e-9
    full = replace(m, inducing=np.unique(x, axis=0))
    assert gaussian.value(full, stats(full, index, y)) == pytest.approx(exact.exact_log_marginal(m, index, y) + gaussian.prior(m), abs=1e-3)
    mean, cov = gaussian.optimal_qv(m, s)
    assert em.gaussian_value(m, s, mean, cov) == pytest.approx(bound, abs=1e-9)
    assert em.gaussian_value(m, s, mean + 0.1, cov) < bound
    assert em.gaussian_value(m, s, mean, 1.3 * cov) < bound


def test_probit_bounds_agree():
    m, index, y = toy(kind="binary")
    k = gaussian.kzz(m)
    lam, trace = fixed_point(m, index, y, k, 400)
    s, kx = stats(m, index, y), m.kernel.gram(m.inputs(index), m.inducing)
    u = kx @ lam
    assert probit.mid_value(m, kx, s.c, y, u, k) == pytest.approx(trace[-1], abs=1e-8)
    ez, ez2, ent = em.z_moments(y, u)
    mi = np.linalg.inv(k + s.g)
    hz = kx.T @ ez
    assert em.probit_value(m, s, hz, ez2.sum(), ent.sum(), k @ mi @ hz, k @ mi @ k) == pytest.approx(trace[-1], abs=1e-8)
    assert np.allclose(k @ lam, passes.block_lambda((m, lam), index, y)[:-1], atol=1e-8)
    a, w = k + s.g, np.arange(1.0, 5)
    best = np.linalg.solve(a, w)
    assert probit.conjugate_lower(a, w, best) == pytest.approx(0.5 * w @ best)
    assert probit.conjugate_lower(a, w, best + 0.1) < 0.5 * w @ best


def test_exact_joints():
    m, index, y = toy(kind="binary")
    f = exact.prior_draw(m, index)
    z = np.where(y > 0, 0.5, -0.5)
    assert np.isfinite(exact.log_joint_probit(m, index, y, z, f))
    assert exact.log_joint_probit(m, index, y, -z, f) == -np.inf
    assert np.isfinite(exact.log_joint_gaussian(m, index, z, f))


def test_special():
    assert special.ndtr(1.959963984540054) == pytest.approx(0.975, abs=1e-14)
    assert special.ndtr(-5.0) == pytest.approx(2.8665157187919333e-07, rel=1e-12)
    assert special.log_ndtr(-40.0) == pytest.approx(-804.6084420137538, rel=1e-12)
    x = np.linspace(-9, 6, 400)
    assert np.all(np.diff(special.log_ndtr(x)) > 0) and np.all(np.diff(special.hazard(x)) < 0)
    assert special.hazard(-5.0001) == pytest.approx(special.hazard(-4.9999), rel=1e-3)
    assert special.student_p(2.7764451051977987, 4) == pytest.approx(0.05, abs=1e-9)


def test_kronecker_identity():
    """A product kernel on the full grid is the Kronecker product of the modes' grams."""
    rng = np.random.default_rng(2)
    u = [rng.normal(size=(d, 2)) for d in (3, 2, 4)]
    grid = np.stack(np.meshgrid(*map(np.arange, (3, 2, 4)), indexing="ij"), -1).reshape(-1, 3)
    m = ModelState(tuple(u), np.zeros((1, 6)), Kernel("rbf", [1.1]))
    x = m.inputs(grid)
    grams = [m.kernel.gram(a, a) for a in u]
    assert np.allclose(m.kernel.gram(x, x), np.kron(np.kron(*grams[:2]), grams[2]))
    y = rng.normal(size=(3, 2, 4))
    value, grads, alpha = kron.value_and_grads(u, Kernel("rbf", [1.1]), 0.3, y)
    k = np.kron(np.kron(*[g + 1e-6 * np.eye(len(g)) for g in grams[:2]]), grams[2] + 1e-6 * np.eye(4))
    assert value + 0.5 * sum((a * a).sum() for a in u) == pytest.approx(exact.log_normal(y.ravel(), k + 0.3 * np.eye(24)), abs=1e-8)
    for i in range(3):
        v = [a.copy() for a in u]
        v[i][1, 0] += 1e-5
        hi = kron.value_and_grads(v, Kernel("rbf", [1.1]), 0.3, y)[0]
        v[i][1, 0] -= 2e-5
        assert (hi - kron.value_and_grads(v, Kernel("rbf", [1.1]), 0.3, y)[0]) / 2e-5 == pytest.approx(grads[i][1, 0], rel=1e-4, abs=1e-6)


def test_optimisers():
    a = np.diag([1.0, 10.0, 100.0])
    f = lambda x: (-0.5 * x @ a @ x + x.sum(), 1 - a @ x)
    x, _, trace = lbfgs(f, np.ones(3), 60)
    assert np.allclose(x, [1, 0.1, 0.01], atol=1e-3) and trace[-1] >= trace[0]
    x, _, trace = gd(f, np.ones(3), 400, 0.01)
    assert np.allclose(x, [1, 0.1, 0.01], atol=5e-2) and all(b >= a for a, b in zip(trace, trace[1:]))
    for s in ("constant", "decay"):
        assert gd(f, np.ones(3), 100, 0.01, s)[1] > f(np.ones(3))[0]


def test_planner():
    assert choose(10**6, [1000, 100, 1000], [3, 3, 3], 100, 50).reduce == "keyfree"
    assert choose(10**12, [10**9, 1000, 1000], [3, 3, 3], 100, 10**5).placement == "anchored"
    assert choose(10**12, [10**9, 10**9, 1000], [3, 3, 3], 100, 10**5).reduce == "keyed"
    assert cost_model(100, [10, 10], [2, 2], 5, 4).flops_per_task == 100 * 25 / 4


def test_cold_index_has_prior_mean():
    assert np.allclose(golden().inputs(np.array([[5, 0, -1]])), [[0, 0.25, 0]])


def test_an_interval_holds_the_exact_log_marginal():
    from flextensor.bounds import exact
    from flextensor.exec.passes import Stats
    from flextensor.functions.kernels import Kernel

    rng = np.random.default_rng(4)
    x, beta, kernel = rng.normal(0, 0.15, (400, 3)), 4.0, Kernel("rbf", [0.5])
    y = np.sin(5 * x[:, 0]) + rng.normal(0, 0.5, 400)
    want = exact.log_normal(y, kernel.gram(x, x) + np.eye(400) / beta)
    wide = []
    for p in (10, 60, 200):
        z = x[:p]
        k = kernel.gram(x, z)
        s = Stats(k.T @ k, k.T @ y, float(y @ y), float(kernel.diag(x).sum()), 400)
        low, high = exact.log_marginal_between(s, kernel.gram(z, z) + 1e-6 * np.eye(p), beta)
        assert low <= want <= high
        wide.append(high - low)
    assert wide[0] > wide[1] > wide[2] and wide[2] < 2
