"""Objectives, solvers, trainers and bounds on arrays."""

import itertools
import math

import numpy as np
import pytest

from gaptide.functions import objectives as O
from gaptide.operators import metrics as M
from gaptide.operators import select as S
from gaptide.operators import solve as V
from gaptide.operators import theory as T
from gaptide.operators import train as R

rng = np.random.default_rng(3)
N, D = 60, 25
X = rng.standard_normal((N, D))
X /= np.linalg.norm(X, axis=1)[:, None]
A0 = np.where(rng.random(N) < 0.1, rng.standard_normal(N), 0)
B = A0 @ X + 0.01 * rng.standard_normal(D)
SIGN = np.sign(X @ rng.standard_normal(D))


def problems():
    lam = 0.1 * np.abs(X @ B).max()
    signed = X * SIGN[:, None]
    return [
        (O.RidgePrimal(0.5, B), X, None), (O.LassoBoxed(lam, B), X, None), (O.ElasticNet(lam, B, 0.4), X, None), (O.LogisticL1(0.3, np.sign(B)), X, None),
        (O.RidgeDual(0.5), X, SIGN), (O.HingeSvmDual(1.0), signed, None), (O.SquaredHingeSvmDual(1.0), signed, None), (O.LogisticDual(1.0), signed, None),
    ]


IDS = [p[0].name for p in problems()]


def feasible(obj, n):
    a = rng.uniform(-0.5, 0.5, n)
    return np.abs(a) if isinstance(obj, O.DualObjective) and not isinstance(obj, O.RidgeDual) else a


@pytest.mark.parametrize("obj,x,y", problems(), ids=IDS)
def test_gaps_bound_suboptimality(obj, x, y):
    cols = R.LocalColumns(x, y)
    best, _, left = R.optimum(cols, obj, 3000, 1e-11)
    assert left < 1e-6
    for _ in range(20):
        a = feasible(obj, len(x))
        v = a @ x
        gaps = obj.gap(a, x @ obj.grad(v), cols.y)
        assert (gaps >= 0).all()
        assert gaps.sum() >= O.total(obj, v, a, cols.y) - best - 1e-7
        pair = obj.f(v) + obj.f_conj(obj.grad(v)) + float(np.sum(obj.g(a, cols.y) + obj.g_conj(-(x @ obj.grad(v)), cols.y)))
        assert math.isclose(pair, gaps.sum(), rel_tol=1e-6, abs_tol=1e-6)


@pytest.mark.parametrize("obj,x,y", problems(), ids=IDS)
@pytest.mark.parametrize("rule", ["gap_memory", "fresh_gap", "random", "sequential"])
def test_objective_never_rises(obj, x, y, rule):
    r = R.train(R.LocalColumns(x, y), obj, rule, rounds=8, init="first_pass")
    values = [row["objective"] for row in r.log]
    assert all(b <= a + 1e-9 * max(1, abs(a)) for a, b in zip(values, values[1:]))


@pytest.mark.parametrize("obj,x,y", problems(), ids=IDS)
def test_local_model_is_monotone_and_exact_for_quadratic_f(obj, x, y):
    a, v, y = np.zeros(N), np.zeros(D), 0.0 if y is None else y
    s = V.passes(x, a, v, obj, y, 2, seed=1, model=True)
    assert O.total(obj, v + s.dv, a + s.delta, y) <= O.total(obj, v, a, y) + 1e-9
    if obj.quadratic:
        np.testing.assert_allclose(V.passes(x, a, v, obj, y, 2, seed=1).delta, s.delta)
    wide = V.guarded(x, a, v, obj, y, k=1, width=16)
    assert O.total(obj, v + wide.dv, a + wide.delta, y) <= O.total(obj, v, a, y) + 1e-9
    near = V.proximal(x, a, v, obj, y)
    assert O.total(obj, v + near.dv, a + near.delta, y) <= O.total(obj, v, a, y) + 1e-9


def test_per_round_bound_for_strong_convexity():
    for obj, x, y in problems():
        if not obj.strong or obj.name == "logit_dual":
            continue
        cols = R.LocalColumns(x, y)
        best, _, _ = R.optimum(cols, obj, 3000, 1e-12)
        r = R.train(cols, obj, "fresh_gap", rounds=6, best=best, trace=True, theta=True)
        for p, q, block in zip(r.log, r.log[1:], r.blocks):
            if p["subopt"] > 1e-9:
                assert q["subopt"] <= T.step_bound(p["subopt"], q["theta"], q["rho"], obj.smooth, obj.strong, V.op_norm_sq(x[block]), len(block), N) * (1 + 1e-9) + 1e-10


def test_per_round_bound_for_bounded_support():
    lam = 0.1 * np.abs(X @ B).max()
    for obj, x in ((O.LassoBoxed(lam, B, box=3.0), X), (O.HingeSvmDual(1.0), X * SIGN[:, None])):
        cols = R.LocalColumns(x)
        best, _, _ = R.optimum(cols, obj, 3000, 1e-12)
        r = R.train(cols, obj, "fresh_gap", rounds=6, best=best, trace=True, theta=True)
        for p, q, block in zip(r.log, r.log[1:], r.blocks):
            g = T.gamma(obj.smooth, obj.bound, V.op_norm_sq(x[block]))
            assert q["subopt"] <= T.step_bound_bounded(p["subopt"], q["theta"], q["rho"], g, len(block), N) * (1 + 1e-9) + 1e-9


def test_rates_are_consistent():
    assert math.isclose(T.rate_strong(2.0, 1, 0.7, 1, 0.5, 3.0, 25, 100), T.step_bound(2.0, 0.7, 1.0, 1, 0.5, 3.0, 25, 100))
    t = T.rounds_needed_strong(1e-4, 0.7, 1, 0.5, 3.0, 25, 100)
    assert T.rate_strong(1.0, t, 0.7, 1, 0.5, 3.0, 25, 100) <= 1e-4 < T.rate_strong(1.0, t - 1, 0.7, 1, 0.5, 3.0, 25, 100)
    g = T.gamma(1, 2, 3)
    start = T.t0(50.0, 0.7, g, 25, 100)
    assert T.rate_bounded(50.0, math.ceil(start) + 5, 0.7, g, 25, 100) < T.rate_bounded(50.0, math.ceil(start), 0.7, g, 25, 100)


def test_tiny_answers():
    x, b = np.eye(3), np.array([3.0, 1.0, 0.2])
    np.testing.assert_allclose(R.plain_scd(R.LocalColumns(x), O.LassoBoxed(1.0, b), 3).alpha, [2, 0, 0])
    np.testing.assert_allclose(R.plain_scd(R.LocalColumns(x), O.RidgePrimal(1.0, b), 3).alpha, b / 2)


def test_ridge_equals_normal_equations_and_whole_block_is_one_round():
    want = np.linalg.solve(X @ X.T + 0.5 * np.eye(N), X @ B)
    r = R.train(R.LocalColumns(X), O.RidgePrimal(0.5, B), "fresh_gap", m=N, rounds=1, solver=V.exact)
    np.testing.assert_allclose(r.alpha, want, atol=1e-9)


def test_lasso_and_svm_optimality_conditions():
    lam = 0.2 * np.abs(X @ B).max()
    _, r, _ = R.optimum(R.LocalColumns(X), O.LassoBoxed(lam, B), 4000, 1e-13)
    u = X @ (r.v - B)
    assert (np.abs(u) <= lam + 1e-6).all()
    np.testing.assert_allclose(u[np.abs(r.alpha) > 1e-8], -lam * np.sign(r.alpha[np.abs(r.alpha) > 1e-8]), atol=1e-5)
    z = X * SIGN[:, None]
    _, r, _ = R.optimum(R.LocalColumns(z), O.HingeSvmDual(1.0), 4000, 1e-13)
    inner = (r.alpha > 1e-6) & (r.alpha < 1 - 1e-6)
    np.testing.assert_allclose((z @ r.v)[inner], 1.0, atol=1e-4)


def test_single_exact_coordinate_is_coordinate_descent():
    obj, a, v = O.RidgePrimal(0.5, B), np.zeros(N), np.zeros(D)
    r = R.train(R.LocalColumns(X), obj, "single", m=1, rounds=7, k=1)
    for _ in range(7):
        i = int(np.argmax(obj.gap(a, X @ obj.grad(v))))
        d = float(obj.step(a[i], X[i] @ obj.grad(v), X[i] @ X[i]))
        a[i] += d
        v += d * X[i]
    np.testing.assert_allclose(r.alpha, a)


def test_fresh_block_is_the_best_of_all_and_share_is_bounded():
    gaps = rng.random(12)
    block = S.select_np("fresh_gap", 4, 0, 0, {"gap": gaps, "z": gaps})
    assert math.isclose(gaps[block].sum(), max(gaps[list(c)].sum() for c in itertools.combinations(range(12), 4)))
    assert 1 <= M.rho(gaps, block) <= 12 / 4
    assert math.isclose(M.rho(np.eye(12)[3], np.array([1, 2, 3, 4])), 3.0)
    assert M.rho(np.ones(12), block) == 1.0 and M.rho(np.zeros(12), block) == 1.0
    shares = [M.rho(gaps, S.select_np("random", 4, t, 5, {"z": gaps})) for t in range(300)]
    assert abs(np.mean(shares) - 1) < 0.05


def test_schemes_reach_one_optimum():
    lam = 0.1 * np.abs(X @ B).max()
    obj, cols = O.LassoBoxed(lam, B), R.LocalColumns(X)
    best, _, _ = R.optimum(cols, obj)
    for rule in ("gap_memory", "fresh_gap", "random", "sequential", "importance_norm", "importance_norm2", "importance_gap", "uniform_batches", "sticky"):
        r = R.train(cols, obj, rule, rounds=150, best=best, tolerance=1e-5, init="first_pass")
        assert r.log[-1]["subopt"] <= 1e-5 * r.log[0]["subopt"], rule
    r = R.tiered_train(cols, obj, rounds=60, best=best, tolerance=1e-4, init="first_pass")
    assert r.log[-1]["subopt"] <= 1e-4 * r.log[0]["subopt"]


def test_memory_at_full_refresh_is_one_round_late():
    obj, cols = O.RidgePrimal(0.5, B), R.LocalColumns(X)
    r = R.train(cols, obj, rounds=3, init="first_pass", refresh_fraction=1.0)
    before = R.train(cols, obj, rounds=2, init="first_pass", refresh_fraction=1.0)
    np.testing.assert_allclose(r.z, obj.gap(before.alpha, X @ obj.grad(before.v)))


def test_swaps():
    obj, cols = O.RidgePrimal(0.5, B), R.LocalColumns(X)
    r = R.train(cols, obj, "sequential", fraction=0.25, rounds=6)
    assert all(row["swaps"] == 15 for row in r.log[1:])
    lam = 0.1 * np.abs(X @ B).max()
    r = R.train(cols, O.LassoBoxed(lam, B), rounds=30, init="first_pass")
    swaps = [row["swaps"] for row in r.log[2:]]
    assert sum(swaps[-10:]) <= sum(swaps[:10])


def test_refresh_modes_and_overlap():
    obj, cols = O.RidgePrimal(0.5, B), R.LocalColumns(X)
    for mode in ("uniform", "oldest_first", "bucket"):
        assert R.train(cols, obj, rounds=4, refresh_fraction=0.3, refresh_mode=mode).log[-1]["refreshed"] > 0
    best, _, _ = R.optimum(cols, obj)
    r = R.train(cols, obj, rounds=80, overlap=True, init="first_pass", best=best, tolerance=1e-4)
    assert r.log[-1]["subopt"] <= 1e-4 * r.log[0]["subopt"]
    r = R.train(cols, obj, rounds=4, refresh_fraction=0.1, refresh_residents=True, rebuild_every=2)
    np.testing.assert_allclose(r.v, r.alpha @ X, atol=1e-9)


def test_resume_equals_one_run():
    obj, cols = O.HingeSvmDual(1.0), R.LocalColumns(X * SIGN[:, None])
    whole = R.train(cols, obj, rounds=6, refresh_fraction=0.3)
    half = R.train(cols, obj, rounds=3, refresh_fraction=0.3)
    np.testing.assert_allclose(R.train(cols, obj, rounds=3, refresh_fraction=0.3, start=half).alpha, whole.alpha)


def test_edges():
    obj = O.RidgePrimal(0.5, B)
    x = X.copy()
    x[7] = 0
    r = R.train(R.LocalColumns(x), obj, "fresh_gap", rounds=5, m=200)
    assert r.alpha[7] == 0 and np.isfinite(r.alpha).all()
    with pytest.raises(ValueError):
        R.train(R.LocalColumns(X), obj, m=0)
    with pytest.raises(ValueError):
        O.RidgePrimal(0.0, B)
    twice = np.vstack([X[:5], X[:5]])
    assert np.isfinite(R.plain_scd(R.LocalColumns(twice), O.LassoBoxed(0.1, B), 5).alpha).all()
    one = R.train(R.LocalColumns(np.ones((4, 1))), O.LassoBoxed(0.1, np.ones(1)), rounds=2)
    assert np.isfinite(one.alpha).all()


def test_tuning_helpers():
    cols = R.LocalColumns(X)
    top = R.lambda_max(cols, B)
    assert M.support(R.plain_scd(cols, O.LassoBoxed(top * 1.01, B), 5).alpha) == 0
    lam = R.lambda_for_support(cols, B, 0.2, steps=8, k=40)
    assert abs(M.support(R.plain_scd(cols, O.LassoBoxed(lam, B), 40).alpha) - 0.2) < 0.15
    got = R.cross_validate(X, SIGN, lambda lam: O.HingeSvmDual(lam), [1.0, 100.0], folds=3, k=5)
    assert set(got) == {1.0, 100.0} and max(got.values()) > 0.5


def test_generic_objective_matches_ridge():
    ridge = O.RidgePrimal(0.5, B)
    own = O.GenericObjective(0.5, B, f_=ridge.f, grad_=ridge.grad, g_=ridge.g, g_conj_=ridge.g_conj, prox_=lambda a, u, q: ridge.minimiser(a, u, q), f_conj_=ridge.f_conj)
    cols = R.LocalColumns(X)
    np.testing.assert_allclose(R.train(cols, own, "fresh_gap", rounds=5, solver=lambda *a: V.passes(*a, k=2, seed=1, model=True)).alpha, R.train(cols, ridge, "fresh_gap", rounds=5, solver=lambda *a: V.passes(*a, k=2, seed=1)).alpha)


def test_recovery_and_fidelity():
    assert M.recovery_round([np.array([0]), np.array([0, 2])], np.array([1.0, 0, 2.0])) == 1
    assert M.recovery_round([np.array([0])], np.array([1.0, 0, 2.0])) is None
    overlap, corr = M.fidelity(np.arange(10.0), np.arange(10.0), 3)
    assert overlap == 1 and math.isclose(corr, 1)
