"""Passes over many coordinates of which most rest, and draws for many ids."""

import numpy as np
import pytest

from gaptide.common import hash32_np, hash32_py
from gaptide.functions import objectives as O
from gaptide.operators.solve import SparseRows, StoredRows, passes


def one_by_one(x, alpha, v, obj, k, seed):
    """Every coordinate has its turn."""
    rng, q, a, w = np.random.default_rng(seed), obj.smooth * np.einsum("ij,ij->i", x, x), alpha.copy(), obj.grad(v)
    for _ in range(k):
        for i in rng.permutation(len(x)):
            step = obj.step_one(a[i], float(x[i] @ w), q[i], 0.0)
            a[i] += step
            w = w + obj.smooth * step * x[i]
    return a


@pytest.mark.parametrize("sparse", [False, True])
@pytest.mark.parametrize("obj", [O.HingeSvmDual(1.0), O.SquaredHingeSvmDual(1.0), O.LassoBoxed(2.0, np.sin(np.arange(24.0))), O.ElasticNet(2.0, np.sin(np.arange(24.0)), 0.5)], ids=lambda o: o.name)
def test_resting_coordinates_are_passed_over_and_nothing_else_changes(obj, sparse, monkeypatch):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((4000, 24)) * (rng.random((4000, 24)) < 0.5)
    x[:, 0] += 2.0
    x[7] = 0.0
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1.0)
    rows = SparseRows.of(*np.nonzero(x), x[np.nonzero(x)], *x.shape) if sparse else x
    turns, step_one = [0], type(obj).step_one

    def counted(self, *args):
        turns[0] += 1
        return step_one(self, *args)

    alpha, v = np.zeros(4000), np.zeros(24)
    for seed in range(12):
        own = one_by_one(x, alpha, v, obj, 1, seed)
        with monkeypatch.context() as m:
            m.setattr(type(obj), "step_one", counted)
            turns[0] = 0
            s = passes(rows, alpha, v, obj, 0.0, 1, seed=seed)
        np.testing.assert_allclose(alpha + s.delta, own, atol=1e-7)
        np.testing.assert_allclose(s.dv, (own - alpha) @ x, atol=1e-6)
        alpha, v = alpha + s.delta, v + s.dv
    if obj.name in ("svm", "lasso") and not sparse:  # few of their steps aren't 0 by now
        assert turns[0] < 3000, turns


@pytest.mark.parametrize("prefix", ["0:r17", "x" * 49, "x" * 60])
def test_draws_are_those_of_the_hash(prefix):
    for n in (0, 1, 11, 1234, 40_000):
        assert hash32_np(prefix, n).tolist() == [hash32_py(prefix, i) for i in range(n)]


def test_rows_in_files_are_not_copied_into_blocks(tmp_path):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((300, 40)) * (rng.random((300, 40)) < 0.2)
    x[[0, 17, 299]] = 0.0
    own = SparseRows.of(*np.nonzero(x), x[np.nonzero(x)], *x.shape)
    for part in ("ptr", "idx", "vals"):
        getattr(own, part).tofile(tmp_path / f"rows.{part}")
    stored = StoredRows(str(tmp_path / "rows"), 40)
    w, some, alpha = rng.standard_normal(40), np.array([5, 299, 0, 17, 4]), np.zeros(300)
    picked = stored[some].joined(stored[np.arange(300) > 290])[np.arange(12)]
    ids = np.concatenate((some, np.arange(291, 298)))
    assert picked.idx is stored.idx and picked.vals is stored.vals and picked.nbytes == own[ids].nbytes - own[ids].ptr.nbytes
    assert (picked @ w == own[ids] @ w).all() and (w[:12] @ picked == w[:12] @ own[ids]).all() and (picked.norms() == own[ids].norms()).all()
    assert len(stored[np.array([], int)] @ w) == 0
    for obj in (O.HingeSvmDual(1.0), O.LogisticL1(0.1, np.sign(w))):
        a, b = passes(picked, alpha[ids], np.zeros(40), obj, 0.0, 3), passes(own[ids], alpha[ids], np.zeros(40), obj, 0.0, 3)
        assert (a.delta == b.delta).all() and a.delta.any()
