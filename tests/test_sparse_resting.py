"""Sparse rows that rest are passed over."""

import numpy as np

from gaptide.functions import objectives as O
from gaptide.operators.solve import Resting, SparseRows, passes


def test_sparse_rows_that_rest_have_no_turn_and_nothing_changes(monkeypatch):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((4000, 60)) * (rng.random((4000, 60)) < 0.2)
    x[:, 0] += 2.0
    x[[7, 3999]] = 0.0
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1.0)
    rows, obj, turns, step_one = SparseRows.of(*np.nonzero(x), x[np.nonzero(x)], *x.shape), O.HingeSvmDual(1.0), [0], O.HingeSvmDual.step_one
    np.testing.assert_allclose(rows @ np.arange(60.0), x @ np.arange(60.0), atol=1e-12)

    def counted(self, *args):
        turns[0] += 1
        return step_one(self, *args)

    rest, alpha, v = Resting(), np.zeros(4000), np.zeros(60)
    for seed in range(25):
        a, w = alpha.copy(), obj.grad(v)
        for i in np.random.default_rng(seed).permutation(4000):  # every row has its turn
            step = obj.step_one(a[i], float(x[i] @ w), float(x[i] @ x[i]), 0.0)
            a[i] += step
            w = w + step * x[i]
        with monkeypatch.context() as m:
            m.setattr(O.HingeSvmDual, "step_one", counted)
            turns[0] = 0
            s = passes(rows, alpha, v, obj, 0.0, 1, seed=seed, rest=rest)
        np.testing.assert_allclose(alpha + s.delta, a, atol=1e-8)
        alpha, v = alpha + s.delta, v + s.dv
    assert turns[0] < 2000, turns
