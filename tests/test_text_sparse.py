"""Text problems over sparse rows."""

import sys
from pathlib import Path

import numpy as np
import pytest
from conftest import DATA

sys.path.insert(0, str(Path(__file__).parent))
from gaptide.functions import objectives as O  # noqa: E402
from gaptide.operators import train as R  # noqa: E402
from gaptide.operators.solve import SparseRows  # noqa: E402
from gaptide.plans import workloads  # noqa: E402


def test_sparse_text_problem_trains_like_the_dense_one(spark, monkeypatch):
    dense, y = workloads.text_problem(spark, DATA)
    sparse, same = workloads.text_problem(spark, DATA, dense_bytes=0)
    assert isinstance(sparse.x, SparseRows) and (y == same).all() and sparse.x.nbytes < dense.x.nbytes
    np.testing.assert_allclose(sparse.norms(), dense.norms())
    for rule in ("gap_memory", "random", "importance_norm", "sequential"):
        for obj in (O.LassoBoxed(0.1 * R.lambda_max(dense, y), y), O.LogisticL1(0.5, y)):
            a, b = (R.train(c, obj, rule, rounds=3, k=1, init="first_pass", trace=True, rebuild_every=2) for c in (dense, sparse))
            np.testing.assert_allclose(a.alpha, b.alpha, atol=1e-7)
    # both queries return rows where no dense matrix is made
    whole = workloads.text_problem
    monkeypatch.setattr(workloads, "text_problem", lambda s, d: whole(s, d, dense_bytes=0))
    assert workloads.importance_text(spark, DATA, rounds=2).count() == 3
    log = workloads.logistic_text(spark, DATA, rounds=2).toPandas()
    assert log.groupby("scheme")["round"].max().eq(2).all() and np.isfinite(log["objective"]).all()


@pytest.mark.parametrize("at", [np.array([2]), np.array([3, 0, 3]), np.array([], int), np.array([True, False, True, False])])
def test_sparse_rows_are_rows(at):
    x = np.array([[0, 1.5, 0], [0, 0, 0], [2, 0, -1], [0, 0, 4.0]])
    s = SparseRows.of(*np.nonzero(x), x[np.nonzero(x)], *x.shape)
    w, a = np.array([1.0, 2, 3]), np.arange(1.0, 1 + len(x[at]))
    np.testing.assert_allclose(s[at] @ w, x[at] @ w)
    np.testing.assert_allclose(a @ s[at], a @ x[at])
    np.testing.assert_allclose(s[at].joined(s) @ w, np.concatenate((x[at], x)) @ w)
