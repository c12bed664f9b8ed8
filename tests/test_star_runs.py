"""One thread over all samples of the star, at any size."""

import numpy as np
import pytest
from conftest import DATA

from gaptide.functions import objectives as O
from gaptide.operators import solve as V
from gaptide.operators import train as R
from gaptide.operators.solve import SparseRows, passes
from gaptide.plans import workloads


def even_rows(n, seed=0):
    """Rows of one length: two places that are the same in all, two that differ."""
    rng = np.random.default_rng(seed)
    idx = np.concatenate((np.tile([0, 1], (n, 1)), rng.integers(2, 9, (n, 1)), rng.integers(9, 30, (n, 1))), axis=1)
    vals = np.concatenate((rng.standard_normal((n, 3)), np.ones((n, 1))), axis=1)
    vals[5] = 0.0
    return idx, vals, rng.standard_normal(n)


def test_one_thread_runs_at_any_size(spark, monkeypatch):
    scale, passes_made = workloads.star_scale, []
    own = workloads.own_passes
    monkeypatch.setattr(workloads, "own_passes", lambda *a: passes_made.append(a[3]) or own(*a))
    few = workloads.star_schemes(spark, DATA, rounds=1).toPandas().set_index("scheme")
    monkeypatch.setattr(workloads, "star_scale", lambda *a: (lambda s, obj, n, options: (s, obj, 50_000_000, options))(*scale(*a)))
    many = workloads.star_schemes(spark, DATA, rounds=1).toPandas().set_index("scheme")
    assert passes_made[0] == passes_made[1] and sorted(few.index) == sorted(many.index)
    np.testing.assert_allclose(few.loc["plain_scd", ["rounds", "log10_best"]].astype(float), many.loc["plain_scd", ["rounds", "log10_best"]].astype(float))


@pytest.mark.parametrize("n", [100, 1000, 2500])
def test_linear_steps_together_are_those_of_one_after_the_other(n, monkeypatch):
    idx, vals, y = even_rows(n)
    x, obj = SparseRows(np.arange(n + 1) * 4, idx.ravel(), vals.ravel(), 30), O.RidgeDual(2.0)
    got = [passes(x, y / 3, np.sin(np.arange(30.0)), obj, y, 3, seed=1, sigma=4.0, model=True)]
    assert V._places(x) is not None
    assert V._places(SparseRows(x.ptr, idx[:, [0, 0, 2, 3]].ravel(), x.vals, 30)) is None  # an index at two places
    monkeypatch.setattr(V, "_places", lambda x: None)
    got.append(passes(x, y / 3, np.sin(np.arange(30.0)), obj, y, 3, seed=1, sigma=4.0, model=True))
    np.testing.assert_allclose(got[0].delta, got[1].delta, atol=1e-12)
    np.testing.assert_allclose(got[0].dv, got[1].dv, atol=1e-10)


def test_rows_and_state_in_files_train_like_those_in_memory(tmp_path):
    n = 1000
    idx, vals, y = even_rows(n)
    own = R.plain_scd(R.SparseColumns(SparseRows(np.arange(n + 1) * 4, idx.ravel(), vals.ravel(), 30), y), O.RidgeDual(2.0), 3, best=-1e9)
    rows, at = R.EvenColumns(n + 7, 30, str(tmp_path)), np.arange(n) + 7 * (np.arange(n) > 400)  # seven ids have no row
    for part in np.array_split(np.random.default_rng(1).permutation(n), 9):
        rows.put(at[part], idx[part], vals[part], y[part])
    once = rows.once
    rows.once = lambda v, obj, seed: once(v, obj, seed, part=150)
    got = R.plain_scd(rows.filled(), O.RidgeDual(2.0), 3, best=-1e9)
    np.testing.assert_allclose(got.alpha[at], own.alpha, atol=1e-12)
    np.testing.assert_allclose([x["objective"] for x in got.log], [x["objective"] for x in own.log], rtol=1e-12)
    assert [isinstance(x, np.ndarray) for x in rows.idx] == [False, False, True, True] and got.log[0]["block_size"] == n
