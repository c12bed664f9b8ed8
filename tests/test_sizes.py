"""Runs whose matrix, block or log is larger than one process may hold."""

import sys
import tracemalloc
from pathlib import Path

import numpy as np
import pytest
from conftest import DATA

sys.path.insert(0, str(Path(__file__).parent))
from gaptide.functions import objectives as O  # noqa: E402
from gaptide.operators import bucketed as B  # noqa: E402
from gaptide.operators import solve as V  # noqa: E402
from gaptide.operators import train as R  # noqa: E402
from gaptide.plans import catalogue, workloads  # noqa: E402
from gaptide.sources import features as X  # noqa: E402


@pytest.mark.parametrize("make", [O.RidgeDual, lambda lam: O.RidgePrimal(lam, np.ones(8))])
def test_exact_block_of_many_short_columns_makes_no_square(make):
    gen = np.random.default_rng(0)
    x, y, a, v = gen.standard_normal((3000, 8)), gen.standard_normal(3000), gen.standard_normal(3000), gen.standard_normal(8)
    obj = make(3.0)
    tracemalloc.start()
    s = V.exact(x, a, v, obj, y)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 5e6  # a square of 3000 is 72 MB
    # no coordinate moves any more
    assert np.abs(obj.step(a + s.delta, x @ obj.grad(v + s.dv), obj.smooth * V.squares(x), y)).max() < 1e-9


def turned(monkeypatch) -> None:
    whole = workloads.poly2_problem
    monkeypatch.setattr(workloads, "poly2_problem", lambda s, d: whole(s, d, dense_bytes=0))


def test_turned_columns_train_like_the_matrix(spark):
    (dense, b), (own, turn) = workloads.poly2_problem(spark, DATA), workloads.poly2_problem(spark, DATA, dense_bytes=0)
    assert own.x.nbytes == 8 * own.n * (own.n + 1) and (own.n, own.length, own.bytes_per_column) == (dense.n, dense.d, dense.bytes_per_column)
    np.testing.assert_allclose(own.x @ turn, dense.x @ b, atol=1e-10)
    lam = R.lambda_on_path(dense, b)
    assert abs(R.lambda_on_path(own, turn) / lam - 1) < 1e-8
    for rule in ("gap_memory", "random"):
        a, c = (R.train(x, O.LassoBoxed(lam, t), rule, rounds=3, init="first_pass", trace=True) for x, t in ((dense, b), (own, turn)))
        np.testing.assert_allclose(a.alpha, c.alpha, atol=1e-8)
        columns = ["objective", "gap_total", "rho", "swaps", "bytes_in"]
        np.testing.assert_allclose(c.frame()[columns].iloc[1:].astype(float), a.frame()[columns].iloc[1:].astype(float), rtol=1e-7)


#: Queries over the turned problem, and how many rows each returns.
TURNED = {
    "run_bounds_by_round": 2,
    "run_importance_dense": 3,
    "run_lasso_schemes": 6,
    "run_ridge_schemes": 6,
    "run_selection_fidelity": 1,
    "run_sparse_share": 2,
    "run_staleness_sweep": 15,
    "run_support_tuning": 1,
    "run_swap_series": 360,
    "run_tiers": 1,
    "run_validation_ridge": 2,
    "run_validation_speedup": 36,
    "run_passes_tuning": 50,
}


@pytest.mark.parametrize("name", sorted(TURNED))
def test_queries_run_where_the_matrix_is_too_large(spark, monkeypatch, name):
    turned(monkeypatch)
    got = catalogue.QUERIES[name](spark, DATA).toPandas()
    assert len(got) == TURNED[name] and ("holds" not in got or got["holds"].all())


def test_pairs_made_on_demand_are_the_matrix(spark):
    columns, b = workloads.poly2_problem(spark, DATA)
    got, sign = workloads.poly2_signs(spark, DATA, *workloads.poly2_problem(spark, DATA, dense_bytes=0))
    assert isinstance(got, R.PairColumns) and (sign == np.sign(b)).all() and got.x.nbytes == 65 * 8 * columns.d
    gen, at = np.random.default_rng(0), np.array([3, 70, 2143, 64])
    w, a = gen.standard_normal(columns.d), gen.standard_normal(columns.n)
    np.testing.assert_allclose(got.products(w), columns.products(w), atol=1e-10)
    np.testing.assert_allclose(a @ got.x, a @ columns.x, atol=1e-10)
    np.testing.assert_allclose(got.norms(), columns.norms())
    for i in (at, at[:1], np.arange(columns.n) < 3):
        np.testing.assert_allclose(got.fetch(i) @ w, columns.x[i] @ w, atol=1e-12)
    r, s = (R.train(c, O.LogisticL1(0.05, sign), rounds=1, k=1, init="first_pass") for c in (columns, got))
    np.testing.assert_allclose(r.alpha, s.alpha, atol=1e-8)


def test_rows_in_files_train_like_rows_in_memory(spark, monkeypatch):
    for stored, own in ((workloads.text_problem(spark, DATA, 0, 0)[0].x, workloads.text_problem(spark, DATA, 0)[0].x), (workloads.svm_rows(spark, DATA, 0), workloads.svm_rows(spark, DATA))):
        assert isinstance(stored, V.StoredRows) and not isinstance(own, V.StoredRows) and stored.shape == own.shape
        for part in ("ptr", "idx", "vals"):
            np.testing.assert_array_equal(getattr(stored, part), getattr(own, part))
    # files go to tasks whatever their size
    whole, rows = workloads.text_problem, workloads.svm_rows
    grid = R.run_grid
    monkeypatch.setattr(R, "run_grid", lambda *a: grid(*a, most_bytes=0))
    monkeypatch.setattr(workloads, "text_problem", lambda s, d: whole(s, d, 0, 0))
    monkeypatch.setattr(workloads, "svm_rows", lambda s, d: rows(s, d, 0))
    assert workloads.importance_text(spark, DATA, rounds=2).count() == 3
    assert workloads.logistic_text(spark, DATA, rounds=2).count() == 9
    assert workloads.text_svm_schemes(spark, DATA, rounds=2).count() == 6


def test_parts_of_entries_add_up(monkeypatch):
    gen = np.random.default_rng(0)
    x = gen.standard_normal((40, 9)) * (gen.random((40, 9)) < 0.4)
    s, parts = V.SparseRows.of(*np.nonzero(x), x[np.nonzero(x)], *x.shape), V._parts
    monkeypatch.setattr(V, "_parts", lambda ptr: parts(ptr, 5))
    assert len(V._parts(s.ptr)) > 10
    w, a, at = gen.standard_normal(9), gen.standard_normal(40), gen.permutation(40)[:30]
    for got, want in ((s @ w, x @ w), (a @ s, a @ x), (s.norms(), (x * x).sum(axis=1)), (s[at] @ w, x[at] @ w)):
        np.testing.assert_allclose(got, want, atol=1e-12)


def test_bound_rows_follow_the_vectors(spark, tmp_path):
    import oracle

    got = catalogue.QUERIES["theory_bound_rows"](spark, DATA).toPandas()
    oracle.same(got, oracle.connect(DATA).sql(catalogue.SQL["theory_bound_rows"]).df())
    spark.read.parquet(f"{DATA}/embeddings.parquet").limit(100).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert not got.equals(catalogue.QUERIES["theory_bound_rows"](spark, str(tmp_path)).toPandas())


def test_turned_star_trains_like_the_columns(spark, monkeypatch):
    names = ["round", "objective", "gap_total", "swaps", "refreshed", "bytes_in", "mean_age"]
    own = workloads.star_lasso(spark, DATA, rounds=2).orderBy("round").toPandas()[names].astype(float)
    # no column and no target as long as the table is made
    monkeypatch.setattr(X, "star_features", None)
    monkeypatch.setattr(X, "star_target", None)
    got = workloads.star_lasso(spark, DATA, rounds=2, most_bytes=0).orderBy("round").toPandas()[names].astype(float)
    np.testing.assert_allclose(got, own, rtol=1e-8)


def test_sums_of_rows_are_the_products(spark):
    rows = X.star_samples(spark, DATA)
    t = rows.toArrow().combine_chunks()
    x, y = np.zeros((t.num_rows, X.STAR_D)), t["y"].to_numpy()
    np.put_along_axis(x, t["idx"].combine_chunks().flatten().to_numpy().reshape(len(x), -1), t["vals"].combine_chunks().flatten().to_numpy().reshape(len(x), -1), 1)
    got = X.sparse_sums(rows, X.STAR_D)
    for a, b in ((got.gram, x.T @ x), (got.moment, x.T @ y), (got.total, x.sum(axis=0)), (got.cells, (x != 0).sum(axis=0)), (got.square, y @ y), (got.mean, y.mean()), (got.n, len(x))):
        np.testing.assert_allclose(a, b, rtol=1e-9, atol=1e-9)


def test_star_schemes_write_one_store(spark, monkeypatch):
    made, write = [], B.write_coordinates
    monkeypatch.setattr(B, "write_coordinates", lambda *a: made.append(1) or write(*a))
    got = workloads.star_schemes(spark, DATA, rounds=2).toPandas()
    assert len(made) == 1 and len(got) == 5 and np.isfinite(got["log10_best"]).all()


def test_logistic_step_of_one_is_the_step_of_many():
    gen = np.random.default_rng(0)
    a, u, q = np.concatenate(([0.0, 1.0], gen.random(998))), 20 * gen.standard_normal(1000), 10.0 ** gen.uniform(-4, 4, 1000)
    obj = O.LogisticDual(1.0)
    calls = []
    obj.minimiser = lambda *x: calls.append(x)  # the search over arrays, which is slow for one
    got = a + [obj.step_one(*map(float, x), 0.0) for x in zip(a, u, q)]
    assert not calls
    np.testing.assert_allclose(got, a + O.LogisticDual(1.0).step(a, u, q), atol=1e-7)
    z = np.clip(got, 1e-12, 1 - 1e-12)
    inside = (z > 1e-9) & (z < 1 - 1e-9)
    assert np.abs((u + q * (z - a) + np.log(z / (1 - z))) / (q + 1 / (z * (1 - z))))[inside].max() < 1e-12
