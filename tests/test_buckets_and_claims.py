"""Workers over buckets read what they ask for, single steps equal array steps, measures of time, new SQL functions."""

import re
import sys
from pathlib import Path

import numpy as np
import pytest
from conftest import DATA
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parent))

from gaptide.functions import objectives as O  # noqa: E402
from gaptide.functions import sqlfun  # noqa: E402
from gaptide.operators import bucketed as B  # noqa: E402
from gaptide.operators import layout as L  # noqa: E402
from gaptide.operators import metrics as M  # noqa: E402
from gaptide.operators import solve as S  # noqa: E402
from gaptide.operators import train as R  # noqa: E402
from gaptide.sources import features as X  # noqa: E402
from gaptide.sources import formats as IO  # noqa: E402
from gaptide.plans import workloads  # noqa: E402


def pruned(rows) -> bool:
    """Whether the scan gets the buckets as a filter of folders, so that others are never listed or opened."""
    return bool(re.search(r"PartitionFilters: \[[^\]]*bucket#\d+", rows._jdf.queryExecution().executedPlan().toString()))


def files(rows) -> int:
    return rows.select(F.input_file_name().alias("f")).distinct().count()


def test_a_refresh_reads_only_its_buckets(spark):
    coords = workloads.signed_samples(spark, DATA)
    n = coords.count()
    store = B.BucketStore(coords, 40)
    some = store.sampled(0.05, 3, 0)
    assert len(some) == 2 and pruned(store.some(some)) and files(store.some(some)) <= 2 < files(store.table)
    state, v, log = B.bucket_train(coords, O.HingeSvmDual(1.0), 64, rounds=4, refresh_fraction=0.05, workers=2, buckets=40, trace=True)
    assert all(0 < r["refreshed"] <= 0.15 * n for r in log[1:]) and all(a["objective"] >= b["objective"] - 1e-9 for a, b in zip(log, log[1:]))
    # no column that is in the fast tier is fetched again, and v is the columns' sum
    fetched = sum(r["bytes_in"] for r in log) / (8 * 64)
    assert fetched <= min(n, sum(r["swaps"] for r in log)) and state.count() == n
    x = {r["coord_id"]: np.array(r["vals"]) for r in coords.collect()}
    np.testing.assert_allclose(sum(r["alpha"] * x[r["coord_id"]] for r in state.collect()), v, atol=1e-9)


@pytest.mark.parametrize("rule", ["fresh_gap", "random", "sequential", "importance_norm"])
def test_workers_with_every_rule_approach_the_optimum(spark, rule):
    coords = workloads.signed_samples(spark, DATA)
    _, x = X.matrix(coords)
    best, _, _ = R.optimum(R.LocalColumns(x), O.HingeSvmDual(5.0), 300)
    _, _, log = B.bucket_train(coords, O.HingeSvmDual(5.0), 64, rule=rule, rounds=6, k=4, workers=1, combine="add", best=best, tolerance=1e-3)
    assert log[-1]["subopt"] < 0.2 * log[0]["subopt"]


def test_sparse_workers_equal_dense_ones(spark):
    rows = [(i, [0, 2, 5], [float(i % 7), 1.0, 0.5 * (i % 3)], float(i % 5)) for i in range(60)]
    sparse = spark.createDataFrame(rows, "coord_id long, idx array<int>, vals array<double>, y double")
    dense = spark.createDataFrame([(i, [v[0], 0.0, v[1], 0.0, 0.0, v[2]], y) for i, _, v, y in rows], "coord_id long, vals array<double>, y double")
    options = {"rounds": 3, "workers": 2, "buckets": 8, "refresh_residents": True}
    _, v, _ = B.bucket_train(sparse, O.RidgeDual(2.0), 6, kind="sparse", **options)
    _, w, _ = B.bucket_train(dense, O.RidgeDual(2.0), 6, **options)
    np.testing.assert_allclose(v, w, atol=1e-9)


@pytest.mark.parametrize("name", sorted(O.MODELS))
def test_single_steps_equal_array_steps(name):
    gen = np.random.default_rng(0)
    b = gen.choice([-1.0, 1.0], 5)
    obj = O.MODELS[name](0.7, b) if name in ("ridge", "lasso", "enet", "logit_l1") else O.MODELS[name](0.7)
    for _ in range(40):
        a, u, q, y = gen.random(), gen.standard_normal() * 2, gen.choice([0.0, 0.3, 2.0]), gen.standard_normal()
        assert abs(obj.step_one(a, u, q, y) - float(obj.step(a, u, q, y))) < 1e-12


def test_stored_columns_read_only_wanted_buckets(spark, tmp_path):
    coords = X.emb_samples(spark, DATA).select("coord_id", "vals")
    IO.write_coordinates(coords, f"{tmp_path}/store", 16)
    cols = R.SparkColumns(spark.read.parquet(f"{tmp_path}/store"), 64, buckets=16)
    _, x = X.matrix(coords)
    ids = np.flatnonzero(cols.own_buckets() == 5)[:4]
    assert pruned(cols._some(ids)) and files(cols._some(ids)) == 1
    np.testing.assert_allclose(cols.fetch(ids), x[ids])
    r = R.train(cols, O.HingeSvmDual(1.0), rounds=2, refresh_mode="bucket", refresh_fraction=0.1, init="first_pass")
    assert r.log[-1]["objective"] < r.log[0]["objective"]


def test_partition_local_top_in_a_trainer():
    gen = np.random.default_rng(1)
    x = gen.standard_normal((80, 20))
    r = R.train(R.LocalColumns(x), O.HingeSvmDual(3.0), "partition_local_top", rounds=8, init="first_pass", trace=True)
    assert all(len(b) <= 24 for b in r.blocks) and r.log[-1]["gap_total"] < r.log[1]["gap_total"]


def test_times_and_utilisation(spark):
    rows = [("a:2", "s", t, 10.0 ** -t, 4, 2, 8, float(t > 0), 0.5, 1.0) for t in range(6)]
    log = spark.createDataFrame(rows, "run_id string, scheme string, round int, subopt double, block_size long, swaps long, refreshed long, t_fast double, t_slow double, t_round double")
    timed = M.cost_model(M.relative(log), 8, 8.0, 4.0, 2.0, 1, 2)
    assert M.time_to(timed, 1e-4).first()["seconds"] == timed.where("round = 4").first()["m_time"]
    busy = M.utilisation(log).first()
    assert abs(busy["fast_busy"] - 5 / 6) < 1e-12 and abs(busy["slow_busy"] - 0.5) < 1e-12


def test_new_sql_functions_and_vector_sums(spark):
    sqlfun.register(spark)
    r = spark.sql("SELECT gap_logit_dual(0.3D, 0.4D) a, gap_logit_l1(0.2D, -1.5D, 1D, 2D) b, sparse_dot(array(0, 2), array(2D, 3D), array(1D, 5D, 7D)) c, dense_dot(array(1D, 2D), array(3D, 4D)) d").first()
    assert abs(r["a"] - float(O.LogisticDual(1.0).gap(0.3, 0.4))) < 1e-12 and r["c"] == 23 and r["d"] == 11
    assert abs(r["b"] - float(O.LassoBoxed(1.0, np.ones(2), 2.0).gap(0.2, -1.5))) < 1e-12
    f = spark.createDataFrame([("x", [1.0, 2.0]), ("x", [3.0, 4.0]), ("y", [5.0, 6.0])], "k string, vals array<double>")
    assert {(r["k"], tuple(r["vals"])) for r in sqlfun.vector_sums(f, "vals", "k").collect()} == {("x", (4.0, 6.0)), ("y", (5.0, 6.0))}


def test_chunks_are_built_in_one_pass(spark):
    coo = spark.createDataFrame([(1, 0, 2.0), (1, 9, 3.0), (2, 13, 4.0)], "coord_id long, row_id long, x double")
    got = {(r["coord_id"], r["chunk"]): r["vals"] for r in L.to_chunked(coo, 8).collect()}
    assert got == {(1, 0): [2.0] + [0.0] * 7, (1, 1): [0.0, 3.0] + [0.0] * 6, (2, 1): [0.0] * 5 + [4.0, 0.0, 0.0]}


def test_a_weight_for_a_support():
    gen = np.random.default_rng(3)
    x = gen.standard_normal((200, 60))
    x /= np.linalg.norm(x, axis=1)[:, None]
    b = gen.standard_normal(60)
    lam = R.lambda_on_path(R.LocalColumns(x), b, 0.12)
    assert abs(M.support(R.plain_scd(R.LocalColumns(x), O.LassoBoxed(lam, b), 300).alpha) - 0.12) < 0.03
