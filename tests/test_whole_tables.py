"""Whole-table forms of the queries whose SQL is over a few ids."""

import numpy as np
from conftest import DATA

from gaptide.plans import catalogue, relational, workloads  # noqa: E402


def test_whole_forms_leave_no_row_out(spark):
    line = spark.read.parquet(f"{DATA}/lineitem.parquet")
    assert catalogue.QUERIES["unpivot_lineitem_whole"](spark, DATA).count() == 3 * line.select("l_orderkey").distinct().count()
    pdf = spark.read.parquet(f"{DATA}/embeddings.parquet").orderBy("vec_id").toPandas()
    x = np.stack(pdf["embedding"]).astype(float)
    gram = relational.join_gram_features(spark, DATA).toPandas()
    assert len(gram) == 64 * 65 // 2
    np.testing.assert_allclose(gram["x"], (x.T @ x)[gram["i"], gram["j"]], atol=1e-6)
    b = np.array([workloads.unit_py("b", int(v)) * 2 - 1 for v in pdf["vec_id"]])
    got = catalogue.QUERIES["run_normal_equations_whole"](spark, DATA).orderBy("coord_id").toPandas()
    assert got["coord_id"].tolist() == list(range(64))
    np.testing.assert_allclose(got["alpha"], np.linalg.solve(x.T @ x + 0.5 * np.eye(64), x.T @ b), atol=2e-6)
