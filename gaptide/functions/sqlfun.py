"""Functions for SQL: gaps and products as registered functions, a block rule and an exploding table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .objectives import MODELS, clip_col, soft_col


def dense_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm2(a: Column) -> Column:
    return dense_dot(a, a)


def sparse_dot(idx: Column, vals: Column, w: Column) -> Column:
    return F.aggregate(F.zip_with(idx, vals, lambda i, x: F.get(w, i).cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)


soft_threshold, clip = soft_col, clip_col


def hinge(u: Column) -> Column:
    return F.greatest(F.lit(0.0), 1 - u)


def register(spark: SparkSession) -> list[str]:
    """gap_ridge(alpha, u, lam), gap_ridge_dual(alpha, u, y), gap_lasso(alpha, u, lam, box), gap_svm(alpha, u), gap_logit_l1, gap_logit_dual, ... and dense_dot, sparse_dot, soft_threshold, clip, hinge as SQL functions (no Python runs in them); vec_sum, explode_coords, block_top as Python ones."""
    made = {
        "gap_ridge": ("a DOUBLE, u DOUBLE, lam DOUBLE", "(lam * a + u) * (lam * a + u) / (2 * lam)"),
        "gap_ridge_dual": ("a DOUBLE, u DOUBLE, y DOUBLE", "(a - y + u) * (a - y + u) / 2"),
        "gap_lasso": ("a DOUBLE, u DOUBLE, lam DOUBLE, box DOUBLE", "greatest(a * u + lam * abs(a) + box * greatest(abs(u) - lam, 0D), 0D)"),
        "gap_svm": ("a DOUBLE, u DOUBLE", "greatest(a * u - a + greatest(0D, 1 - u), 0D)"),
        "gap_sqhinge": ("a DOUBLE, u DOUBLE", "greatest(a * u - a + a * a / 4 + greatest(0D, 1 - u) * greatest(0D, 1 - u), 0D)"),
        "gap_enet": ("a DOUBLE, u DOUBLE, l1 DOUBLE, l2 DOUBLE", "greatest(a * u + l1 * abs(a) + l2 * a * a / 2 + greatest(abs(u) - l1, 0D) * greatest(abs(u) - l1, 0D) / (2 * l2), 0D)"),
        "gap_logit_l1": ("a DOUBLE, u DOUBLE, lam DOUBLE, box DOUBLE", "greatest(a * u + lam * abs(a) + box * greatest(abs(u) - lam, 0D), 0D)"),
        "gap_logit_dual": ("a DOUBLE, u DOUBLE", "greatest(a * u + CASE WHEN a > 0 THEN a * ln(a) ELSE 0D END + CASE WHEN a < 1 THEN (1 - a) * ln(1 - a) ELSE 0D END + greatest(-u, 0D) + log1p(exp(-abs(u))), 0D)"),
        "sparse_dot": ("idx ARRAY<INT>, vals ARRAY<DOUBLE>, w ARRAY<DOUBLE>", "aggregate(zip_with(idx, vals, (i, x) -> get(w, i) * x), 0D, (s, x) -> s + x)"),
        "dense_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
        "soft_threshold": ("x DOUBLE, t DOUBLE", "sign(x) * greatest(abs(x) - t, 0D)"),
        "clip_to": ("x DOUBLE, lo DOUBLE, hi DOUBLE", "greatest(lo, least(hi, x))"),
        "hinge": ("u DOUBLE", "greatest(0D, 1 - u)"),
    }
    for name, (args, body) in made.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")
    spark.udf.register("vec_sum", vec_sum)
    spark.udtf.register("explode_coords", ExplodeCoords)
    spark.udtf.register("block_top", BlockTop)
    return [*made, "vec_sum", "explode_coords", "block_top"]


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_sum(v: pd.Series) -> list:
    """Sum of arrays of one length, as an aggregate of a group that fits one task; vector_sums has no such bound."""
    return np.sum(np.stack(v.to_numpy()), axis=0).tolist() if len(v) else []


def vector_sums(rows: DataFrame, vals: str, *keys: str) -> DataFrame:
    """keys and vals, the sum of the arrays of each group: cells are summed by place, so partial sums are added wherever the rows are and no task holds a group."""
    cells = rows.select(*keys, F.posexplode(vals).alias("p_", "x_")).groupBy(*keys, "p_").agg(F.sum(F.col("x_").cast("double")).alias("x_"))
    return cells.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("p_", "x_"))).alias("c_")).select(*keys, F.transform("c_", lambda e: e["x_"]).alias(vals))


@F.udtf(returnType=T.StructType([T.StructField("row_id", T.LongType()), T.StructField("x", T.DoubleType())]))
class ExplodeCoords:
    """Non-zero cells of a dense row."""

    def eval(self, vals: list):
        for i, x in enumerate(vals or []):
            if x:
                yield i, float(x)


@F.udtf(returnType=T.StructType([T.StructField("coord_id", T.LongType()), T.StructField("z", T.DoubleType())]))
class BlockTop:
    """The m greatest z of each partition: block_top(TABLE(state) PARTITION BY (bucket), m)."""

    def __init__(self):
        self.rows, self.m = [], 0

    def eval(self, row, m: int):
        self.m = m
        self.rows.append((-row["z"], row["coord_id"]))
        if len(self.rows) > 4 * m:
            self.rows = sorted(self.rows)[:m]

    def terminate(self):
        for z, c in sorted(self.rows)[: self.m]:
            yield c, -z


def gap_arrow(model: str, **constants):
    """A vectorised function of (alpha, u) for any model, over Arrow batches."""
    obj = MODELS[model](**constants)

    @F.arrow_udf("double")
    def gap(a: pa.Array, u: pa.Array) -> pa.Array:
        return pa.array(obj.gap(a.to_numpy(zero_copy_only=False), u.to_numpy(zero_copy_only=False)))

    return gap


def gap_report(spark: SparkSession, view: str, gap: str) -> None:
    """A view `<view>_gaps` of coord_id and gap, and `<view>_report` of their number, sum and greatest, from a view with alpha and u and a gap expression such as gap_svm(alpha, u)."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY VIEW {view}_gaps AS SELECT coord_id, {gap} AS gap FROM {view}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY VIEW {view}_report AS SELECT count(*) AS n, sum(gap) AS gap_total, max(gap) AS greatest FROM {view}_gaps")
