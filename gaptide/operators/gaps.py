"""Dual points, column products, coordinate gaps and the certificate, over coordinate tables.

Row layouts need no shuffle: the dual point goes to every executor if it has at most BROADCAST_NUMBERS numbers, else the
chunked layout joins it by chunk.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..common import BROADCAST_NUMBERS, ship
from ..functions.objectives import Objective
from .layout import to_coo


def dual_point(obj: Objective, v: np.ndarray) -> np.ndarray:
    return obj.grad(v)


def dense_block(column) -> np.ndarray:
    """Rows of a list column as a matrix."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def sparse_products(idx, vals, w: np.ndarray) -> np.ndarray:
    sizes = np.diff(idx.offsets.to_numpy())
    cells = vals.flatten().to_numpy(zero_copy_only=False).astype(np.float64) * w[idx.flatten().to_numpy(zero_copy_only=False)]
    out = np.zeros(len(sizes))
    if len(cells):
        np.add.at(out, np.repeat(np.arange(len(sizes)), sizes), cells)
    return out


def vector_table(spark: SparkSession, w: np.ndarray, width: int | None = None) -> DataFrame:
    """A vector as (row_id, w), or as chunks (chunk, w) of a width."""
    if width is None:
        return spark.createDataFrame(pa.table({"row_id": np.arange(len(w)), "w": np.asarray(w, np.float64)}))
    parts = [w[i : i + width] for i in range(0, len(w), width)]
    parts = [np.concatenate([p, np.zeros(width - len(p))]) for p in parts]
    return spark.createDataFrame(pa.table({"chunk": pa.array(range(len(parts)), pa.int32()), "w": pa.array([p.tolist() for p in parts], pa.list_(pa.float64()))}))


def dots(coords: DataFrame, w: np.ndarray | DataFrame, kind: str = "dense", width: int = 65536) -> DataFrame:
    """coord_id and u, the product of each column with w. For chunked and coo layouts w may be a table (chunk or row_id, w)."""
    spark = coords.sparkSession
    if kind in ("dense", "sparse"):
        if len(w) > BROADCAST_NUMBERS:
            raise ValueError(f"{len(w)} numbers are too many to broadcast: use the chunked layout")
        ship(spark)
        sent = spark.sparkContext.broadcast(np.asarray(w, np.float64))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    u = dense_block(batch.column(1)) @ sent.value if kind == "dense" else sparse_products(batch.column(1), batch.column(2), sent.value)
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(u, pa.float64())], ["coord_id", "u"])

        return coords.select("coord_id", *(["vals"] if kind == "dense" else ["idx", "vals"])).mapInArrow(run, "coord_id long, u double")
    if isinstance(w, np.ndarray):
        w = vector_table(spark, w, width if kind == "chunked" else None)
    if kind == "chunked":
        part = F.aggregate(F.zip_with("vals", "w", lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)
        return coords.join(w, "chunk").select("coord_id", part.alias("p")).groupBy("coord_id").agg(F.sum("p").alias("u"))
    return coords.join(w, "row_id").groupBy("coord_id").agg(F.sum(F.col("x") * F.col("w")).alias("u"))


def dots_sql(coords: DataFrame, w: np.ndarray) -> DataFrame:
    """The dense product as one expression without Python, for short vectors."""
    part = F.aggregate(F.zip_with("vals", F.lit([float(x) for x in w]), lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)
    return coords.select("coord_id", part.alias("u"))


def coordinate_gaps(coords: DataFrame, state: DataFrame, obj: Objective, w: np.ndarray | DataFrame, kind: str = "dense", subset: DataFrame | None = None, targets: bool = False) -> DataFrame:
    """coord_id, alpha, u and gap; subset (coord_id) keeps to some coordinates before anything is multiplied."""
    if subset is not None:
        coords = coords.join(subset.select("coord_id"), "coord_id", "left_semi")
    u = dots(coords, w, kind)
    own = state.select("coord_id", "alpha", *(["y"] if targets else []))
    y = F.col("y") if targets else None
    return u.join(own, "coord_id").withColumn("gap", obj.gap_col(F.col("alpha"), F.col("u"), y))


def total_gap(gaps: DataFrame) -> DataFrame:
    return gaps.agg(F.sum("gap").alias("gap_total"))


def pair_gap(obj: Objective, state: DataFrame, products: DataFrame, v: np.ndarray, w: np.ndarray, targets: bool = False) -> float:
    """The gap of any primal and dual pair: products holds u for that w."""
    y = F.col("y") if targets else F.lit(0.0)
    both = state.join(products, "coord_id").agg(F.sum(obj.g_col(F.col("alpha"), y) + obj.conj_col(-F.col("u"), y))).first()[0]
    return obj.f(v) + obj.f_conj(w) + (both or 0.0)


def objective(state: DataFrame, obj: Objective, v: np.ndarray, targets: bool = False) -> float:
    y = F.col("y") if targets else F.lit(0.0)
    return obj.f(v) + (state.agg(F.sum(obj.g_col(F.col("alpha"), y))).first()[0] or 0.0)


def weighted_rows(coords: DataFrame, state: DataFrame, kind: str = "dense") -> DataFrame:
    """row_id and v, the sum of columns times alpha, as a table: coordinates at zero are left out before the columns are read."""
    used = state.where("alpha <> 0").select("coord_id", "alpha")
    return to_coo(coords.join(used, "coord_id", "left_semi"), kind).join(used, "coord_id").groupBy("row_id").agg(F.sum(F.col("x") * F.col("alpha")).alias("v"))


def rebuild_v(coords: DataFrame, state: DataFrame, d: int, kind: str = "dense") -> np.ndarray:
    if d > BROADCAST_NUMBERS:
        raise ValueError("v is too long for the driver: use weighted_rows")
    used = state.where("alpha <> 0").select("coord_id", "alpha")
    joined = coords.join(used, "coord_id")
    if kind not in ("dense", "sparse"):
        t = weighted_rows(coords, state, kind).toArrow()
        v = np.zeros(d)
        v[t["row_id"].to_numpy()] = t["v"].to_numpy()
        return v
    cols = ["alpha", *(["vals"] if kind == "dense" else ["idx", "vals"])]

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = np.zeros(d)
        for batch in batches:
            a = batch.column(0).to_numpy()
            if kind == "dense":
                if len(a):
                    v += a @ dense_block(batch.column(1))
            else:
                sizes = np.diff(batch.column(1).offsets.to_numpy())
                np.add.at(v, batch.column(1).flatten().to_numpy(), np.repeat(a, sizes) * batch.column(2).flatten().to_numpy(zero_copy_only=False))
        at = np.flatnonzero(v)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(v[at])], ["row_id", "p"])

    t = joined.select(*cols).mapInArrow(part, "row_id long, p double").groupBy("row_id").agg(F.sum("p").alias("v")).toArrow()
    v = np.zeros(d)
    v[t["row_id"].to_numpy()] = t["v"].to_numpy()
    return v


def norms(coords: DataFrame, kind: str = "dense") -> DataFrame:
    if kind in ("dense", "sparse"):
        return coords.select("coord_id", F.aggregate("vals", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")).alias("norm2"))
    return to_coo(coords, kind).groupBy("coord_id").agg(F.sum(F.col("x") * F.col("x")).alias("norm2"))


def gap_profile(gaps: DataFrame, share: float = 0.25) -> DataFrame:
    """How unequal gaps are: quantiles, mean, greatest and the part of the total in the top share."""
    cut_at = F.percentile_approx("gap", 1 - share, 10000)
    stats = gaps.agg(F.count(F.lit(1)).alias("n"), F.sum("gap").alias("total"), F.max("gap").alias("greatest"), F.percentile("gap", F.lit(0.5)).alias("median"), F.percentile("gap", F.lit(0.9)).alias("p90"), cut_at.alias("cut"))
    top = gaps.crossJoin(stats.select("cut")).agg(F.sum(F.when(F.col("gap") >= F.col("cut"), F.col("gap")).otherwise(0.0)).alias("top"))
    return stats.crossJoin(top).select("n", "total", "greatest", "median", "p90", (F.col("top") / F.when(F.col("total") > 0, F.col("total"))).alias("top_share"))


def product_column(vals: Column, w: Column) -> Column:
    return F.aggregate(F.zip_with(vals, w, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
