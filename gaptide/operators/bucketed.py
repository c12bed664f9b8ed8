"""Training over workers with gap memory, where a round reads no more of the data than it asks for.

The slow tier is a store of files by hash bucket. Refreshing a share of the memory reads that share of the buckets (a
bucket is a fair sample of coordinates, and files of other buckets are never opened); fetching a block's new columns opens
the buckets that they are in. The fast tier is a table of fetched columns, dealt by worker once when they come in, so that
a round moves no column that is already there; it is written anew when half of it is no longer wanted. The state is a
narrow table. Only v is common: its length is checked before it is broadcast.

Each worker has a working set of its own, the best of its own coordinates: its share of the gap is at least its mean, so the
whole block's is too.
"""

from __future__ import annotations

import math
import threading
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..common import BROADCAST_NUMBERS, cut, hash32, hash32_py, shared_path, ship, unit_draw
from ..functions.objectives import Objective
from ..sources.formats import write_coordinates
from . import gaps as G
from .layout import ROUND_LOG
from .select import weighted_key
from .solve import SparseRows, passes

MEMORY_RULES = ("gap_memory", "fresh_gap")


class BucketStore:
    """Coordinates (coord_id, vals and, for sparse ones, idx) in files by hash bucket, in the shared folder. bytes: what of a column is moved, if that isn't its cells here."""

    def __init__(self, coords: DataFrame, buckets: int, kind: str = "dense"):
        self.spark, self.buckets, self.kind = coords.sparkSession, buckets, kind
        self.cells = ["vals"] if kind == "dense" else ["idx", "vals"]
        path = shared_path(self.spark, "slow-tier")
        write_coordinates(coords.select("coord_id", *self.cells, *[c for c in ("y", "bytes") if c in coords.columns]), path, buckets)
        self.table = self.spark.read.parquet(path)

    def some(self, buckets: list[int] | None = None, ids: DataFrame | None = None) -> DataFrame:
        """Rows of some buckets, and of some ids (columns bucket, coord_id) within them."""
        rows = self.table if buckets is None else self.table.where(F.col("bucket").isin(buckets) if buckets else F.lit(False))
        return rows if ids is None else rows.join(ids.select("bucket", "coord_id"), ["bucket", "coord_id"], "left_semi")

    def sampled(self, share: float, t: int, seed: int) -> list[int]:
        """The buckets that a round refreshes."""
        turn = sorted(range(self.buckets), key=lambda b: hash32_py(seed, f"r{t}", b))
        return sorted(turn[: min(self.buckets, math.ceil(share * self.buckets))])


def buckets_for(workers: int) -> int:
    return max(64, 8 * workers)


class FastTier:
    """Fetched columns, bucketed by worker: a worker's columns are read where it runs, without a shuffle."""

    def __init__(self, spark, workers: int):
        self.spark, self.workers, self.name, self.rows = spark, workers, None, 0

    def add(self, columns: DataFrame, many: int) -> None:
        name = self.name or f"fast_{uuid.uuid4().hex}"
        columns.repartition("worker").write.mode("append").bucketBy(4 * self.workers, "worker").sortBy("coord_id").format("parquet").saveAsTable(name)
        self.name, self.rows = name, self.rows + many

    def read(self) -> DataFrame:
        return self.spark.table(self.name)

    def keep(self, wanted: DataFrame, many: int) -> None:
        """Written anew with wanted columns only."""
        old, rows = self.name, self.read().join(wanted.select("worker", "coord_id"), ["worker", "coord_id"], "left_semi")
        self.name, self.rows = None, 0
        self.add(rows, many)
        self.spark.sql(f"DROP TABLE IF EXISTS {old}")

    def drop(self) -> None:
        if self.name:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")


def chosen(state: DataFrame, rule: str, fraction: float, t: int, seed: int) -> Column:
    """Whether a coordinate is in its worker's working set: a rank within the worker."""
    own = W.partitionBy("worker")
    many = F.greatest(F.lit(1), F.floor(F.count(F.lit(1)).over(own) * fraction))
    orders = {
        "gap_memory": F.desc("z"),
        "fresh_gap": F.desc("z"),
        "random": hash32(seed, t, F.col("coord_id")),
        "importance_norm": F.desc(weighted_key(F.sqrt("norm2"), unit_draw(seed, t, F.col("coord_id")))),
        "sequential": F.col("coord_id"),
    }
    rank = F.row_number().over(own.orderBy(orders[rule], "coord_id")) - 1
    if rule == "sequential":
        rank = F.pmod(rank - many * t, F.count(F.lit(1)).over(own))
    return rank < many


def _block(table: pa.Table, kind: str, d: int):
    vals = table["vals"].combine_chunks()
    if kind == "dense":
        return G.dense_block(vals)
    ptr = np.concatenate(([0], np.cumsum(np.diff(vals.offsets.to_numpy())))).astype(np.int64)
    return SparseRows(ptr, table["idx"].combine_chunks().flatten().to_numpy().astype(np.int64), vals.flatten().to_numpy(zero_copy_only=False).astype(np.float64), d)


def _solver(sent, obj: Objective, d: int, kind: str, k: int, scale: float, sigma: float, seed: int, t: int):
    """What a worker does: its fetched columns and its block's state give changes of alpha (kind 0) and of v (kind 1)."""

    def work(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({"kind": pa.array([], pa.int32()), "id": pa.array([], pa.int64()), "x": pa.array([], pa.float64())})
        b = b.sort_by("coord_id")
        ids, have = b["coord_id"].to_numpy(), a["coord_id"].to_numpy()
        at = np.searchsorted(ids, have)
        at[at == len(ids)] = 0
        rows = np.flatnonzero(ids[at] == have)
        rows = rows[np.argsort(have[rows])]
        x, y = _block(a.take(pa.array(rows)), kind, d), b["y"].to_numpy() if obj.uses_target else 0.0
        got = passes(x, b["alpha"].to_numpy(), sent.value, obj, y, k, seed=hash32_py(seed, t, int(b["worker"][0].as_py())), sigma=sigma, model=True)
        moved, change = np.flatnonzero(got.delta), np.flatnonzero(got.dv)
        return pa.table({"kind": pa.array(np.repeat(np.array([0, 1], np.int32), [len(moved), len(change)])), "id": pa.array(np.concatenate((ids[moved], change)), pa.int64()), "x": pa.array(scale * np.concatenate((got.delta[moved], got.dv[change])))})

    return work


def bucket_train(
    coords: DataFrame | BucketStore,
    obj: Objective,
    d: int,
    rule: str = "gap_memory",
    rounds: int = 10,
    fraction: float = 0.25,
    k: int = 2,
    refresh_fraction: float = 0.25,
    combine: str = "average",
    workers: int = 8,
    buckets: int | None = None,
    seed: int = 0,
    kind: str = "dense",
    best: float | None = None,
    tolerance: float | None = None,
    trace: bool = False,
    run_id: str | None = None,
    refresh_residents: bool = False,
) -> tuple[DataFrame, np.ndarray, list[dict]]:
    """State table, v and the log of each round. coords: coord_id, vals, idx (sparse) and, if wanted, y; or a store of them (sized), which several runs may share.

    A round: each worker takes the best of its memory; new columns are fetched; the local model is solved by all workers
    against the same v while a share of the memory is refreshed at the point before the update; changes are averaged, or
    added with the curvature of so many workers. The first pass fills the memory. tolerance ends the run on suboptimality
    relative to round 0. refresh_residents also takes the gaps of columns in the fast tier, which reads nothing of the slow
    one: without it a trained block's memory stays as it was until its buckets are sampled. trace adds the certificate, a scan of everything that isn't part of the method. The log's
    refreshed are columns read for the memory, bytes_in those of fetched columns.
    """
    spark = coords.spark if isinstance(coords, BucketStore) else coords.sparkSession
    if d > BROADCAST_NUMBERS:
        raise ValueError(f"v of {d} numbers can't be broadcast")
    if combine not in ("average", "add"):
        raise ValueError("combine is average or add")
    ship(spark)
    store = coords if isinstance(coords, BucketStore) else BucketStore(coords, buckets or buckets_for(workers), kind)
    width = 8 if kind == "dense" else 12
    fast = FastTier(spark, workers)
    y = F.col("y") if "y" in store.table.columns else F.lit(0.0)
    moved = F.col("bytes") if "bytes" in store.table.columns else F.size("vals").cast("long") * width
    norm2 = F.aggregate("vals", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")) if rule == "importance_norm" else F.lit(0.0)
    v = np.zeros(d)
    keeps = rule in MEMORY_RULES
    u0 = G.dots(store.table, obj.grad(v), kind) if keeps else None
    state = store.table.select("coord_id", "bucket", F.pmod("bucket", F.lit(workers)).alias("worker"), y.cast("double").alias("y"), norm2.alias("norm2"), moved.alias("bytes"), F.lit(0.0).alias("alpha"), F.lit(0).alias("z_round"), F.lit(False).alias("resident"), F.lit(False).alias("held"))
    target = F.col("y") if obj.uses_target else F.lit(0.0)
    gap = lambda u: obj.gap_col(F.col("alpha"), u, target)
    state = cut(state.join(u0, "coord_id").withColumn("z", gap(F.col("u"))).drop("u") if keeps else state.withColumn("z", F.lit(0.0)))
    scale, sigma = (1 / workers, 1.0) if combine == "average" else (1.0, float(workers))
    log, names = [], state.columns

    def value_of(s: DataFrame) -> tuple[float, float]:
        r = s.agg(F.sum(obj.g_col(F.col("alpha"), target)), F.avg(F.lit(len(log)) - F.col("z_round"))).first()
        return obj.f(v) + (r[0] or 0.0), float(r[1] or 0.0)

    def row(t: int, **x) -> dict:
        return dict.fromkeys(ROUND_LOG.names) | {"run_id": run_id or f"{rule}-{combine}-{workers}", "round": t, "scheme": rule, "swaps": 0, "bytes_in": 0, "refreshed": 0, "gap_total": certificate() if trace else None} | x

    def certificate() -> float:
        return G.dots(store.table, obj.grad(v), kind).join(state, "coord_id").agg(F.sum(gap(F.col("u")))).first()[0]

    value, age = value_of(state)
    log.append(row(0, objective=value, subopt=None if best is None else value - best))
    first = value - best if best is not None else None
    try:
        for t in range(rounds):
            w = obj.grad(v)
            refreshed = 0
            if rule == "fresh_gap" and t:
                state = cut(state.join(G.dots(store.table, w, kind), "coord_id").withColumn("z", gap(F.col("u"))).withColumn("z_round", F.lit(t)).select(*names))
            marked = cut(state.withColumn("now", chosen(state, rule, fraction, t, seed)))
            block = marked.where("now")
            missing = block.where(~F.col("held"))
            new = ~F.col("held")
            size, swaps, fetched, moved_in, wanted = block.agg(F.count(F.lit(1)), F.sum(F.when(F.col("resident"), 0).otherwise(1)), F.sum(new.cast("long")), F.sum(F.when(new, F.col("bytes"))), F.collect_set(F.when(new, F.col("bucket")))).first()  # at most the number of buckets
            if fetched:
                fast.add(store.some(sorted(wanted), missing).select(F.pmod("bucket", F.lit(workers)).alias("worker"), "coord_id", *store.cells), fetched)

            fresh: list[DataFrame] = []
            sample: list[int] = []
            error: list[BaseException] = []

            def refresh(t=t, w=w) -> None:
                try:
                    read = cut(G.dots(store.some(store.sampled(refresh_fraction, t, seed)), w, kind))
                    sample.append(read.count())
                    if refresh_residents:
                        read = cut(read.union(G.dots(fast.read().select("coord_id", *store.cells), w, kind)).groupBy("coord_id").agg(F.first("u").alias("u")))
                    fresh.append(read)
                except BaseException as e:  # raised again by the round
                    error.append(e)

            slow = threading.Thread(target=refresh, daemon=True) if rule == "gap_memory" else None
            if slow:
                slow.start()
            sent = spark.sparkContext.broadcast(v)

            own = block.select(F.col("worker").alias("worker"), F.col("coord_id").alias("coord_id"), F.col("alpha").alias("alpha"), F.col("y").alias("y"))
            out = cut(fast.read().groupBy("worker").cogroup(own.groupBy("worker")).applyInArrow(_solver(sent, obj, d, kind, k, scale, sigma, seed, t), "kind int, id long, x double"))
            sent.unpersist()
            if slow:
                slow.join()
                if error:
                    raise error[0]
            change = out.where("kind = 1").groupBy("id").agg(F.sum("x").alias("x")).toArrow()  # at most d rows
            v = v.copy()
            v[change["id"].to_numpy()] += change["x"].to_numpy()
            delta = out.where("kind = 0").select(F.col("id").alias("coord_id"), F.col("x").alias("delta"))
            merged = marked.join(delta, "coord_id", "left")
            if fresh:
                refreshed = sample[0]
                merged = merged.join(fresh[0], "coord_id", "left").withColumn("z", F.coalesce(F.when(F.col("u").isNotNull(), gap(F.col("u"))), F.col("z"))).withColumn("z_round", F.when(F.col("u").isNotNull(), t).otherwise(F.col("z_round")))
            full = fast.rows > 2 * size
            held = F.col("now") if full else F.col("held") | F.col("now")
            state = cut(merged.withColumn("alpha", F.col("alpha") + F.coalesce("delta", F.lit(0.0))).withColumn("resident", F.col("now")).withColumn("held", held).select(*names))
            if full:
                fast.keep(block, size)
            value, age = value_of(state)
            log.append(row(t + 1, block_size=size, objective=value, subopt=None if best is None else value - best, swaps=swaps, bytes_in=int(moved_in or 0), refreshed=refreshed, mean_age=age if keeps else None))
            if tolerance is not None and first is not None and value - best <= tolerance * first:
                break
    finally:
        fast.drop()
    return state, v, log
