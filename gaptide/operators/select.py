"""Rules that choose the block, over the state table; numpy twins for the local engine draw the same keys.

Rules return coord_id of exactly min(m, n) rows; ties go to the smaller id. Random draws are hashes of seed, round and id.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..common import hash32, hash32_np, unit_draw
from .layout import dense_ids

#: Up to this many rows a top list is one task's sort; beyond it the histogram finds the cut.
SORT_UP_TO = 100_000


def block_size(n: int, fraction: float | None = None, budget_bytes: int | None = None, bytes_per_column: int | None = None) -> int:
    m = math.floor(n * fraction) if fraction is not None else budget_bytes // bytes_per_column
    if m < 1:
        raise ValueError("the fast tier holds no column")
    return min(m, n)


def top_sorted(rows: DataFrame, key: Column, m: int) -> DataFrame:
    return rows.select("coord_id", key.alias("k")).orderBy(F.desc("k"), "coord_id").limit(m).select("coord_id")


def top_threshold(rows: DataFrame, key: Column, m: int, steps: int = 16) -> DataFrame:
    """The same rows without a global sort: a histogram on logarithmic bins finds the bin of the m-th, all above it stay, and only that bin is ordered.

    Keys are not negative. If the bin is still large it is split once more by its range.
    """
    k = rows.select("coord_id", key.alias("k"))
    k = k.withColumn("bin", F.when(F.col("k") > 0, F.floor(F.log2("k") * steps)).otherwise(F.lit(-(1 << 20))).cast("int"))
    counts = sorted(((r["bin"], r["n"]) for r in k.groupBy("bin").agg(F.count(F.lit(1)).alias("n")).collect()), reverse=True)
    above, at, inside = 0, None, 0
    for b, n in counts:
        at, inside = b, n
        if above + n >= m:
            break
        above += n
    if at is None:
        return k.select("coord_id")
    sure, edge, need = k.where(F.col("bin") > at).select("coord_id"), k.where(F.col("bin") == at), m - above
    if inside > SORT_UP_TO:
        ends = edge.agg(F.min("k"), F.max("k")).first()
        cell = F.floor((F.col("k") - ends[0]) / max(ends[1] - ends[0], 1e-300) * 4096)
        fine = sorted(((r["c"], r["n"]) for r in edge.groupBy(cell.alias("c")).agg(F.count(F.lit(1)).alias("n")).collect()), reverse=True)
        got, last = 0, None
        for c, n in fine:
            last = c
            if got + n >= need:
                break
            got += n
        sure, edge, need = sure.union(edge.where(cell > last).select("coord_id")), edge.where(cell == last), need - got
    return sure.union(edge.orderBy(F.desc("k"), "coord_id").limit(max(need, 0)).select("coord_id"))


def top_approx(rows: DataFrame, key: Column, m: int, n: int) -> DataFrame:
    """About m rows: those above an approximate quantile."""
    at = rows.agg(F.percentile_approx(key, max(0.0, 1 - m / n), 10000)).first()[0]
    return rows.where(key >= at).select("coord_id")


def top(rows: DataFrame, key: Column, m: int) -> DataFrame:
    return top_sorted(rows, key, m) if m <= SORT_UP_TO else top_threshold(rows, key, m)


def weighted_key(weight: Column, draw: Column) -> Column:
    """Sampling without replacement in proportion to weights: the greatest of log(draw) / weight."""
    return F.when(weight > 0, F.log(draw) / weight).otherwise(F.lit(-1e300))


def select_block(rule: str, state: DataFrame, m: int, round: int = 0, seed: int = 0, **options) -> DataFrame:
    """coord_id of the block. state has coord_id and what the rule reads: gap, z, norm2, slope, alpha, u, resident or bucket.

    fresh_gap: greatest gap; gap_memory: greatest z; random; sequential: slices of ids 0..n-1, wrapping; importance_norm and
    importance_norm2: static weights; importance_gap: weights z; steepest: greatest slope; single: one coordinate of the
    greatest gap; uniform_batches: slices of a permutation that changes each epoch; keep_informative: active ones among
    residents first, then fresh ones in order; partition_local_top: each bucket's share of its own best; sticky: a
    newcomer's z counts 1 + margin times less.
    """
    if m < 1:
        raise ValueError("a block has one coordinate at least")
    c = F.col
    draw = unit_draw(seed, round, c("coord_id"))
    if rule == "fresh_gap":
        return top(state, c("gap"), m)
    if rule == "gap_memory":
        return top(state, c("z"), m)
    if rule == "single":
        return top_sorted(state, c("gap"), 1)
    if rule == "steepest":
        return top(state, F.abs(c("slope")), m)
    if rule == "random":
        return state.select("coord_id", hash32(seed, round, c("coord_id")).alias("k")).orderBy("k", "coord_id").limit(m).select("coord_id") if m <= SORT_UP_TO else top_threshold(state, F.lit(float(1 << 32)) - hash32(seed, round, c("coord_id")), m)
    if rule in ("importance_norm", "importance_norm2", "importance_gap"):
        weight = {"importance_norm": F.sqrt("norm2"), "importance_norm2": c("norm2"), "importance_gap": c("z")}[rule]
        return top_sorted(state, weighted_key(weight, draw), m) if m <= SORT_UP_TO else top_threshold(state, F.when(weight > 0, -1 / (F.log(draw) / weight)).otherwise(0.0), m)
    if rule == "sequential":
        n = options.get("n") or state.count()
        lo = (round * m) % n
        hi = lo + m
        inside = (c("coord_id") >= lo) & (c("coord_id") < hi)
        return state.where(inside | (c("coord_id") < hi - n) if hi > n else inside).select("coord_id")
    if rule == "uniform_batches":
        n = options.get("n") or state.count()
        per = max(1, n // m)
        epoch, lo = round // per, (round % per) * m
        # ranks in the epoch's order without one task for all: ranges are sorted apart, then offset
        drawn = state.select("coord_id", hash32(seed, f"e{epoch}", c("coord_id")).alias("k"))
        return dense_ids(drawn, "k", "coord_id", name="r").where((c("r") >= lo) & (c("r") < lo + m)).select("coord_id")
    if rule == "keep_informative":
        n = options.get("n") or state.count()
        active = c("resident") & (((c("alpha") > 0) & (c("alpha") < 1)) | (c("u") < 1))
        turn = F.pmod(c("coord_id") - F.lit(round * m), F.lit(n))
        return state.select("coord_id", F.when(active, 0).otherwise(1).alias("k"), turn.alias("t")).orderBy("k", "t").limit(m).select("coord_id")
    if rule == "partition_local_top":
        n = options.get("n") or state.count()
        sizes = state.groupBy("bucket").agg(F.count(F.lit(1)).alias("n_k"))
        order = W.partitionBy("bucket").orderBy(F.desc("z"), "coord_id")
        return state.join(sizes, "bucket").select("coord_id", F.row_number().over(order).alias("r"), F.ceil(c("n_k") * (m / n)).alias("q")).where(c("r") <= c("q")).select("coord_id")
    if rule == "sticky":
        margin = options.get("margin", 0.1)
        return top(state, F.when(c("resident"), c("z") * (1 + margin)).otherwise(c("z")), m)
    raise ValueError(f"unknown rule {rule}")


# --- numpy twins for the local engine; ids are 0..n-1


def top_np(key: np.ndarray, m: int) -> np.ndarray:
    return np.sort(np.lexsort((np.arange(len(key)), -key))[:m])


def draws_np(seed: int, round: int | str, n: int) -> np.ndarray:
    return hash32_np(f"{seed}:{round}", n).astype(np.float64)


def select_np(rule: str, m: int, round: int, seed: int, s: dict[str, np.ndarray], margin: float = 0.1) -> np.ndarray:
    n = len(s["z"])
    m = min(m, n)
    ids = np.arange(n)
    if rule in ("fresh_gap", "single"):
        return top_np(s["gap"], 1 if rule == "single" else m)
    if rule == "gap_memory":
        return top_np(s["z"], m)
    if rule == "steepest":
        return top_np(np.abs(s["slope"]), m)
    if rule == "random":
        return np.sort(np.lexsort((ids, draws_np(seed, round, n)))[:m])
    if rule.startswith("importance"):
        weight = {"importance_norm": np.sqrt(s["norm2"]), "importance_norm2": s["norm2"], "importance_gap": s["z"]}[rule]
        with np.errstate(divide="ignore"):
            key = np.where(weight > 0, np.log((draws_np(seed, round, n) + 0.5) / (1 << 32)) / np.where(weight > 0, weight, 1), -1e300)
        return top_np(key, m)
    if rule == "sequential":
        return np.sort((round * m + np.arange(m)) % n)
    if rule == "uniform_batches":
        per = max(1, n // m)
        order = np.lexsort((ids, draws_np(seed, f"e{round // per}", n)))
        return np.sort(order[(round % per) * m : (round % per) * m + m])
    if rule == "keep_informative":
        active = s["resident"] & (((s["alpha"] > 0) & (s["alpha"] < 1)) | (s["u"] < 1))
        return np.sort(np.lexsort(((ids - round * m) % n, ~active))[:m])
    if rule == "partition_local_top":
        own = s["bucket"]
        parts = [np.flatnonzero(own == b) for b in np.unique(own)]
        return np.sort(np.concatenate([p[top_np(s["z"][p], math.ceil(len(p) * m / n))] for p in parts]))
    if rule == "sticky":
        return top_np(np.where(s["resident"], s["z"] * (1 + margin), s["z"]), m)
    raise ValueError(f"unknown rule {rule}")
