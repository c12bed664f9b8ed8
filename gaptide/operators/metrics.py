"""Cost and accuracy measures, on arrays for the local engine and as plans over round logs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.objectives import Objective, total
from .solve import exact


def rho(gaps: np.ndarray, block: np.ndarray) -> float:
    """Mean gap within the block over mean gap: 1 when all gaps are zero."""
    mean = gaps.mean()
    return float(gaps[block].mean() / mean) if mean > 0 else 1.0


def rho_plan(gaps: DataFrame, block: DataFrame) -> DataFrame:
    """The same over tables (coord_id, gap) and (coord_id)."""
    both = gaps.join(block.select("coord_id").withColumn("inside", F.lit(True)), "coord_id", "left")
    return both.agg((F.avg(F.when(F.col("inside"), F.col("gap"))) / F.avg("gap")).alias("rho"))


def theta(x: np.ndarray, alpha: np.ndarray, v: np.ndarray, obj: Objective, delta: np.ndarray, dv: np.ndarray, y=0.0) -> float:
    """Part of the block's possible decrease that an update has reached."""
    before = total(obj, v, alpha, y)
    best = exact(x, alpha, v, obj, y)
    possible = before - total(obj, v + best.dv, alpha + best.delta, y)
    return float((before - total(obj, v + dv, alpha + delta, y)) / possible) if possible > 1e-14 * max(1, abs(before)) else 1.0


def swaps(old: DataFrame, new: DataFrame) -> DataFrame:
    """Columns of the new block that weren't resident."""
    return new.join(old, "coord_id", "left_anti").agg(F.count(F.lit(1)).alias("swaps"))


def bytes_in(swapped: int, bytes_per_column: int) -> int:
    return swapped * bytes_per_column


def relative(log: DataFrame) -> DataFrame:
    """Suboptimality over that of round 0 of the run."""
    first = F.first("subopt").over(W.partitionBy("run_id").orderBy("round").rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    return log.withColumn("rel", F.col("subopt") / F.when(first > 0, first))


def rounds_to(log: DataFrame, tolerance: float = 1e-4) -> DataFrame:
    """First round of each run whose relative suboptimality is at most the tolerance; null if none is."""
    return relative(log).groupBy("run_id", "scheme").agg(F.min(F.when(F.col("rel") <= tolerance, F.col("round"))).alias("rounds"), F.max("round").alias("rounds_run"), F.min("rel").alias("best"))


def per_round_ratio(log: DataFrame) -> DataFrame:
    """Decrease of each round over the suboptimality before it, and its rate (minus the logarithm of what is left)."""
    before = F.lag("subopt").over(W.partitionBy("run_id").orderBy("round"))
    left = F.col("subopt") / F.when(before > 0, before)
    return log.withColumn("decrease", 1 - left).withColumn("rate", -F.log(F.when(left > 0, left)))


def observed_speedup(log: DataFrame, scheme: str, reference: str) -> DataFrame:
    """For each round: the ratio of decreases of two schemes, that of their rates, and the ratio predicted by their shares of the gap.

    A round's decrease can't be more than all, so where rounds leave little the ratio of decreases is held down; rates aren't.
    """
    r = per_round_ratio(log).where("round > 0")
    a, b = (r.where(F.col("scheme") == s).select("round", F.col("decrease").alias(f"d_{t}"), F.col("rate").alias(f"r_{t}"), F.col("eta").alias(f"e_{t}")) for s, t in ((scheme, "a"), (reference, "b")))
    over = lambda x: F.col(f"{x}_a") / F.when(F.col(f"{x}_b") > 0, F.col(f"{x}_b"))
    return a.join(b, "round").select("round", over("d").alias("observed"), over("r").alias("observed_rate"), over("e").alias("predicted"))


def mean_deviation(speedups: DataFrame) -> DataFrame:
    off = lambda c: F.avg(F.abs(F.col(c) - F.col("predicted")))
    return speedups.agg(off("observed").alias("mean_deviation"), off("observed_rate").alias("mean_rate_deviation"), F.count("observed").alias("rounds"))


def cost_model(log: DataFrame, bytes_per_column: int, bandwidth: float, fast_rate: float, slow_rate: float, cells: float, passes) -> DataFrame:
    """Modelled seconds of a round: transfer, then the longer of the block solver and the refresh."""
    transfer = F.col("swaps") * bytes_per_column / bandwidth
    fast = F.col("block_size") * cells * passes / fast_rate
    slow = F.col("refreshed") * cells / slow_rate
    out = log.withColumn("m_transfer", transfer).withColumn("m_fast", fast).withColumn("m_slow", slow).withColumn("m_round", transfer + F.greatest(fast, slow))
    return out.withColumn("m_time", F.sum("m_round").over(W.partitionBy("run_id").orderBy("round").rowsBetween(W.unboundedPreceding, 0)))


def time_to(log: DataFrame, tolerance: float = 1e-4, clock: str = "m_time") -> DataFrame:
    return relative(log).groupBy("run_id", "scheme").agg(F.min(F.when(F.col("rel") <= tolerance, F.col(clock))).alias("seconds"))


def utilisation(log: DataFrame, fast: str = "t_fast", slow: str = "t_slow", whole: str = "t_round") -> DataFrame:
    """Parts of all rounds' time, measured or modelled, in which the fast and the slow unit work."""
    return log.where(F.col(whole) > 0).groupBy("run_id", "scheme").agg((F.sum(fast) / F.sum(whole)).alias("fast_busy"), (F.sum(slow) / F.sum(whole)).alias("slow_busy"))


def support(alpha: np.ndarray, eps: float = 1e-10) -> float:
    return float(np.mean(np.abs(alpha) > eps))


def support_plan(state: DataFrame, eps: float = 1e-10) -> DataFrame:
    return state.agg(F.avg(F.when(F.abs("alpha") > eps, 1.0).otherwise(0.0)).alias("support"))


def recovery_round(blocks: list[np.ndarray], final: np.ndarray, eps: float = 1e-10) -> int | None:
    """First round whose block holds the whole final support."""
    need = set(np.flatnonzero(np.abs(final) > eps))
    return next((t for t, b in enumerate(blocks) if need <= set(b.tolist())), None)


def fidelity(z: np.ndarray, gaps: np.ndarray, m: int) -> tuple[float, float]:
    """Overlap of the blocks by memory and by fresh gaps, and their rank correlation."""
    top = lambda k: set(np.lexsort((np.arange(len(k)), -k))[:m].tolist())
    ranks = lambda k: np.argsort(np.argsort(k, kind="stable"), kind="stable").astype(float)
    a, b = ranks(z), ranks(gaps)
    corr = float(np.corrcoef(a, b)[0, 1]) if len(z) > 1 else 1.0
    return len(top(z) & top(gaps)) / m, corr
