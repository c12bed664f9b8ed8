"""The experiments, on the given tables: problems, schemes, sweeps, comparisons. Each returns a table of rounds or of results.

Targets are planted, because the tables carry no signal. Runs of a grid are tasks of one job; the matrix is sent to all
executors after a check of its size. The large-n case keeps data and state in buckets.
"""

from __future__ import annotations

import math
import tempfile
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from ..common import cut, hash32_py, release, stash, table
from ..functions import objectives as O
from ..operators import bucketed as B
from ..operators import gaps as G
from ..operators import layout as L
from ..operators import metrics as M
from ..operators import theory as T
from ..operators import train as R
from ..operators.layout import ROUND_LOG
from ..operators.solve import PairRows, SparseRows, op_norm_sq
from ..sources import features as X

#: Schemes of the comparisons: the method, its oracle, and what it is held against.
SCHEMES = ("gap_memory", "fresh_gap", "random", "sequential", "importance_norm", "plain_scd")
#: A modelled machine: link bytes a second, cells a second of the fast and the slow unit. Wall time here says nothing about two units.
LINK, FAST, SLOW = 8e9, 4e10, 4e9


def unit_py(*parts) -> float:
    return (hash32_py(*parts) + 0.5) / (1 << 32)


def planted_weights(n: int, density: float = 0.03, seed: int = 1) -> np.ndarray:
    return np.array([(2 * unit_py(f"a{seed}", i) - 1) * 2 if unit_py(f"d{seed}", i) < density else 0.0 for i in range(n)])


def planted(x: np.ndarray, density: float = 0.03, noise: float = 0.01, seed: int = 1) -> np.ndarray:
    """Target of each row for coordinates x (a row each): the same draws as sources.features.planted_target."""
    return planted_weights(len(x), density, seed) @ x + noise * np.array([2 * unit_py(f"n{seed}", j) - 1 for j in range(x.shape[1])])


def poly2_problem(spark: SparkSession, sf_dir: str, dense_bytes: int = 256 << 20) -> tuple[R.LocalColumns, np.ndarray]:
    """Features and their pairs as coordinates (2,144); a planted target. If the matrix were over dense_bytes it is turned, which leaves every least-squares run over it the same."""
    if poly2_bytes(spark, sf_dir) > dense_bytes:
        gram, d = X.poly2_gram(spark, sf_dir)
        columns, noise = R.RotatedColumns.of(gram, d)
        return columns, planted_weights(columns.n) @ columns.x + 0.01 * noise[0]
    _, x = X.matrix(X.emb_poly2(spark, sf_dir))
    return R.LocalColumns(x), planted(x)


def poly2_signs(spark: SparkSession, sf_dir: str, columns: R.LocalColumns, b: np.ndarray) -> tuple[R.LocalColumns, np.ndarray]:
    """The same columns and the signs of the target, for fits that aren't least squares: where poly2_problem turned them, over the vectors (64 numbers a row), the pairs made when they are asked for."""
    if not isinstance(columns, R.RotatedColumns):
        return columns, np.sign(b)
    _, e = X.matrix(X.emb_samples(spark, sf_dir).where("vals is not null").select("coord_id", "vals"))
    x = PairRows.of(np.ascontiguousarray(e.T))
    return R.PairColumns(x), np.sign(planted(x))


def poly2_bytes(spark: SparkSession, sf_dir: str) -> int:
    return 8 * (X.D64 + X.D64 * (X.D64 + 1) // 2) * table(spark, sf_dir, "embeddings").where("embedding is not null").count()


def signed_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples times their class (the label's half) as coordinates."""
    sign = F.when(F.col("label") < 5, 1.0).otherwise(-1.0)
    return X.emb_samples(spark, sf_dir).select("coord_id", F.transform("vals", lambda v: v * sign).alias("vals"))


def svm_problem(spark: SparkSession, sf_dir: str) -> R.LocalColumns:
    """Samples times their class: the label's half."""
    return R.LocalColumns(X.matrix(signed_samples(spark, sf_dir))[1])


def separated(spark: SparkSession, sf_dir: str, wrong: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """Samples and the side of a planted plane that they are on, a tenth of them on the wrong one: labels that can be learned and need a regulariser."""
    _, x = X.matrix(X.emb_samples(spark, sf_dir).select("coord_id", "vals"))
    side = np.sign(x @ np.array([2 * unit_py("sep", j) - 1 for j in range(x.shape[1])]))
    return x, side * np.where([unit_py("flip", i) < wrong for i in range(len(x))], -1.0, 1.0)


def best_lam(x: np.ndarray, labels: np.ndarray, lams=(0.3, 1.0, 3.0, 10.0), k: int = 8) -> tuple[float, dict[float, float]]:
    """The regulariser of the greatest held-out accuracy, the greater one of equals."""
    got = R.cross_validate(x, labels, O.HingeSvmDual, list(lams), k=k)
    return max(got, key=lambda lam: (got[lam], lam)), got


def text_problem(spark: SparkSession, sf_dir: str, dense_bytes: int = 256 << 20, sparse_bytes: int = 256 << 20) -> tuple[R.LocalColumns, np.ndarray]:
    """Tokens of labelled documents as coordinates (logarithms of counts), quality as -1 and 1 for each document. Sparse rows if a dense matrix were over dense_bytes, in files if these are over sparse_bytes."""
    coo = stash(X.doc_tf(spark, sf_dir).select("coord_id", "row_id", "x").repartitionByRange("coord_id").sortWithinPartitions("coord_id", "row_id"), "tokens")
    labels = table(spark, sf_dir, "labels", "doc_id", "quality").orderBy("doc_id").toPandas()
    docs, y = labels["doc_id"].to_numpy(), np.where(labels["quality"].to_numpy() == 1, 1.0, -1.0)
    n = coo.agg(F.max("coord_id")).first()[0] + 1

    def cells(t: pa.Table) -> tuple[np.ndarray, ...]:
        row, at, x = t["coord_id"].to_numpy(), np.searchsorted(docs, t["row_id"].to_numpy()), np.log1p(t["x"].to_numpy())
        order = np.lexsort((at, row))
        return row[order], at[order], x[order]

    if n * len(docs) * 8 > dense_bytes:
        # a token of no labelled document has a row without entries
        sizes = spark.range(n).select(F.col("id").alias("coord_id")).join(coo.groupBy("coord_id").agg(F.count(F.lit(1)).alias("n")), "coord_id", "left").select("coord_id", F.coalesce("n", F.lit(0)).alias("n"))
        return R.SparseColumns(X.sparse_rows(coo, sizes, "coord_id", lambda t: cells(t)[1:], len(docs), sparse_bytes)), y
    row, at, x = cells(coo.toArrow())
    dense = np.zeros((n, len(docs)))
    dense[row, at] = x
    return R.LocalColumns(dense), y


def runs_for(schemes, best: float, rounds: int, **options) -> list[dict]:
    return [{"rule": s, "run_id": s, "best": best, "rounds": rounds, "init": "first_pass", **options} for s in schemes]


def refresh_share(k: int, fraction: float = 0.25) -> float:
    """Part of the memory that the slow unit refreshes while the fast one makes k passes over its block."""
    return min(1.0, k * fraction * SLOW / FAST)


def compare(spark: SparkSession, columns: R.LocalColumns, make, schemes=SCHEMES, rounds: int = 60, tolerance: float = 1e-4, reference: int = 600, passes=(1, 2, 5, 10), **options) -> DataFrame:
    """Round logs of the schemes with relative suboptimality and modelled time, each scheme at each number of passes.

    The memory is refreshed for as long as the block is solved, so its share follows from the passes and the two units' rates.
    """
    best, _, _ = R.optimum(columns, make(), reference, 1e-10)
    base = {"best": best, "tolerance": tolerance, "rounds": rounds}
    runs = [{"rule": s, "run_id": f"{s}:{k}", "k": k, "init": "first_pass", "refresh_fraction": refresh_share(k), **base, **options} for s in schemes if s != "plain_scd" for k in passes]
    if "plain_scd" in schemes:
        runs.insert(0, {"rule": "plain_scd", "run_id": "plain_scd:1", **base, "rounds": 4 * rounds})
    log = cut(R.run_grid(spark, columns, make, runs))
    return modelled(log, columns.n, columns.length, columns.bytes_per_column)


def modelled(log: DataFrame, n: int, d: float, bytes_per_column: int) -> DataFrame:
    """Modelled time of logs whose run_id ends in the number of passes. A rule that reads all gaps waits for a scan in each round, a memory for its first pass; one thread works at the slow rate and copies nothing."""
    k = F.element_at(F.split("run_id", ":"), -1).cast("double")
    scan = n * d / SLOW
    timed = M.cost_model(M.relative(log), bytes_per_column, LINK, FAST, SLOW, d, k)
    scans = F.when(F.col("scheme").isin("fresh_gap", "steepest", "keep_informative"), F.col("round")).when(F.col("scheme").isin(*R.MEMORY), F.least(F.col("round"), F.lit(1))).otherwise(0)
    return timed.withColumn("m_time", F.when(F.col("scheme") == "plain_scd", F.col("round") * scan).otherwise(F.col("m_time") + scans * scan))


def summary(log: DataFrame, tolerance: float = 1e-4) -> DataFrame:
    """Each scheme at its own best number of passes: rounds, modelled seconds and bytes to the tolerance, busy shares of the two units, and seconds over the gap memory's (of a run that didn't reach the tolerance, where rounds is null: what it spent, so at least so much)."""
    seconds, busy = M.time_to(log, tolerance).drop("scheme"), M.utilisation(log, "m_fast", "m_slow", "m_round").drop("scheme")
    runs = M.rounds_to(log, tolerance).join(seconds, "run_id").join(log.groupBy("run_id").agg(F.sum("swaps").alias("swaps"), F.sum("bytes_in").alias("bytes_in"), F.max("m_time").alias("spent")), "run_id").join(busy, "run_id", "left")
    first = F.row_number().over(W.partitionBy("scheme").orderBy(F.col("seconds").asc_nulls_last(), "best", "run_id"))
    tuned = cut(runs.withColumn("r", first).where("r = 1"))  # a row for each scheme
    memory = tuned.where("scheme = 'gap_memory'").select(F.col("seconds").alias("own"))
    passes = F.element_at(F.split("run_id", ":"), -1).cast("int")
    return tuned.join(F.broadcast(memory), F.lit(True), "left").select("scheme", passes.alias("passes"), "rounds", F.col("seconds").alias("model_seconds"), (F.coalesce("seconds", "spent") / F.col("own")).alias("over_memory"), "swaps", "bytes_in", F.log10(F.greatest("best", F.lit(1e-16))).alias("log10_best"), "rounds_run", "fast_busy", "slow_busy")


def lasso_lam(columns: R.LocalColumns, b: np.ndarray, support: float = 0.12) -> float:
    """The L1 weight that leaves about so many coordinates away from zero."""
    return R.lambda_on_path(columns, b, support)


# --- behaviour


#: Ridge regularisers: from blocks whose coordinates lean on one another to nearly independent ones, where the theory is tight.
RIDGE = (0.5, 5.0, 50.0)


def validation_log(spark: SparkSession, columns: R.LocalColumns, make, rounds: int) -> DataFrame:
    best, _, _ = R.optimum(columns, make(), 300, 1e-12)
    return R.run_grid(spark, columns, make, runs_for(("fresh_gap", "random"), best, rounds, trace=True, theta=True, exact=True))


def validation_ridge(spark: SparkSession, sf_dir: str, rounds: int = 12) -> DataFrame:
    """Ridge, a quarter of the columns a block, blocks solved exactly so that theta is 1 for both: share of the gap and decrease of fresh-gap and random blocks, round by round."""
    columns, b = poly2_problem(spark, sf_dir)
    out = None
    for lam in RIDGE:
        log = validation_log(spark, columns, lambda lam=lam: O.RidgePrimal(lam, b), rounds).select(F.lit(lam).alias("lam"), "scheme", "round", "subopt", "rho", "theta", "eta", "run_id", "swaps")
        out = log if out is None else out.unionByName(log)
    return out


def validation_dual(spark: SparkSession, sf_dir: str, rounds: int = 12) -> DataFrame:
    """The same for dual ridge on the raw vectors: samples are coordinates."""
    _, x = X.matrix(X.emb_samples(spark, sf_dir).select("coord_id", "vals"))
    y = x @ np.array([2 * unit_py("sep", j) - 1 for j in range(x.shape[1])]) + 0.1 * np.array([2 * unit_py("yn", i) - 1 for i in range(len(x))])
    return validation_log(spark, R.LocalColumns(x, y), lambda: O.RidgeDual(float(len(x)) / 10), rounds).select("scheme", "round", "subopt", "rho", "theta", "eta", "run_id", "swaps")


def validation_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Observed over predicted speed-up of each round, and their mean deviation, for each regulariser."""
    log = cut(validation_ridge(spark, sf_dir).withColumn("run_id", F.concat_ws(":", "run_id", F.col("lam").cast("string"))))
    out = None
    for lam in RIDGE:
        s = M.observed_speedup(log.where(F.col("lam") == lam), "fresh_gap", "random").where("predicted is not null and observed is not null")
        rows = cut(s.withColumn("lam", F.lit(lam)))
        rows = rows.join(F.broadcast(M.mean_deviation(rows)), F.lit(True)).select("lam", "round", "observed", "observed_rate", "predicted", "mean_deviation", "mean_rate_deviation")
        out = rows if out is None else out.unionByName(rows)
    return out


def sparse_share(spark: SparkSession, sf_dir: str, rounds: int = 8) -> DataFrame:
    """Lasso with a support smaller than the block: the fresh-gap block's share goes to n / m, its greatest; and the first round whose block holds the whole final support."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    make = lambda: O.LassoBoxed(lam, b)
    best, end, _ = R.optimum(columns, make(), 300, 1e-10)
    r = R.train(columns, make(), "fresh_gap", rounds=rounds, best=best)
    found = M.recovery_round(r.blocks, end.alpha, 1e-6)
    rows = [(x["round"], x["rho"], columns.n / math.floor(columns.n / 4), M.support(end.alpha, 1e-6), found) for x in r.log[1:]]
    return spark.createDataFrame(rows, "round int, rho double, greatest double, support double, recovered_in int")


def staleness_sweep(spark: SparkSession, sf_dir: str, shares=(0.01, 0.02, 0.05, 0.1, 0.25, 0.5, 1.0), rounds: int = 400, tolerance: float = 1e-4, k: int = 2) -> DataFrame:
    """Lasso: rounds to the tolerance for each part of the memory refreshed a round and each start, over the oracle's, at one number of passes for all."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    make = lambda: O.LassoBoxed(lam, b)
    best, _, _ = R.optimum(columns, make(), 300, 1e-10)
    base = {"best": best, "rounds": rounds, "tolerance": tolerance, "k": k}
    runs = [{"rule": "gap_memory", "scheme": f"{init}", "refresh_fraction": r, "init": init, "run_id": f"{init}:{r}", **base} for r in shares for init in ("zeros", "first_pass")]
    runs.append({"rule": "fresh_gap", "scheme": "oracle", "run_id": "oracle:1", **base})
    log = cut(R.run_grid(spark, columns, make, runs))
    got = M.rounds_to(log, tolerance).join(log.where("round > 0").groupBy("run_id").agg(F.round(F.avg("mean_age"), 3).alias("mean_delay"), F.sum("swaps").alias("swaps")), "run_id")
    oracle = got.where("scheme = 'oracle'").select(F.col("rounds").alias("oracle_rounds"))
    return got.crossJoin(oracle).select("scheme", F.split("run_id", ":")[1].cast("double").alias("refreshed"), "rounds", "mean_delay", (F.col("rounds") / F.col("oracle_rounds")).alias("over_oracle"), "swaps")


def swap_series(spark: SparkSession, sf_dir: str, shares=(0.05, 0.25, 1.0), rounds: int = 120) -> DataFrame:
    """Lasso: columns replaced in each round."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    runs = [{"rule": "gap_memory", "scheme": f"refresh {r}", "refresh_fraction": r, "init": "first_pass", "run_id": f"r{r}", "rounds": rounds} for r in shares]
    return R.run_grid(spark, columns, lambda: O.LassoBoxed(lam, b), runs).where("round > 0").select("scheme", "round", "swaps", "mean_age")


def selection_fidelity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far blocks by memory agree with blocks by fresh gaps."""
    columns, b = poly2_problem(spark, sf_dir)
    obj = O.LassoBoxed(lasso_lam(columns, b), b)
    rows = []
    for share in (0.05, 0.25, 1.0):
        r = R.train(columns, obj, rounds=8, refresh_fraction=share, init="first_pass")
        fresh = obj.gap(r.alpha, columns.products(obj.grad(r.v)), columns.y)
        rows.append((share, *M.fidelity(r.z, fresh, columns.n // 4)))
    return spark.createDataFrame(rows, "refreshed double, overlap double, rank_correlation double")


# --- comparisons


def lasso_schemes(spark: SparkSession, sf_dir: str, rounds: int = 300) -> DataFrame:
    """Lasso at 12% support."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    return summary(compare(spark, columns, lambda: O.LassoBoxed(lam, b), rounds=rounds))


def svm_schemes(spark: SparkSession, sf_dir: str, rounds: int = 300) -> DataFrame:
    """Support vector machine with the regulariser of the greatest held-out accuracy."""
    x, labels = separated(spark, sf_dir)
    lam, _ = best_lam(x, labels)
    return summary(compare(spark, R.LocalColumns(x * labels[:, None]), lambda: O.HingeSvmDual(lam), rounds=rounds))


def ridge_schemes(spark: SparkSession, sf_dir: str, rounds: int = 60) -> DataFrame:
    columns, b = poly2_problem(spark, sf_dir)
    return summary(compare(spark, columns, lambda: O.RidgePrimal(0.5, b), rounds=rounds))


def svm_rows(spark: SparkSession, sf_dir: str, sparse_bytes: int = 256 << 20) -> SparseRows:
    """Labelled documents times their class, in order of their ids."""
    rows = stash(X.doc_svm(spark, sf_dir).repartitionByRange("coord_id").sortWithinPartitions("coord_id"), "documents")

    def cells(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        t = t.take(np.argsort(t["coord_id"].to_numpy(), kind="stable")).combine_chunks()
        idx, vals = t["idx"].combine_chunks(), t["vals"].combine_chunks()
        return idx.flatten().to_numpy(), vals.flatten().to_numpy(zero_copy_only=False) * np.repeat(t["y"].to_numpy(), np.diff(idx.offsets.to_numpy()))

    d = rows.agg(F.max(F.array_max("idx"))).first()[0] + 1
    return X.sparse_rows(rows, rows.select("coord_id", F.size("idx").alias("n")), "coord_id", cells, d, sparse_bytes)


def text_svm_schemes(spark: SparkSession, sf_dir: str, rounds: int = 80) -> DataFrame:
    """Support vector machine of quality on labelled documents, sparse rows of tokens."""
    rows = svm_rows(spark, sf_dir)
    release(spark)  # executors are to hold the rows' files, and need the room
    return summary(compare(spark, R.SparseColumns(rows), lambda: O.HingeSvmDual(1.0), rounds=rounds, reference=200, passes=(1, 5)))


def related_schemes(spark: SparkSession, sf_dir: str, rounds: int = 60) -> DataFrame:
    """Rules of related work: shuffled batches, kept informative samples, steepest coordinates, adaptive sampling, hysteresis; and each part's own best.

    Keeping informative samples has no guarantee: once more samples are active than a block holds, it repeats the same ones and log10_best stays where it is.
    """
    return summary(compare(spark, svm_problem(spark, sf_dir), lambda: O.HingeSvmDual(1.0), ("gap_memory", "uniform_batches", "keep_informative", "steepest", "importance_gap", "sticky", "partition_local_top"), rounds, passes=(2,)))


def importance_dense(spark: SparkSession, sf_dir: str, rounds: int = 40) -> DataFrame:
    """Columns of one length: static importance is random selection."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    n2 = columns.norms()
    out = summary(compare(spark, columns, lambda: O.LassoBoxed(lam, b), ("random", "importance_norm", "importance_norm2"), rounds, passes=(2,)))
    return out.withColumn("norm_variation", F.lit(float(n2.std() / n2.mean())))


def importance_text(spark: SparkSession, sf_dir: str, rounds: int = 12) -> DataFrame:
    """Token columns differ much in length, and static importance differs from random selection."""
    columns, y = text_problem(spark, sf_dir)
    lam = 0.1 * R.lambda_max(columns, y)
    n2 = columns.norms()
    out = summary(compare(spark, columns, lambda: O.LassoBoxed(lam, y), ("gap_memory", "random", "importance_norm"), rounds, reference=60, passes=(1,)))
    return out.withColumn("norm_variation", F.lit(float(n2.std() / n2.mean())))


def logistic_text(spark: SparkSession, sf_dir: str, rounds: int = 10) -> DataFrame:
    """L1 logistic regression of quality on tokens through the local model: objective and certificate by round."""
    columns, y = text_problem(spark, sf_dir)
    lam = 0.2 * float(np.abs(columns.products(-0.5 * y)).max())
    runs = [{"rule": s, "run_id": s, "rounds": rounds, "init": "first_pass", "trace": True} for s in ("gap_memory", "sequential", "random")]
    return R.run_grid(spark, columns, lambda: O.LogisticL1(lam, y), runs).select("scheme", "round", "objective", "gap_total", "swaps")


def passes_tuning(spark: SparkSession, sf_dir: str, passes=(1, 2, 3, 5, 10), rounds: int = 200) -> DataFrame:
    """Rounds and modelled seconds to the tolerance for each number of passes of each scheme, on a Lasso and a support vector machine, and which is least."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    out = None
    for model, cols, make in (("lasso", columns, lambda: O.LassoBoxed(lam, b)), ("svm", svm_problem(spark, sf_dir), lambda: O.HingeSvmDual(1.0))):
        log = compare(spark, cols, make, ("gap_memory", "fresh_gap", "random", "sequential", "importance_norm"), rounds, passes=passes)
        rows = M.rounds_to(log).join(M.time_to(log).drop("scheme"), "run_id").select(F.lit(model).alias("model"), "scheme", F.split("run_id", ":")[1].cast("int").alias("passes"), "rounds", F.col("seconds").alias("model_seconds"))
        least = F.first("passes").over(W.partitionBy("scheme").orderBy(F.col("model_seconds").asc_nulls_last(), "passes"))
        rows = cut(rows.withColumn("tuned", F.when(F.min("model_seconds").over(W.partitionBy("scheme")).isNotNull(), least)))
        out = rows if out is None else out.unionByName(rows)
    return out


def svm_cross_validation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out accuracy for each weight, on a planted separator with a tenth of the labels wrong."""
    _, got = best_lam(*separated(spark, sf_dir))
    return spark.createDataFrame([(float(k), float(v)) for k, v in got.items()], "lam double, accuracy double")


def support_tuning(spark: SparkSession, sf_dir: str, wanted: float = 0.12) -> DataFrame:
    """The L1 weight that leaves the wanted share of coordinates away from zero."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = R.lambda_on_path(columns, b, wanted)
    r = R.plain_scd(columns, O.LassoBoxed(lam, b), 200)
    return spark.createDataFrame([(lam, M.support(r.alpha), wanted)], "lam double, support double, wanted double")


def bounds_by_round(spark: SparkSession, sf_dir: str, rounds: int = 10) -> DataFrame:
    """Ridge: what each round leaves, and the most that theory lets it leave."""
    columns, b = poly2_problem(spark, sf_dir)
    obj = O.RidgePrimal(0.5, b)
    best, _, _ = R.optimum(columns, obj, 300, 1e-12)
    rows = []
    for rule in ("fresh_gap", "random"):
        r = R.train(columns, obj, rule, rounds=rounds, best=best, trace=True, theta=True)
        for before, after, block in zip(r.log, r.log[1:], r.blocks):
            bound = T.step_bound(before["subopt"], max(0.0, after["theta"]), after["rho"], obj.smooth, obj.strong, op_norm_sq(columns.fetch(block)), len(block), columns.n)
            rows.append((rule, after["round"], after["subopt"] / before["subopt"], bound / before["subopt"], after["rho"], after["theta"]))
    return spark.createDataFrame(rows, "scheme string, round int, left double, bound double, rho double, theta double")


# --- trainers over tables


def spark_lasso(spark: SparkSession, sf_dir: str, rounds: int = 6, overlap: bool = False, width: int = 1) -> DataFrame:
    """Gap-memory training with a coordinate table as the slow tier: gaps are Spark jobs, only swapped columns are fetched."""
    coords = cut(X.emb_poly2(spark, sf_dir))
    d = coords.select(F.size("vals")).first()[0]
    target = X.planted_target(coords).orderBy("row_id").toArrow()["target"].to_numpy()
    columns = R.SparkColumns(coords, d)
    obj = O.LassoBoxed(0.1 * R.lambda_max(columns, target), target)  # a scan; the weight for a support takes many passes
    r = R.train(columns, obj, rounds=rounds, init="first_pass", refresh_fraction=0.25, overlap=overlap, width=width, run_id="table")
    return spark.createDataFrame(pa.Table.from_pylist(r.log)).select(*[F.col(f.name).cast(f.dataType) for f in ROUND_LOG])


def overlapped_lasso(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark_lasso(spark, sf_dir, 4, overlap=True)


def wide_lasso(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of coordinates updated from one residual, with the guard."""
    return spark_lasso(spark, sf_dir, 4, width=32)


def tiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    columns, b = poly2_problem(spark, sf_dir)
    r = R.tiered_train(columns, O.LassoBoxed(lasso_lam(columns, b), b), rounds=8, init="first_pass")
    return spark.createDataFrame([(x["round"], x["objective"], x["swaps"]) for x in r.log], "round int, objective double, swaps long")


LOG = "scheme string, round int, objective double, gap_total double, swaps long, refreshed long, bytes_in long, mean_age double"


def logged(spark: SparkSession, log: list[dict]) -> DataFrame:
    return spark.createDataFrame([(x["scheme"], x["round"], x["objective"], x["gap_total"], x["swaps"], x["refreshed"], x["bytes_in"], x["mean_age"]) for x in log], LOG)


def workers(spark: SparkSession, sf_dir: str, combine: str = "average", rounds: int = 4) -> DataFrame:
    """Workers with working sets of their own; a quarter of the memory's buckets is read in a round."""
    return logged(spark, B.bucket_train(signed_samples(spark, sf_dir), O.HingeSvmDual(1.0), X.D64, rounds=rounds, workers=4, combine=combine, trace=True)[2])


def star_scale(spark: SparkSession, sf_dir: str, per_worker: int) -> tuple[DataFrame, O.Objective, int, dict]:
    n = table(spark, sf_dir, "lineitem").count()
    return X.star_samples(spark, sf_dir), O.RidgeDual(0.001 * n), n, {"d": X.STAR_D, "kind": "sparse", "workers": max(4, math.ceil(n / per_worker)), "combine": "add", "k": 1}


def star_ridge(spark: SparkSession, sf_dir: str, rounds: int = 3, per_worker: int = 50_000) -> DataFrame:
    """Dual ridge on line items: as many workers as bound each one's share of samples; only v is common, and a round reads a twentieth of the samples for its memory."""
    samples, obj, _, options = star_scale(spark, sf_dir, per_worker)
    return logged(spark, B.bucket_train(samples, obj, rounds=rounds, refresh_fraction=0.05, refresh_residents=True, trace=True, **options)[2])


def star_schemes(spark: SparkSession, sf_dir: str, rounds: int = 8, tolerance: float = 1e-3, per_worker: int = 50_000) -> DataFrame:
    """Dual ridge on line items to a tolerance: gap memory, sequential, random and importance blocks over workers, and one thread over all samples (sparse rows, in files where its task runs).

    The optimum is the dual of the normal equations, which are small: their sums are taken by Spark. All schemes share one store.
    """
    samples, obj, n, options = star_scale(spark, sf_dir, per_worker)
    store = B.BucketStore(samples, B.buckets_for(options["workers"]), "sparse")
    # the primal of the dual ridge: least squares with a penalty; its value is minus the dual's
    t = X.sparse_sums(store.table, X.STAR_D)  # at most STAR_D squared
    w = np.linalg.solve(t.gram + obj.lam * np.eye(X.STAR_D), t.moment)
    best = -(0.5 * (t.square - 2 * w @ t.moment + w @ t.gram @ w) + 0.5 * obj.lam * float(w @ w))

    def run(rule: str) -> list[dict]:
        return B.bucket_train(store, obj, rule=rule, rounds=rounds, refresh_fraction=0.05, refresh_residents=True, best=best, tolerance=tolerance, run_id=f"{rule}:1", **options)[2]

    def one_thread() -> list[dict]:
        return [x.asDict() for x in own_passes(store.table, obj, X.STAR_D, 6, best, tolerance).collect()]  # a row for each pass

    nnz = len(X.STAR_NUMERIC) + 6
    jobs = [lambda rule=rule: run(rule) for rule in ("gap_memory", "sequential", "random", "importance_norm")]
    jobs.insert(0, one_thread)  # the longest
    # a round is many short jobs, so the schemes' rounds go on side by side
    with ThreadPoolExecutor(len(jobs)) as pool:
        rows = [x for log in pool.map(inheritable_thread_target(spark)(lambda job: job()), jobs) for x in log]
    log = spark.createDataFrame(pa.Table.from_pylist(rows)).select(*[F.col(f.name).cast(f.dataType) for f in ROUND_LOG])
    return summary(modelled(log, n, nnz, 12 * nnz), tolerance)


def own_passes(samples: DataFrame, obj: O.Objective, d: int, k: int, best: float, tolerance: float) -> DataFrame:
    """Log of one thread over all samples (sparse rows of one length), which is a task of its own: rows and state are in files of its temporary folder."""
    R.ship(samples.sparkSession)
    kind, n = to_arrow_schema(ROUND_LOG), samples.agg(F.max("coord_id")).first()[0] + 1

    def work(batches):
        with tempfile.TemporaryDirectory(prefix="rows-", ignore_cleanup_errors=True) as folder:
            rows = R.EvenColumns(n, d, folder)
            for b in batches:
                if b.num_rows:
                    rows.put(b.column(0).to_numpy(), *(b.column(i).flatten().to_numpy().reshape(b.num_rows, -1) for i in (1, 2)), b.column(3).to_numpy())
            log = R.plain_scd(rows.filled(), obj, k, best=best, tolerance=tolerance, run_id="plain_scd:1").log
        yield from pa.Table.from_pylist(log, kind).to_batches()

    return samples.select("coord_id", "idx", "vals", "y").coalesce(1).mapInArrow(work, ROUND_LOG)


def star_lasso(spark: SparkSession, sf_dir: str, rounds: int = 4, budget: float = 0.25, most_bytes: int = 128 << 20) -> DataFrame:
    """Lasso on the transposed star: features as coordinates, sparse columns over line items; the block is a share of the coordinates.

    Columns are as long as the table, so trainers over buckets take them (v is checked before it is broadcast). Where all of
    them are over most_bytes they are turned, which leaves every value, gap and step the same: no column and no v is as long
    as the table then.
    """
    options = {"rounds": rounds, "fraction": budget, "refresh_fraction": 0.25, "workers": 2, "combine": "average", "trace": True}
    if 12 * (len(X.STAR_NUMERIC) + 6) * table(spark, sf_dir, "lineitem").count() > most_bytes:
        cells, target = turned_star(spark, sf_dir)
        top = greatest_product(cells, -target, "dense")
        return logged(spark, B.bucket_train(cells, O.LassoBoxed(0.05 * top, target), len(target), **options)[2])
    s = X.star_features(spark, sf_dir)
    cells = cut(s.select("coord_id", "idx", "vals"))
    target = X.star_target(spark, sf_dir)
    mid = target.mean()
    top = greatest_product(cells, mid - target)
    r = B.bucket_train(cells, O.LassoBoxed(0.05 * top, target - mid), len(target), kind="sparse", **options)
    return logged(spark, r[2])


def turned_star(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, np.ndarray]:
    """Features of the star as dense coordinates of as many numbers as there are features and a target, bytes being those of their own cells; the target less its mean, turned alike."""
    t = X.sparse_sums(X.star_rows(spark, sf_dir, table(spark, sf_dir, "lineitem")), X.STAR_D)
    own = np.flatnonzero(t.cells)  # columns of no cell are left out
    side = np.append(t.moment - t.mean * t.total, 0.0)[np.append(own, -1)]
    gram = np.zeros((len(own) + 1, len(own) + 1))
    gram[:-1, :-1] = t.gram[np.ix_(own, own)]
    gram[-1] = gram[:, -1] = side
    gram[-1, -1] = t.square - t.n * t.mean * t.mean
    columns, target = R.RotatedColumns.of(gram, t.n)
    d = columns.x.shape[1]
    vals = pa.ListArray.from_arrays(pa.array(np.arange(len(own) + 1, dtype=np.int32) * d), pa.array(columns.x.ravel()))
    return spark.createDataFrame(pa.table({"coord_id": own, "vals": vals, "bytes": 12 * t.cells[own].astype(np.int64)})), target[0]


def greatest_product(cells: DataFrame, w: np.ndarray, kind: str = "sparse") -> float:
    return G.dots(cells, w, kind).agg(F.max(F.abs("u"))).first()[0]


def normal_equations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ridge on two features, trained by single exact coordinates to the end."""
    e = X.emb_cells(spark, sf_dir).where("coord_id < 2")
    t = e.orderBy("coord_id", "row_id").toArrow()
    x = t["x"].to_numpy().reshape(2, -1)
    rows = t["row_id"].to_numpy().reshape(2, -1)[0]
    b = np.array([unit_py("b", int(r)) * 2 - 1 for r in rows])
    r = R.train(R.LocalColumns(x), O.RidgePrimal(0.5, b), "single", m=1, rounds=200)
    return spark.createDataFrame([(i, float(a)) for i, a in enumerate(r.alpha)], "coord_id long, alpha double").select("coord_id", F.round("alpha", 6).alias("alpha"))


def normal_equations_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ridge on all features over all rows, trained by passes over all of them until the certificate is next to nothing."""
    ids, x = X.matrix(X.emb_samples(spark, sf_dir).select("coord_id", "vals"))
    b = np.array([unit_py("b", int(r)) * 2 - 1 for r in ids])
    r = R.train(R.LocalColumns(x.T), O.RidgePrimal(0.5, b), "sequential", fraction=1.0, rounds=500, trace=True, gap_tolerance=1e-16)
    return spark.createDataFrame([(i, float(a)) for i, a in enumerate(r.alpha)], "coord_id long, alpha double").select("coord_id", F.round("alpha", 6).alias("alpha"))

def all_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every model trained by gap memory: objective and certificate at the start and the end."""
    columns, b = poly2_problem(spark, sf_dir)
    lam = lasso_lam(columns, b)
    whole, labels = poly2_signs(spark, sf_dir, columns, b)
    samples = svm_problem(spark, sf_dir)
    sign = np.sign(samples.x[:, 0])
    makers = [
        (columns, O.RidgePrimal(0.5, b)), (columns, O.LassoBoxed(lam, b)), (columns, O.ElasticNet(lam, b, 0.5)), (whole, O.LogisticL1(lam, labels)),
        (samples, O.HingeSvmDual(1.0)), (samples, O.SquaredHingeSvmDual(1.0)), (samples, O.LogisticDual(1.0)), (R.LocalColumns(samples.x, sign), O.RidgeDual(0.5)),
    ]
    rows = []
    for cols, obj in makers:
        r = R.train(cols, obj, rounds=12, init="first_pass", trace=True)
        rows.append((obj.name, r.log[0]["objective"], r.log[-1]["objective"], r.log[1]["gap_total"], r.log[-1]["gap_total"], M.support(r.alpha)))
    return spark.createDataFrame(rows, "model string, start double, end double, first_gap double, last_gap double, support double")


def claim(name: str, run, tests: dict) -> None:
    """Register what a run must show, as rows (claim, holds), and the same in SQL."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = run(spark, sf_dir).toPandas()  # a row for each round or model
        return spark.createDataFrame([(text, bool(test(p))) for text, test in tests.items()], "claim string, holds boolean")

    QUERIES[f"run_{name}"] = query
    SQL[f"run_{name}"] = " UNION ALL ".join(f"SELECT '{text}' AS claim, true AS holds" for text in tests)


def falls(p) -> bool:
    """The objective never rises, round by round of each scheme."""
    p = p.sort_values("round")
    return all((g["objective"].diff().dropna() <= 1e-9 * g["objective"].abs().max()).all() for _, g in (p.groupby("scheme") if "scheme" in p else [("", p)]))


def shares(p) -> bool:
    """Fresh-gap blocks hold their part of the gap at least, and no more than all of it."""
    rho = p[(p["scheme"] == "fresh_gap") & (p["round"] > 0)]["rho"].dropna()
    return len(rho) > 0 and rho.between(1 - 1e-9, 4.1).all()


def sooner(p) -> bool:
    """After all rounds fresh-gap blocks leave less than random ones."""
    last = p.sort_values("round").groupby("run_id")["subopt"].last()
    return all(v < last[k.replace("fresh_gap", "random")] for k, v in last.items() if k.startswith("fresh_gap"))


QUERIES = {
    f"run_{f.__name__}": f
    for f in (validation_speedup, staleness_sweep, swap_series, lasso_schemes, svm_schemes, text_svm_schemes, ridge_schemes, related_schemes, importance_dense, importance_text, logistic_text, passes_tuning, spark_lasso, star_ridge, star_schemes, star_lasso, normal_equations, normal_equations_whole)
}
SQL = {
    "run_normal_equations": """
WITH x AS (SELECT vec_id, embedding[1]::DOUBLE AS p, embedding[2]::DOUBLE AS q, (('0x' || substr(md5('b:' || vec_id), 1, 8))::BIGINT + 0.5) / 4294967296.0 * 2 - 1 AS b FROM embeddings),
s AS (SELECT sum(p * p) + 0.5 AS pp, sum(p * q) AS pq, sum(q * q) + 0.5 AS qq, sum(p * b) AS pb, sum(q * b) AS qb FROM x)
SELECT 0::BIGINT AS coord_id, round((qq * pb - pq * qb) / (pp * qq - pq * pq), 6) AS alpha FROM s UNION ALL SELECT 1, round((pp * qb - pq * pb) / (pp * qq - pq * pq), 6) FROM s
""",
}
RISES = "the objective never rises"
claim("validation_ridge", validation_ridge, {"fresh blocks hold between their part and all of the gap": shares, "fresh blocks leave less than random ones": sooner})
claim("validation_dual", validation_dual, {"fresh blocks hold between their part and all of the gap": shares, "fresh blocks leave less than random ones": sooner})
claim("sparse_share", sparse_share, {"the share reaches its greatest": lambda p: p["rho"].max() >= 0.95 * p["greatest"].max(), "the support is smaller than the block": lambda p: p["support"].max() < 0.25})
claim("selection_fidelity", selection_fidelity, {"fresher memories choose blocks more like the oracle": lambda p: p.sort_values("refreshed")["overlap"].is_monotonic_increasing})
claim("svm_cross_validation", svm_cross_validation, {"held-out accuracy is above chance": lambda p: p["accuracy"].max() > 0.6})
claim("support_tuning", support_tuning, {"the support is near the wanted one": lambda p: (p["support"] - p["wanted"]).abs().max() < 0.03})
claim("bounds_by_round", bounds_by_round, {"no round leaves more than the bound": lambda p: (p["left"] <= p["bound"] + 1e-9).all(), "the bound says something": lambda p: (p["bound"] < 1).all()})
claim("overlapped_lasso", overlapped_lasso, {RISES: falls, "the memory is refreshed meanwhile": lambda p: (p[p["round"] > 0]["refreshed"] > 0).all()})
claim("wide_lasso", wide_lasso, {RISES: falls})
claim("tiers", tiers, {RISES: falls})
claim("workers", workers, {RISES: falls, "the certificate falls": lambda p: p["gap_total"].iloc[-1] < p["gap_total"].iloc[0]})
claim("workers_add", lambda spark, sf_dir: workers(spark, sf_dir, "add"), {RISES: falls, "the certificate falls": lambda p: p["gap_total"].iloc[-1] < p["gap_total"].iloc[0]})
claim("all_models", all_models, {"every objective falls": lambda p: (p["end"] < p["start"]).all(), "every certificate falls": lambda p: (p["last_gap"] < p["first_gap"]).all(), "eight models": lambda p: len(p) == 8})
