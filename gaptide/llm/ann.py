"""Approximate nearest neighbours by stable projections and a kd-tree.

Vectors are brought to length 1, so that nearness by cosine is nearness by distance, and projected on a few Gaussian (2-stable) directions:
the squared projected distance over the squared true distance follows a chi-square law with as many degrees of freedom. A
kd-tree over the projections gives neighbours in growing projected distance; each is verified on the whole vector, and the search
stops once the law says that a vector still unseen is nearer than the worst kept with less than a set probability. A true
neighbour is passed over with at most that probability; with fewer directions or more confidence more vectors are verified.

Vectors are dealt into blocks, each with its own tree; blocks of queries meet blocks of vectors and the best of each block
are merged. Equal vectors are searched once and spread at the end by their smallest ids, of which no answer needs more.

Cases: vectors that are null, zero, or hold a null or non-finite component take no part; vectors of another length than
the query's are no candidates; null ids take no part; a table with fewer candidates gives all; ties go to the smaller id; an empty table gives an empty table.
"""

from __future__ import annotations

import math
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import cut, ship

LEAF = 64


def chi_square_cdf(x: float, k: int) -> float:
    """Regularised lower incomplete gamma function of k/2 at x/2, by its series."""
    if x <= 0:
        return 0.0
    a, h = k / 2, x / 2
    term = total = 1 / a
    n = a
    while term > total * 1e-12:
        n += 1
        term *= h / n
        total += term
    return min(1.0, total * math.exp(-h + a * math.log(h) - math.lgamma(a)))


def chi_square_quantile(p: float, k: int) -> float:
    lo, hi = 0.0, 10.0 * k + 100
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi_square_cdf(mid, k) < p else (lo, mid)
    return hi


class ProjectionTree:
    """Vectors of one block; leaves of a kd-tree over their projections, as boxes."""

    def __init__(self, unit: np.ndarray, directions: np.ndarray, leaf: int = LEAF):
        p = unit @ directions
        stack, leaves = [np.arange(len(unit))], []
        while stack:
            at = stack.pop()
            if len(at) <= leaf:
                leaves.append(at)
                continue
            axis = int(np.argmax(np.ptp(p[at], axis=0)))
            half = len(at) // 2
            order = at[np.argpartition(p[at, axis], half)]
            stack += [order[:half], order[half:]]
        self.order = np.concatenate(leaves)
        self.ends = np.cumsum([0, *map(len, leaves)])
        self.low = np.array([p[x].min(axis=0) for x in leaves])
        self.high = np.array([p[x].max(axis=0) for x in leaves])
        self.unit, self.projected = unit[self.order], p[self.order]

    def search(self, query: np.ndarray, seen: np.ndarray, k: int, factor: float) -> tuple[np.ndarray, np.ndarray, int]:
        """Places and cosines of the k nearest found, and how many vectors were verified. seen: the query's projection; factor: the law's quantile.

        Leaves come in the order of their boxes' distance, more of them at a time as the search goes on; of their vectors
        only those are verified whose own projected distance the stopping test leaves open.
        """
        gap = np.maximum(np.maximum(self.low - seen, seen - self.high), 0)
        near = np.einsum("ij,ij->i", gap, gap)
        turn = np.argsort(near, kind="stable")
        at, cosine, step, done, verified, limit = np.zeros(0, np.int64), np.zeros(0), 4, 0, 0, np.inf
        while done < len(turn) and near[turn[done]] <= limit:
            some = turn[done : done + step]
            done, step = done + step, min(2 * step, 64)
            rows = np.concatenate([np.arange(self.ends[i], self.ends[i + 1]) for i in some])
            off = self.projected[rows] - seen
            rows = rows[np.einsum("ij,ij->i", off, off) <= limit]
            verified += len(rows)
            at, cosine = np.concatenate((at, rows)), np.concatenate((cosine, self.unit[rows] @ query))
            if len(at) > 4 * k:
                best = np.argpartition(-cosine, 2 * k)[: 2 * k]
                at, cosine = at[best], cosine[best]
            if len(cosine) >= k:
                limit = factor * max(2 - 2 * np.partition(cosine, len(cosine) - k)[len(cosine) - k], 1e-12)
        return self.order[at], cosine, verified


def usable(vectors: DataFrame, key: str, vector: str) -> DataFrame:
    v = F.col(vector).cast("array<double>")
    good = F.col(key).isNotNull() & v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(v, lambda x: x != 0.0)
    return vectors.where(F.coalesce(good, F.lit(False))).select(F.col(key).cast("long").alias("id"), v.alias("v"))


def matrix(column: pa.ChunkedArray, size: int) -> np.ndarray:
    """Rows of a list column of one length, brought to length 1."""
    y = column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, size)
    y = y / np.abs(y).max(axis=1, keepdims=True)
    return y / np.sqrt(np.einsum("ij,ij->i", y, y))[:, None]


def nearest(vectors: DataFrame, is_query: Column, key: str = "vec_id", vector: str = "embedding", k: int = 5, dims: int = 24, confidence: float = 0.95, block: int = 32768, query_block: int = 32768, seed: int = 7, counted: bool = False) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each query among all other rows.

    A block of vectors meets a block of queries in one task, so vectors move once for each query_block queries. counted:
    instead return q, seen and verified, the number of vectors that each searched vector met and verified, block by block.
    """
    spark = vectors.sparkSession
    ship(spark)
    good = usable(vectors, key, vector)
    # Equal vectors: their k+1 smallest ids, found with a limit on each group before the shuffle.
    ranked = good.withColumn("r", F.row_number().over(W.partitionBy("v").orderBy("id"))).where(F.col("r") <= k + 1)
    classes = cut(ranked.groupBy("v").agg(F.array_sort(F.collect_list("id")).alias("ids")).withColumn("rep", F.element_at("ids", 1)))
    queries = good.where(F.expr(is_query) if isinstance(is_query, str) else is_query)
    asked = cut(queries.groupBy("v").agg(F.min("id").alias("q")).join(classes.select("v", "rep"), "v").select("q", "rep", "v"))
    n, m = classes.count(), asked.count()
    # smaller blocks where there would be fewer than cores
    parts, lots = max(1, math.ceil(n / block), min(math.ceil(n / 4096), spark.sparkContext.defaultParallelism)), max(1, math.ceil(m / query_block))
    factor = chi_square_quantile(confidence, dims)

    def dealt(h: Column, many: int) -> Column:
        return F.pmod(F.xxhash64(h), F.lit(many)).cast("int")

    left = classes.select(dealt(F.col("rep"), parts).alias("p"), F.explode(F.sequence(F.lit(0), F.lit(lots - 1))).alias("l"), F.col("rep").alias("i"), "v")
    right = asked.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("p"), dealt(F.col("q"), lots).alias("l"), F.col("q").alias("i"), F.col("v").alias("v"))  # v anew: a column of both sides would come once

    def search(a: pa.Table, b: pa.Table) -> pa.Table:
        asker, found, near, seen, verified = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        lengths = [pc.list_value_length(t["v"]).to_numpy() if t.num_rows else np.zeros(0, np.int64) for t in (a, b)]
        for size in sorted(set(lengths[1].tolist()) & set(lengths[0].tolist())):
            base, ask = a.filter(pa.array(lengths[0] == size)), b.filter(pa.array(lengths[1] == size))
            x, q = matrix(base["v"], size), matrix(ask["v"], size)
            directions = np.random.default_rng(seed).standard_normal((size, dims))
            tree, ids = ProjectionTree(x, directions), base["i"].to_numpy()
            for query, place, i in zip(q, q @ directions, ask["i"].to_numpy()):
                at, cosine, many = tree.search(query, place, k + 1, factor)
                # rounding must not decide among near-equal ones before the exact score does: a few more go on
                best = np.argsort(-cosine, kind="stable")[: 2 * k]
                asker.append(np.full(len(best), i))
                found.append(ids[at[best]])
                near.append(cosine[best])
                seen.append(np.full(len(best), len(x)))
                verified.append(np.full(len(best), many))
        return pa.table({"q": pa.array(np.concatenate(asker), pa.int64()), "rep": pa.array(np.concatenate(found), pa.int64()), "near": pa.array(np.concatenate(near), pa.float64()), "seen": pa.array(np.concatenate(seen), pa.int64()), "verified": pa.array(np.concatenate(verified), pa.int64())})

    found = left.groupBy("p", "l").cogroup(right.groupBy("p", "l")).applyInArrow(search, "q long, rep long, near double, seen long, verified long")
    if counted:
        return found.groupBy("q", "seen", "verified").agg(F.count(F.lit(1)).alias("kept"))
    few = found.withColumn("r", F.row_number().over(W.partitionBy("q").orderBy(F.desc("near"), "rep"))).where(F.col("r") <= 2 * k).select("q", "rep")
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    few = few.join(classes.select("rep", "ids", F.col("v").alias("w")), "rep").join(asked.select("q", "v"), "q")
    few = few.withColumn("score", dot(F.col("v"), F.col("w")) / (F.sqrt(dot(F.col("v"), F.col("v"))) * F.sqrt(dot(F.col("w"), F.col("w")))))
    # All queries with that vector, against the ids of each class.
    answer = few.groupBy("q").agg(F.collect_list(F.struct("score", "ids")).alias("found"))
    each = queries.groupBy("v", "id").agg(F.count(F.lit(1)).alias("n")).join(asked.select("q", "v"), "v").select("q", F.col("id").alias("query_id"))
    flat = each.join(answer, "q").select("query_id", F.explode("found").alias("f")).select("query_id", "f.score", F.explode("f.ids").alias("vec_id")).where(F.col("vec_id") != F.col("query_id"))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return flat.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
