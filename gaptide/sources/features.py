"""Feature recipes on the given tables, all deterministic, as coordinate layouts."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..common import cut, hash32, ship, table, unit_draw
from ..operators.layout import dense_ids
from ..operators.solve import SparseRows, StoredRows, _parts

D64 = 64


def emb_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples as coordinates: coord_id, vals (64), label."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("coord_id"), F.col("embedding").cast("array<double>").alias("vals"), "label")


def emb_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Features as coordinates, triples: coord_id 0..63, row_id = vec_id, x."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("row_id"), F.posexplode("embedding").alias("p", "x")).select(F.col("p").cast("long").alias("coord_id"), "row_id", F.col("x").cast("double").alias("x"))


def poly2(vals: Column, d: int = D64) -> Column:
    """The values and their products of pairs i <= j, in that order."""
    pairs = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.transform(F.slice(vals, i + 1, d), lambda x: x * F.get(vals, i))))
    return F.concat(vals, pairs)


def emb_poly2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """2,144 features as coordinates (coord_id, vals over the vectors in order of vec_id), centred and of length 1."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(poly2(F.col("embedding").cast("array<double>"))).alias("c", "x"))
    cells = F.array_sort(F.collect_list(F.struct("vec_id", "x")))
    x = F.col("x")
    got = rows.groupBy(F.col("c").cast("long").alias("coord_id")).agg(cells.alias("cells"), F.avg("x").alias("mean"), F.sqrt(F.sum(x * x) - F.count("x") * F.avg("x") * F.avg("x")).alias("norm"))
    return got.select("coord_id", F.transform("cells", lambda e: F.when(F.col("norm") > 0, (e["x"] - F.col("mean")) / F.col("norm")).otherwise(0.0)).alias("vals"))


def standardize(vals: Column) -> Column:
    """Less their mean, which is taken once: it is bound before the values are gone through again."""
    return F.aggregate(vals, F.lit(0.0), lambda s, x: s + x, lambda s: F.transform(vals, lambda x: x - s / F.size(vals)))


def unit_norm(vals: Column) -> Column:
    return F.aggregate(vals, F.lit(0.0), lambda s, x: s + x * x, lambda s: F.transform(vals, lambda x: F.when(s > 0, x / F.sqrt(s)).otherwise(0.0)))


def add_intercept(vals: Column) -> Column:
    return F.concat(vals, F.array(F.lit(1.0)))


def signed(part: str, key: Column | int, seed: int) -> Column:
    """A draw within -1 and 1."""
    return unit_draw(f"{part}{seed}", key) * 2 - 1


def planted_alpha(ids: DataFrame, density: float = 0.03, seed: int = 1) -> DataFrame:
    """coord_id, alpha: a few coordinates away from zero."""
    c = F.col("coord_id")
    return ids.select("coord_id", F.when(unit_draw(f"d{seed}", c) < density, signed("a", c, seed) * 2).otherwise(0.0).alias("alpha"))


def planted_target(coords: DataFrame, seed: int = 1, density: float = 0.03, noise: float = 0.01) -> DataFrame:
    """row_id, target: the planted weights' product with dense coordinates, plus noise."""
    used = planted_alpha(coords, density, seed).where("alpha <> 0")
    cells = coords.join(used, "coord_id").select(F.posexplode("vals").alias("p", "x"), "alpha")
    rows = cells.groupBy(F.col("p").cast("long").alias("row_id")).agg(F.sum(F.col("x") * F.col("alpha")).alias("t"))
    return rows.select("row_id", (F.col("t") + noise * signed("n", F.col("row_id"), seed)).alias("target"))


#: Numeric columns of the star and how they are scaled.
STAR_NUMERIC = (("l_quantity", 50.0), ("l_discount", 0.1), ("l_tax", 0.08), ("p_retailprice", 1000.0), ("p_size", 50.0))


def star_rows(spark: SparkSession, sf_dir: str, line: DataFrame, *keep: str) -> DataFrame:
    """Line items joined with their dimensions: columns to keep, idx and vals (sparse), y. Categories are hashed in the dimensions, so that no text is dealt with the line items."""
    base, span = len(STAR_NUMERIC), 64  # each category has a range of its own; categories are hashed within it
    hot = ("brand", "type", "segment", "nation", "priority", "month")
    place = lambda name, c: (F.lit(base + span * hot.index(name)) + F.pmod(hash32(name, F.coalesce(c, F.lit(""))), F.lit(span))).cast("int").alias(name)
    part = table(spark, sf_dir, "part").select("p_partkey", place("brand", F.col("p_brand")), place("type", F.col("p_type")), "p_size", "p_retailprice")
    supp = table(spark, sf_dir, "supplier").select("s_suppkey", place("nation", F.col("s_nationkey").cast("string")))
    cust = table(spark, sf_dir, "customer").select("c_custkey", place("segment", F.col("c_mktsegment")))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", place("priority", F.col("o_orderpriority"))).join(cust, F.col("o_custkey") == F.col("c_custkey"), "left").select("o_orderkey", "priority", "segment")
    rows = line.select(*keep, "l_partkey", "l_suppkey", "l_orderkey", "l_quantity", "l_discount", "l_tax", "l_extendedprice", place("month", F.month("l_shipdate").cast("string")))
    joined = rows.join(part, rows.l_partkey == part.p_partkey).join(supp, rows.l_suppkey == supp.s_suppkey).join(orders, rows.l_orderkey == orders.o_orderkey, "left")
    idx = F.array(*[F.lit(i) for i in range(base)], *[F.coalesce(F.col(name), place(name, F.lit(""))) for name in hot])
    vals = F.array(*[F.coalesce(F.col(n).cast("double") / s, F.lit(0.0)) for n, s in STAR_NUMERIC], *[F.lit(1.0)] * len(hot))
    return joined.select(*keep, idx.alias("idx"), vals.alias("vals"), (F.col("l_extendedprice") / 100000.0).alias("y"))


def star_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items as samples: coord_id (rank over all columns), idx and vals (sparse), y. The line item is read once and pruned."""
    line = table(spark, sf_dir, "lineitem")
    return star_rows(spark, sf_dir, dense_ids(line, *line.columns), "coord_id")


STAR_D = len(STAR_NUMERIC) + 64 * 6


def star_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star transposed: coord_id (feature), idx (rank of the line item) and vals; columns of no cell are left out."""
    s = star_samples(spark, sf_dir).select(F.col("coord_id").cast("int").alias("i"), F.explode(F.arrays_zip("idx", "vals")).alias("e"))
    cells = F.array_sort(F.collect_list(F.struct("i", F.col("e.vals").alias("x"))))
    got = s.where("e.vals <> 0").groupBy(F.col("e.idx").cast("long").alias("coord_id")).agg(cells.alias("c"))
    return got.select("coord_id", F.transform("c", lambda e: e["i"]).alias("idx"), F.transform("c", lambda e: e["x"]).alias("vals"))


def star_target(spark: SparkSession, sf_dir: str, most: int = 10_000_000) -> np.ndarray:
    """Target of each line item in order of its rank, for the driver: at most so many."""
    t = star_samples(spark, sf_dir).select("coord_id", "y")
    n = t.count()
    if n > most:
        raise ValueError(f"{n} targets are too many for the driver")
    got = t.toArrow()
    out = np.zeros(n)
    out[got["coord_id"].to_numpy()] = got["y"].to_numpy()
    return out


@dataclass
class Sums:
    """Products of all pairs of features over rows, and of each with the target y and with 1; places of a feature other than zero; products of y and 1."""

    gram: np.ndarray
    moment: np.ndarray
    total: np.ndarray
    cells: np.ndarray
    square: float
    mean: float
    n: int


def sparse_sums(rows: DataFrame, d: int, batch: int = 4096) -> Sums:
    """Sums over rows idx, vals (of one length) and y, in one scan. A task holds one square of the number of features, which is what it sends on; nothing grows with the rows."""
    ship(rows.sparkSession)
    side = d + 2  # features, y, 1

    def squares(batches):
        total, places = np.zeros(side * side), np.zeros(side)
        for whole in batches:
            for at in range(0, whole.num_rows, batch):
                b = whole.slice(at, batch)
                k = b.num_rows
                idx, vals = b.column(0).flatten().to_numpy().reshape(k, -1).astype(np.int64), b.column(1).flatten().to_numpy().reshape(k, -1)
                idx, vals = np.concatenate((idx, np.full((k, 1), d), np.full((k, 1), d + 1)), axis=1), np.concatenate((vals, b.column(2).to_numpy()[:, None], np.ones((k, 1))), axis=1)
                p, q = np.triu_indices(idx.shape[1])
                total += np.bincount((idx[:, p] * side + idx[:, q]).ravel(), (vals[:, p] * vals[:, q]).ravel(), side * side)
                places += np.bincount(idx[vals != 0], minlength=side)
        at, own = np.flatnonzero(total), np.flatnonzero(places)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate((at, side * side + own)), pa.int64()), pa.array(np.concatenate((total[at], places[own])), pa.float64())], ["i", "x"])

    t = rows.select("idx", "vals", "y").mapInArrow(squares, "i long, x double").groupBy("i").agg(F.sum("x").alias("x")).toArrow()  # at most one square
    flat = np.zeros(side * side + side)
    flat[t["i"].to_numpy()] = t["x"].to_numpy()
    gram = flat[: side * side].reshape(side, side)
    gram = gram + gram.T - np.diag(np.diag(gram))  # a pair is in one of the two places, whatever the order of a row
    n = int(gram[d + 1, d + 1])
    return Sums(gram[:d, :d], gram[d, :d], gram[d + 1, :d], flat[side * side :][:d], float(gram[d, d]), float(gram[d, d + 1] / max(1, n)), n)


def tokens(docs: DataFrame) -> DataFrame:
    """doc_id, token: words of letters, lower case."""
    return docs.select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("token")).where("token <> ''")


def doc_tf(spark: SparkSession, sf_dir: str, least_docs: int = 5) -> DataFrame:
    """coord_id (rank of the token), token, row_id (doc_id), x: counts of tokens in at least so many documents, labelled documents only."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text").repartition("doc_id")  # so that texts are dealt and not their tokens
    count = lambda d: tokens(d).groupBy("doc_id", "token").agg(F.count(F.lit(1)).cast("double").alias("x"))
    df = count(docs).groupBy("token").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= least_docs)
    ids = dense_ids(df.select("token"), "token")
    labelled = table(spark, sf_dir, "labels", "doc_id")
    return count(docs.join(labelled, "doc_id", "left_semi")).join(ids, "token").select("coord_id", "token", F.col("doc_id").alias("row_id"), "x")


def doc_hash(spark: SparkSession, sf_dir: str, bits: int = 12) -> DataFrame:
    """row_id (doc_id), coord_id (hashed token), x: signed counts in 2**bits features; no vocabulary is needed."""
    t = tokens(table(spark, sf_dir, "documents", "doc_id", "text"))
    h = hash32("tok", F.col("token"))
    return t.select("doc_id", F.pmod(h, F.lit(1 << bits)).alias("coord_id"), F.when(F.shiftright(h, 31) == 1, 1.0).otherwise(-1.0).alias("s")).groupBy(F.col("doc_id").alias("row_id"), "coord_id").agg(F.sum("s").alias("x"))


def doc_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, c = F.coalesce("text", F.lit("")), F.length
    return table(spark, sf_dir, "documents").select("doc_id", c(t).alias("chars"), F.regexp_count(t, F.lit(r"[^\x20\x09-\x0D]+")).cast("long").alias("words"), (F.regexp_count(t, F.lit("\n")) + 1).cast("long").alias("lines"), F.regexp_count(t, F.lit("[0-9]")).cast("long").alias("digits"), F.regexp_count(t, F.lit("[A-Z]")).cast("long").alias("capitals"))


def event_user_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    kinds = ("view", "click", "purchase")
    return e.groupBy("user_id").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("value"), 6).alias("value"), F.round(F.avg(F.hour("ts")), 6).alias("mean_hour"), F.round(F.avg(F.get_json_object("props", "$.k").cast("double")), 6).alias("mean_k"), *[F.sum(F.when(F.col("event_type") == k, 1).otherwise(0)).alias(f"n_{k}") for k in kinds])


def page_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = F.coalesce("html", F.lit(""))
    return table(spark, sf_dir, "pages").select("page_id", F.length(h).alias("chars"), F.regexp_count(h, F.lit("<a ")).cast("long").alias("links"), F.regexp_count(h, F.lit("<p>")).cast("long").alias("paragraphs"), F.regexp_extract("url", "^https?://([^/?#]+)", 1).alias("host"))


def conv_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return c.groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns"), F.sum(F.length("text")).alias("chars"), F.sum(F.when(F.col("role") == "user", 1).otherwise(0)).alias("user_turns"))


def benchmark_overlap(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """doc_id and how many distinct word n-grams it shares with benchmark items. Item n-grams are few, documents are many: a semi-join."""
    grams = lambda c: F.transform(F.sequence(F.lit(1), F.greatest(F.size(c) - n + 1, F.lit(1))), lambda i: F.concat_ws(" ", F.slice(c, i, n)))
    ws = lambda t: F.filter(F.split(F.lower(t), r"[\x20\x09-\x0D]+"), lambda x: x != "")
    items = table(spark, sf_dir, "benchmark").select(ws(F.col("text")).alias("w")).where(F.size("w") >= n).select(F.explode(grams(F.col("w"))).alias("g")).distinct()
    docs = table(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", ws(F.col("text")).alias("w")).where(F.size("w") >= n).select("doc_id", F.explode(grams(F.col("w"))).alias("g"))
    return docs.join(items, "g", "left_semi").distinct().groupBy("doc_id").agg(F.count(F.lit(1)).alias("shared"))


def doc_svm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents as samples: coord_id (doc_id), idx and vals (tokens, logarithms of counts, length 1), y (quality as -1 and 1)."""
    coo = doc_tf(spark, sf_dir).select(F.col("row_id").alias("coord_id"), F.col("coord_id").cast("int").alias("i"), F.log1p("x").alias("x"))
    rows = coo.groupBy("coord_id").agg(F.sort_array(F.collect_list(F.struct("i", "x"))).alias("c"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("coord_id"), F.when(F.col("quality") == 1, 1.0).otherwise(-1.0).alias("y"))
    return rows.join(labels, "coord_id").select("coord_id", F.transform("c", lambda e: e["i"]).alias("idx"), F.transform("c", lambda e: e["x"] / F.col("norm")).alias("vals"), "y")


def sparse_rows(rows: DataFrame, sizes: DataFrame, key: str, cells: Callable[[pa.Table], tuple[np.ndarray, np.ndarray]], d: int, most_bytes: int = 256 << 20, entries: int = 1 << 21) -> SparseRows:
    """Rows of a table, in order of the key, as a sparse matrix. sizes: key and n, the number of entries; cells: indices and values of a part of the table, which comes in order of the key.

    Parts of a bounded number of entries come to this process one after the other. Over most_bytes they go to files of its
    temporary folder; a number for each row is all that it holds.
    """
    t = sizes.select(key, "n").orderBy(key).toArrow()
    ids, ptr = t[key].to_numpy(), np.concatenate(([0], np.cumsum(t["n"].to_numpy()))).astype(np.int64)
    stored = 12 * int(ptr[-1]) > most_bytes
    folder = tempfile.mkdtemp(prefix="rows-") if stored else ""
    path = f"{folder}/{uuid.uuid4().hex}"
    if stored:
        atexit.register(shutil.rmtree, folder, True)  # tasks may fetch the files until then
        ptr.tofile(f"{path}.ptr")
        idx, vals = np.memmap(f"{path}.idx", np.int32, "w+", shape=int(ptr[-1])), np.memmap(f"{path}.vals", np.float64, "w+", shape=int(ptr[-1]))
    else:
        idx, vals = np.empty(ptr[-1], np.int32), np.empty(ptr[-1])
    for a, b in _parts(ptr, entries):
        got = cells(rows.where(F.col(key).between(int(ids[a]), int(ids[b - 1]))).toArrow())
        idx[ptr[a] : ptr[b]], vals[ptr[a] : ptr[b]] = got
    if not stored:
        return SparseRows(ptr, idx, vals, d)
    idx.flush()
    vals.flush()
    return StoredRows(path, d)


def train_test_split(key: Column, share: float = 0.8, seed: int = 0) -> Column:
    """Whether a row is for training: a hash of its key."""
    return unit_draw(f"split{seed}", key) < share


def event_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """coord_id, vals (8) and y (1 for a purchase, else -1)."""
    e = table(spark, sf_dir, "events")
    one = [F.when(F.col("event_type") == k, 1.0).otherwise(0.0) for k in ("view", "click", "cart", "search", "purchase")]
    hour, day = F.hour("ts") / 24.0, F.dayofweek("ts") / 7.0
    return e.select(F.col("event_id").alias("coord_id"), F.array(*one[:4], F.get_json_object("props", "$.k").cast("double") / 100.0, hour, day, F.lit(1.0)).alias("vals"), F.when(F.col("event_type") == "purchase", 1.0).otherwise(-1.0).alias("y"))


def poly2_np(e: np.ndarray) -> np.ndarray:
    """Rows of values and their products of pairs i <= j, in the order of poly2."""
    i, j = np.triu_indices(e.shape[1])
    return np.concatenate((e, e[:, i] * e[:, j]), axis=1)


def poly2_gram(spark: SparkSession, sf_dir: str, seed: int = 1, d: int = D64, batch: int = 2048) -> tuple[np.ndarray, int]:
    """Products of all pairs of the features of emb_poly2, and of each with the noise of planted_target (last row and column); the number of rows.

    Two scans of the vectors: means, then products of what is less its mean. A task holds one square of the number of
    features, as do the driver and what each task sends on; nothing grows with the rows.
    """
    ship(spark)
    ranked = dense_ids(table(spark, sf_dir, "embeddings").where("embedding is not null").select("vec_id", F.col("embedding").cast("array<double>").alias("vals")), "vec_id")
    rows = cut(ranked.select("vals", signed("n", F.col("coord_id"), seed).alias("noise"))).coalesce(max(1, spark.sparkContext.defaultParallelism))

    def parts(batches):
        for b in batches:
            for at in range(0, b.num_rows, batch):
                part = b.slice(at, batch)
                yield poly2_np(part.column(0).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, d)), part.column(1).to_numpy()

    def sums(batches):
        total, n = 0.0, 0
        for x, _ in parts(batches):
            total, n = total + x.sum(axis=0), n + len(x)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(range(len(total) + 1), pa.int32()), pa.array(np.append(total, n), pa.float64())], ["i", "x"])

    t = rows.mapInArrow(sums, "i int, x double").groupBy("i").agg(F.sum("x").alias("x")).orderBy("i").toArrow()["x"].to_numpy()  # a number for each feature
    n = int(t[-1])
    sent = spark.sparkContext.broadcast(t[:-1] / n)

    def squares(batches):
        gram = None
        for x, noise in parts(batches):
            x = np.concatenate((x - sent.value, noise[:, None]), axis=1)
            gram = x.T @ x if gram is None else gram + x.T @ x
        for i in range(0 if gram is None else len(gram)):
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([gram[i, i:]], pa.list_(pa.float64()))], ["i", "x"])

    def added(group: pa.Table) -> pa.Table:
        total = sum(c.flatten().to_numpy().reshape(len(c), -1).sum(axis=0) for c in group["x"].chunks)
        return pa.table({"i": group["i"][:1], "x": pa.array([total], pa.list_(pa.float64()))})

    got = rows.mapInArrow(squares, "i int, x array<double>").groupBy("i").applyInArrow(added, "i int, x array<double>").toArrow()
    gram = np.zeros((got.num_rows, got.num_rows))
    for i, x in zip(got["i"].to_pylist(), got["x"]):
        gram[i, i:] = x.values.to_numpy()
    gram += np.triu(gram, 1).T
    norm = np.append(np.sqrt(np.maximum(np.diag(gram)[:-1], 0.0)), 1.0)
    scale = np.where(norm > 0, 1 / np.where(norm > 0, norm, 1.0), 0.0)
    return gram * scale[:, None] * scale, n


def matrix(coords: DataFrame, most_bytes: int = 256 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Ids and rows of dense coordinates, in order of id, after a check of their size."""
    n, d = coords.agg(F.count(F.lit(1)), F.max(F.size("vals"))).first()
    if n * (d or 0) * 8 > most_bytes:
        raise ValueError(f"{n} x {d} is too large for one process")
    t = coords.select("coord_id", "vals").orderBy("coord_id").toArrow().combine_chunks()
    flat = t["vals"].combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return t["coord_id"].to_numpy(), flat.reshape(n, -1).astype(np.float64)
