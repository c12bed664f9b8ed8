"""How a matrix is kept as coordinates: dense rows, sparse rows, chunks of rows, or triples; and the state table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..common import cut

_long, _double, _int = T.LongType(), T.DoubleType(), T.IntegerType()


def _schema(*fields) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields])


DENSE = _schema(("coord_id", _long), ("vals", T.ArrayType(_double)))
SPARSE = _schema(("coord_id", _long), ("idx", T.ArrayType(_int)), ("vals", T.ArrayType(_double)))
CHUNKED = _schema(("coord_id", _long), ("chunk", _int), ("vals", T.ArrayType(_double)))
COO = _schema(("coord_id", _long), ("row_id", _long), ("x", _double))
STATE = _schema(("coord_id", _long), ("bucket", _int), ("alpha", _double), ("z", _double), ("z_round", _int), ("norm2", _double), ("resident", T.BooleanType()), ("nnz", _int))
ROUND_LOG = _schema(
    ("run_id", T.StringType()), ("round", _int), ("scheme", T.StringType()), ("block_size", _long), *[(n, _double) for n in ("objective", "gap_total", "subopt", "rho", "theta", "eta")],
    *[(n, _long) for n in ("swaps", "bytes_in", "refreshed")], *[(n, _double) for n in ("mean_age", "max_age", "t_select", "t_transfer", "t_fast", "t_slow", "t_round")],
)
KINDS = {"dense": DENSE, "sparse": SPARSE, "chunked": CHUNKED, "coo": COO, "state": STATE}


def validate(df: DataFrame, kind: str) -> DataFrame:
    """The layout's columns in its types; raises where one is missing. Float arrays are widened, sums are in double."""
    want = KINDS[kind]
    missing = [f.name for f in want if f.name not in df.columns]
    if missing:
        raise ValueError(f"{kind} layout: missing {missing}")
    return df.select(*[F.col(f.name).cast(f.dataType) for f in want], *[c for c in df.columns if c not in want.names])


def finite(x: Column) -> Column:
    return x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))


def to_coo(df: DataFrame, kind: str, width: int = 65536) -> DataFrame:
    """Triples of the non-zero finite cells; row_id counts from 0."""
    if kind == "coo":
        return df.select("coord_id", "row_id", "x")
    if kind == "sparse":
        out = df.select("coord_id", F.explode(F.arrays_zip("idx", "vals")).alias("e")).select("coord_id", F.col("e.idx").cast("long").alias("row_id"), F.col("e.vals").cast("double").alias("x"))
    else:
        keys = ["coord_id"] + (["chunk"] if kind == "chunked" else [])
        out = df.select(*keys, F.posexplode("vals").alias("p", "x"))
        base = F.col("chunk").cast("long") * width if kind == "chunked" else F.lit(0).cast("long")
        out = out.select("coord_id", (base + F.col("p")).alias("row_id"), F.col("x").cast("double").alias("x"))
    return out.where(finite(F.col("x")) & (F.col("x") != 0))


def to_sparse(coo: DataFrame) -> DataFrame:
    cells = F.array_sort(F.collect_list(F.struct(F.col("row_id").cast("int").alias("i"), "x")))
    return coo.groupBy("coord_id").agg(cells.alias("c")).select("coord_id", F.transform("c", lambda e: e["i"]).alias("idx"), F.transform("c", lambda e: e["x"]).alias("vals"))


def to_chunked(coo: DataFrame, width: int = 65536) -> DataFrame:
    """Every chunk that holds a cell, at full width."""
    placed = coo.select("coord_id", F.floor(F.col("row_id") / width).cast("int").alias("chunk"), F.pmod("row_id", F.lit(width)).cast("int").alias("p"), "x")
    got = placed.groupBy("coord_id", "chunk").agg(F.array_sort(F.collect_list(F.struct("p", "x"))).alias("c"))
    # zeros up to each cell's place, the cell, and zeros after the last one: each cell is touched once
    at = F.transform("c", lambda e: e["p"])
    lead = F.zip_with(F.concat(F.array(F.lit(-1)), F.slice(at, 1, F.size(at) - 1)), "c", lambda q, e: F.concat(F.array_repeat(F.lit(0.0), e["p"] - q - 1), F.array(e["x"])))
    return got.select("coord_id", "chunk", F.concat(F.flatten(lead), F.array_repeat(F.lit(0.0), width - 1 - F.element_at(at, -1))).alias("vals"))


def to_dense(coo: DataFrame, d: int) -> DataFrame:
    return to_chunked(coo, d).select("coord_id", "vals")


def transpose(coo: DataFrame) -> DataFrame:
    """Samples become coordinates and the other way round."""
    return coo.select(F.col("row_id").alias("coord_id"), F.col("coord_id").alias("row_id"), "x")


def bucket_of(key: Column | str, buckets: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int")


def dense_ids(df: DataFrame, *order: str, name: str = "coord_id") -> DataFrame:
    """Ids from 0 without gaps in the order of the columns: ranges are sorted apart, then offset by the counts of those before."""
    ranged = df.repartitionByRange(*[F.col(c) for c in order]).sortWithinPartitions(*order)
    tagged = cut(ranged.withColumn("mono_", F.monotonically_increasing_id()))
    part = F.shiftrightunsigned("mono_", 33)
    counts = tagged.groupBy(part.alias("part_")).agg(F.count(F.lit(1)).alias("n_"))
    before = F.coalesce(F.sum("n_").over(W.orderBy("part_").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return tagged.withColumn("part_", part).join(counts.select("part_", before.alias("off_")), "part_").withColumn(name, F.col("off_") + F.col("mono_").bitwiseAND(F.lit((1 << 33) - 1))).drop("mono_", "part_", "off_", "n_")


def init_state(coords: DataFrame, kind: str = "dense", buckets: int = 64) -> DataFrame:
    """State of all coordinates at zero."""
    vals = F.col("vals") if kind != "coo" else None
    if kind in ("coo", "chunked"):
        cells = to_coo(coords, kind).groupBy("coord_id").agg(F.sum(F.col("x") * F.col("x")).alias("norm2"), F.count(F.lit(1)).cast("int").alias("nnz"))
    else:
        norm2 = F.aggregate(vals, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
        cells = coords.select("coord_id", norm2.alias("norm2"), F.size(F.filter(vals, lambda x: x != 0)).alias("nnz"))
    zero = F.lit(0.0)
    return cells.select("coord_id", bucket_of("coord_id", buckets).alias("bucket"), zero.alias("alpha"), zero.alias("z"), F.lit(0).alias("z_round"), "norm2", F.lit(False).alias("resident"), "nnz")
