"""Matrix files: LIBSVM, CSV and JSON, bucketed and sequential stores, and a data source of planted matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.layout import DENSE, bucket_of


def write_libsvm(sparse: DataFrame, path: str, target: str = "y") -> None:
    """One line for each row: target, then index:value from 1 on."""
    cells = F.transform(F.arrays_zip("idx", "vals"), lambda e: F.concat((e["idx"] + 1).cast("string"), F.lit(":"), e["vals"].cast("string")))
    sparse.select(F.concat_ws(" ", F.col(target).cast("string"), F.concat_ws(" ", cells)).alias("value")).write.text(path)


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    """y, idx, vals of each line; without ids, which the format lacks."""
    parts = F.split(F.trim("value"), " +")
    cells = F.transform(F.slice(parts, 2, 1 << 30), lambda c: F.struct((F.split(c, ":")[0].cast("int") - 1).alias("i"), F.split(c, ":")[1].cast("double").alias("x")))
    rows = spark.read.text(path).where("trim(value) <> ''").select(parts[0].cast("double").alias("y"), cells.alias("c"))
    return rows.select("y", F.transform("c", lambda e: e["i"]).alias("idx"), F.transform("c", lambda e: e["x"]).alias("vals"))


def write_csv(dense: DataFrame, path: str) -> None:
    dense.select("coord_id", F.concat_ws(";", F.transform("vals", lambda x: x.cast("string"))).alias("vals")).write.option("header", True).csv(path)


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    rows = spark.read.schema("coord_id long, vals string").option("header", True).csv(path)
    return rows.select("coord_id", F.transform(F.split("vals", ";"), lambda x: x.cast("double")).alias("vals"))


def write_json(dense: DataFrame, path: str) -> None:
    dense.select("coord_id", "vals").write.json(path)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(DENSE).json(path)


def write_coordinates(df: DataFrame, path: str, buckets: int = 64) -> None:
    """Files by hash bucket, sorted by id: a bucket is a fair sample, and a block's ids prune row groups."""
    df.withColumn("bucket", bucket_of("coord_id", buckets)).repartition("bucket").sortWithinPartitions("bucket", "coord_id").write.partitionBy("bucket").parquet(path)


def write_blocks(df: DataFrame, path: str, files: int) -> None:
    """Files of contiguous ids, for blocks that are copied whole."""
    df.repartitionByRange(files, "coord_id").sortWithinPartitions("coord_id").write.parquet(path)


class _PlantedPartition(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__((lo, hi))
        self.lo, self.hi = lo, hi


class _PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.d, self.seed, self.parts = (int(options.get(k, v)) for k, v in (("n", 1000), ("d", 64), ("seed", 0), ("partitions", 4)))

    def partitions(self):
        ends = np.linspace(0, self.n, self.parts + 1).astype(int)
        return [_PlantedPartition(int(a), int(b)) for a, b in zip(ends, ends[1:]) if b > a]

    def read(self, partition):
        for lo in range(partition.lo, partition.hi, 1024):
            ids = np.arange(lo, min(lo + 1024, partition.hi))
            rows = [np.random.default_rng((self.seed, int(i))).standard_normal(self.d) for i in ids]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([(r / np.linalg.norm(r)).tolist() for r in rows], pa.list_(pa.float64()))], ["coord_id", "vals"])


class PlantedMatrixSource(DataSource):
    """spark.dataSource.register(PlantedMatrixSource); spark.read.format("planted").option("n", ...).load(): rows of length 1, the same for any partitioning."""

    @classmethod
    def name(cls):
        return "planted"

    def schema(self):
        return "coord_id long, vals array<double>"

    def reader(self, schema):
        return _PlantedReader(self.options)
