"""Session helpers: tables, shared checkpoints, the package on the workers."""

from __future__ import annotations

import math
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_shipped: set[str] = set()
#: Most numbers in a vector that goes to every executor (80 MB); beyond it the chunked layout joins.
BROADCAST_NUMBERS = 10_000_000


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_checkpoints(spark: SparkSession) -> None:
    """Leave the cluster's checkpoint folder alone; choose one only where none is set (tests)."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoints-"))


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared checkpoint folder."""
    shared_checkpoints(spark)
    return f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/{uuid.uuid4().hex}/{name}"


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage through the shared checkpoint folder, so that a lost executor loses nothing."""
    shared_checkpoints(df.sparkSession)
    return df.checkpoint()


def stash(df: DataFrame, name: str) -> DataFrame:
    """Write a table as Parquet in the shared checkpoint folder and read it again."""
    path = shared_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner remove the shuffle files of finished phases now: nothing refers to them once a lineage is cut."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def ship(spark: SparkSession) -> None:
    """Give the workers this package, once for each application, wherever they run."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="package-"), f"{root.name}.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)


def attach(rows: DataFrame, few: DataFrame, keys: list[str], most: int = 100_000, salts: int = 64) -> DataFrame:
    """rows joined with a table of one row for each key value, without dealing rows by that key.

    Up to `most` counted rows it is broadcast (a few numbers each, some MB at most); beyond it each of its rows is copied
    to every salt, so that one value's rows are spread over so many tasks.
    """
    few = cut(few)
    if few.count() <= most:
        return rows.join(F.broadcast(few), keys)
    copies = few.withColumn("salt_", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("salt_", F.pmod(F.xxhash64(*rows.columns), F.lit(salts)).cast("int")).join(copies, [*keys, "salt_"]).drop("salt_")


def hash32(*parts: Column | str | int) -> Column:
    """32 bits of the MD5 of the parts joined by colons, as a whole number; SQL engines can repeat it."""
    texts = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *texts)), 1, 8), 16, 10).cast("long")


def hash32_py(*parts) -> int:
    import hashlib

    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16)


#: MD5: how far each step turns its sum, and what it adds.
_TURNS = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_ADDED = [int(abs(math.sin(i + 1)) * (1 << 32)) for i in range(64)]


def hash32_np(prefix: str, n: int, part: int = 1 << 15) -> np.ndarray:
    """hash32_py(prefix, i) for i in 0..n-1, many at a time."""
    head, out = f"{prefix}:".encode(), np.empty(n, np.int64)
    if len(head) + len(str(max(n - 1, 0))) > 55:  # more than one block
        return np.array([hash32_py(prefix, i) for i in range(n)], np.int64)
    at = 0
    while at < n:
        digits = len(str(at))
        end = min(n, at + part, 10**digits)
        ids, last = np.arange(at, end), len(head) + digits
        block = np.zeros((end - at, 64), np.uint8)
        block[:, : len(head)] = np.frombuffer(head, np.uint8)
        for d in range(digits):
            block[:, last - 1 - d] = 48 + ids // 10**d % 10
        block[:, last], block[:, 56], block[:, 57] = 128, 8 * last % 256, 8 * last // 256
        words = np.ascontiguousarray(block.view("<u4").T.astype(np.uint32))
        a, b, c, d = (np.full(end - at, x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
        for i, (turn, added) in enumerate(zip(_TURNS, _ADDED)):
            if i < 16:
                f, g = d ^ (b & (c ^ d)), i
            elif i < 32:
                f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
            elif i < 48:
                f, g = b ^ c ^ d, (3 * i + 5) % 16
            else:
                f, g = c ^ (b | ~d), 7 * i % 16
            f = f + a + np.uint32(added) + words[g]
            a, b, c, d = d, b + ((f << np.uint32(turn)) | (f >> np.uint32(32 - turn))), b, c
        out[at:end] = (a + np.uint32(0x67452301)).byteswap()
        at = end
    return out


def unit_draw(*parts: Column | str | int) -> Column:
    """A draw in (0, 1) that depends on the parts alone."""
    return (hash32(*parts) + 0.5) / float(1 << 32)
