"""Streams of events and of new coordinates; run to their end (availableNow) they equal the batch queries.

Event time must be a timestamp with time zone, so timestamp_ntz is cast first. Results go through foreachBatch to Parquet
in the shared folder, so no result passes through the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..common import shared_path, ship, table
from ..functions.objectives import Objective
from ..operators.gaps import dots


def source(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events table as a stream of its files."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{sf_dir}/event[s].parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str, name: str, each=None) -> DataFrame:
    """Run a stream over what is there now and read what it wrote: the last result in complete mode, all results in append mode."""
    spark = stream.sparkSession
    out, at = shared_path(spark, f"{name}-out"), shared_path(spark, f"{name}-state")

    def write(batch: DataFrame, _: int) -> None:
        (each(batch) if each else batch).write.mode("overwrite" if mode == "complete" else "append").parquet(out)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", at).trigger(availableNow=True).foreachBatch(write).start()
    q.awaitTermination()
    return spark.read.parquet(out)


def stamp(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


def tumbling(events: DataFrame, late: str = "1 hour", size: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("v"))
    return w.select(stamp("window.start").alias("start"), "event_type", "n", F.round("v", 6).alias("v"))


def sliding(events: DataFrame, late: str = "1 hour", size: str = "6 hours", step: str = "2 hours") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(stamp("window.start").alias("start"), "n")


def sessions(events: DataFrame, late: str = "1 hour", gap: str = "12 hours") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", stamp("session_window.start").alias("start"), "n")


def dedup(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")


def followed(events: DataFrame, other: DataFrame, first: str = "view", then: str = "purchase", within: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Pairs of a first event and a later one of the same user within a time."""
    a = events.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("t1")).withWatermark("t1", late)
    b = other.where(F.col("event_type") == then).select(F.col("user_id").alias("u2"), F.col("event_id").alias("then_id"), F.col("ts").alias("t2")).withWatermark("t2", late)
    return a.join(b, F.expr(f"user_id = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("user_id", "first_id", "then_id")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """A static side: the segment of each event's user."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id", "left").select("event_id", "c_mktsegment")


def new_coordinates(samples: DataFrame, obj: Objective, w: np.ndarray):
    """For foreachBatch: each arrival starts at alpha 0 with its gap at the present w as its first memory."""
    u = dots(samples, w)
    return u.select("coord_id", F.lit(0.0).alias("alpha"), obj.gap_col(F.lit(0.0), F.col("u")).alias("z"))


def should_retrain(arrivals: DataFrame, certificate: float, share: float = 0.1) -> bool:
    """Whether the arrivals' gaps are more than a share of the certificate."""
    return (arrivals.agg(F.sum("z")).first()[0] or 0.0) > share * certificate


def user_memory(events: DataFrame, keep: str = "2 days", late: str = "1 hour") -> DataFrame:
    """Per user: number of events, decayed value and last time, kept as state until a user has been silent for so long. Rows of one update."""
    ship(events.sparkSession)
    keep_ms = int(pd.Timedelta(keep).total_seconds() * 1000)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, z, last = state.get if state.exists else (0, 0.0, 0)
        for f in frames:
            n, z = n + len(f), z + float(f["value"].sum())
            last = max(last, int(f["ts"].max().timestamp() * 1000))
        state.update((n, z, last))
        state.setTimeoutTimestamp(max(last + keep_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "z": [z]})

    rows = events.withWatermark("ts", late).select("user_id", "ts", "value")
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, z double", "n long, z double, last long", "update", GroupStateTimeout.EventTimeTimeout)
