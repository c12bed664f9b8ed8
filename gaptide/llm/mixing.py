"""Mixing sources to target weights along a time-varying curriculum.

Each source has a weight schedule, piecewise linear over training time 0 to 1. Its integral is the source's weight; the
shares of all sources make up a wanted total, and no source is asked for more than a stated multiple of what it has (the
excess goes to the others by weight). A source lays its documents in hash order on a line of tokens and walks it again
when it needs more; the cumulative demand of its schedule, inverted, turns a place on that line into a training position,
and documents are range-sorted by position.

A running sum over a source that holds a third of all rows can't be one task's work: it is taken in two levels, within
buckets of about the square root of the source's rows, then over bucket totals. Plans are DataFrame functions only.

Cases: null or empty text has size 0, takes nothing; a null source is a source of its own, last in order; null doc_ids
share one hash key; repeated rows are separate documents; an empty table gives an empty table; a document is cut where
the target ends, so that a source's taken words differ from its target by less than one word; other columns of docs aren't
read by `mix` (those it keeps must not have the names it adds), and pass through `materialised` whatever their names.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import WORD, attach, cut, fresh

Schedule = Sequence[tuple[float, float]]


def ramps(weights: Sequence[float], swing: float = 0.5) -> list[Schedule]:
    """Schedules that rise or fall in turn and whose integrals are the weights."""
    return [[(0.0, w * (1 - s)), (1.0, w * (1 + s))] for i, w in enumerate(weights) for s in [swing if i % 2 == 0 else -swing]]


def integral(schedule: Schedule) -> float:
    return sum((t2 - t1) * (w1 + w2) / 2 for (t1, w1), (t2, w2) in zip(schedule, schedule[1:]))


def invert(schedule: Schedule, share: Column) -> Column:
    """The time by which a share (0 to 1) of the schedule's integral has been asked for."""
    whole, before, out = integral(schedule), 0.0, None
    pieces = []
    for (t1, w1), (t2, w2) in zip(schedule, schedule[1:]):
        area = (t2 - t1) * (w1 + w2) / 2
        if area > 0:
            slope = (w2 - w1) / (t2 - t1)
            x = F.greatest(share * whole - before, F.lit(0.0))
            root = F.sqrt(F.greatest(F.lit(w1 * w1) + 2 * slope * x, F.lit(0.0)))
            pieces.append((before + area, F.least(F.lit(t2), t1 + 2 * x / F.greatest(w1 + root, F.lit(1e-300)))))
        before += area
    for end, at in reversed(pieces):
        out = at if out is None else F.when(share * whole <= end, at).otherwise(out)
    return out


def targets(sizes: DataFrame, schedules: Sequence[Schedule], total_share: float, limit: float) -> DataFrame:
    """source, source_size, n_docs, turn (its schedule) and target of each source; one row for each source, so windows over all of them are small."""
    weights = [integral(s) for s in schedules]
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    every = W.partitionBy(F.lit(0))
    turn = (F.row_number().over(every.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    per = per.withColumn("turn", turn.cast("int")).withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), F.col("turn") + 1))
    per = per.withColumn("most", limit * F.col("source_size")).withColumn("wanted", total_share * F.sum("source_size").over(every))
    before = every.orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    left = F.col("wanted") - F.coalesce(F.sum("most").over(before), F.lit(0.0))
    others = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    per = per.withColumn("full", F.col("most") * others <= F.col("weight") * left)
    taken = F.sum(F.when(F.col("full"), F.col("most")).otherwise(0.0)).over(every)
    open_weight = F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("weight"))).over(every)
    share = F.when(F.col("full"), F.col("most")).otherwise(F.col("weight") * (F.col("wanted") - taken) / F.when(open_weight > 0, open_weight))
    return per.select("source", "source_size", "n_docs", "turn", share.alias("target"))


def mix(docs: DataFrame, schedules: Sequence[Schedule], total_share: float = 1.5, limit: float = 2.0, seed: str = "mix", keep: Sequence[str] = ("doc_id",), source: str = "source", text: str = "text") -> DataFrame:
    """keep..., size, source_size, target, taken, first_position, second_position (of its first and second pass; null: not taken), range-sorted by first position.

    limit is at most 2 passes. The narrow table of sizes is checkpointed: the text is read once.
    """
    if not 0 < limit <= 2:
        raise ValueError("limit must be above 0 and at most 2")
    if taken := {"size", "source", "key", "sk", "sn", "source_size", "turn", "target", "buckets", "bucket", "bucket_start", "inside", "at", "taken"} & {k.lower() for k in keep}:
        raise ValueError(f"columns to keep must have other names than {sorted(taken)}")
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(keep[0]).cast("string"), F.lit(""))))
    key = F.conv(F.substring(digest, 1, 15), 16, 10).cast("long")
    size = F.coalesce(F.regexp_count(F.col(text).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")
    base = cut(docs.select(*keep, F.col(source).alias("source"), size.alias("size"), key.alias("key")))
    plan = targets(base, schedules, total_share, limit)
    # null sources meet by a null-safe key
    plan = plan.withColumn("buckets", F.ceil(F.sqrt("n_docs")).cast("long"))
    name = (F.coalesce(F.col("source"), F.lit("")), F.col("source").isNull())
    plan = plan.select(name[0].alias("sk"), name[1].alias("sn"), "source_size", "turn", "target", "buckets")
    rows = attach(base.withColumn("sk", name[0]).withColumn("sn", name[1]), plan, ["sk", "sn"])
    rows = rows.withColumn("bucket", F.shiftright(F.shiftright("key", 28) * F.col("buckets"), 32))
    group = ["sk", "sn", "bucket"]
    starts = rows.groupBy(*group).agg(F.sum("size").alias("bucket_size"))
    ahead = W.partitionBy("sk", "sn").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = starts.select(*group, F.coalesce(F.sum("bucket_size").over(ahead), F.lit(0)).alias("bucket_start"))
    within = W.partitionBy(*group).orderBy("key", *keep, "size").rowsBetween(W.unboundedPreceding, -1)
    rows = rows.withColumn("inside", F.coalesce(F.sum("size").over(within), F.lit(0)))
    rows = rows.join(starts, group).withColumn("at", F.col("bucket_start") + F.col("inside"))
    goal = F.floor(F.col("target") + 0.5).cast("long")
    take = lambda start: F.greatest(F.lit(0).cast("long"), F.least(goal - start, F.col("size")))
    one, two = take(F.col("at")), take(F.col("at") + F.col("source_size"))

    def position(start: Column, words: Column) -> Column:
        share, out = start / F.when(F.col("target") > 0, F.col("target")), None
        for i, s in enumerate(schedules):
            out = F.when(F.col("turn") == i, invert(s, share)) if out is None else out.when(F.col("turn") == i, invert(s, share))
        return F.when(words > 0, out)

    rows = rows.select(*keep, "size", "source_size", "target", (one + two).alias("taken"), position(F.col("at"), one).alias("first_position"), position(F.col("at") + F.col("source_size"), two).alias("second_position"), one.alias("first_taken"), two.alias("second_taken"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    tie = [F.col(keep[0]).asc_nulls_last()]
    order = [F.col("first_position").asc_nulls_last(), *tie]
    return rows.repartitionByRange(parts, *order).sortWithinPartitions(*order)


def materialised(docs: DataFrame, schedules: Sequence[Schedule], total_share: float = 1.5, limit: float = 2.0, seed: str = "mix") -> DataFrame:
    """The mix itself: docs once for each pass that takes at least half of their words, range-sorted by training position.

    doc_id is a key here: repeated rows are mixed as one. Documents without words, or without a doc_id, are never asked for.
    """
    one = docs.where(F.col("doc_id").isNotNull())
    plan = mix(one.select("doc_id", "source", "text"), schedules, total_share, limit, seed)
    passes = F.array(*[F.struct(F.col(f"{n}_position").alias("position"), F.col(f"{n}_taken").alias("words")) for n in ("first", "second")])
    asked = plan.select("doc_id", "size", F.explode(passes).alias("p")).where((F.col("p.words") > 0) & (2 * F.col("p.words") >= F.col("size")))
    at = fresh("position", docs.columns)
    asked = asked.select("doc_id", F.col("p.position").alias(at)).distinct()
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = one.join(asked, "doc_id")
    return placed.repartitionByRange(parts, at, "doc_id").sortWithinPartitions(at, "doc_id").select(*docs.columns)
