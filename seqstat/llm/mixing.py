"""Mixing sources to target weights along a time-varying curriculum, in DataFrame operations only.

Each source has a weight and a schedule: a piecewise linear multiplier over training time 0..1. The integral of the schedule,
scaled to the source's target, is its cumulative demand for words; a document's first word stands at the sum of sizes before
it in its source (in the order of a hash, plus whole source sizes for repeats), and the time at which demand reaches that
word is the document's training position. Documents are range-sorted by position.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqstat.llm.prefix import grouped_offsets
from seqstat.llm.shared import scratch, stage, word_count

Schedule = tuple[tuple[float, float], ...]


@dataclass(frozen=True)
class Curriculum:
    """Weights and schedules repeat over the sources by code point, null last; ``most`` is the largest multiple of a source's size."""

    weights: tuple[int, ...] = (5, 2, 1)
    schedules: tuple[Schedule, ...] = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)), ((0.0, 1.0), (1.0, 1.0)))
    most: int = 3


def sizes(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size, order, text_hash); order is spread evenly over 0 .. 2**32-1 and depends on the id alone."""
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    order = F.conv(F.substring(key, 1, 8), 16, 10).cast("long").alias("order")
    text = F.col("text")
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), word_count(text).alias("size"), order, F.xxhash64(text).alias("text_hash"))


def targets(sized: DataFrame, plan: Curriculum = Curriculum()) -> DataFrame:
    """(source, source_size, kind, target): shares of all sizes by weight, held at ``most`` times a source's size.

    Held shares leave an excess that the others divide by weight until none is above. The level of that is found in one pass:
    sorted by limit over weight, the first source whose share of what is left stays under its limit sets it. One row per
    source meets in one task here, never a document.
    """
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    everywhere = Window.partitionBy(F.lit(0))
    by_name = everywhere.orderBy(F.col("source").asc_nulls_last())
    kind = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(plan.weights))).cast("int")
    known = totals.withColumn("kind", kind).withColumn("weight", F.element_at(F.array(*map(F.lit, plan.weights)), F.col("kind") + 1).cast("long"))
    known = known.withColumn("limit", F.col("source_size") * plan.most)
    by_limit = everywhere.orderBy(F.col("limit") / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    left = F.sum("source_size").over(everywhere) - F.coalesce(F.sum("limit").over(by_limit), F.lit(0))
    weights = F.sum("weight").over(everywhere) - F.coalesce(F.sum("weight").over(by_limit), F.lit(0))
    placed = known.withColumn("level", left.cast("double") / weights.cast("double"))
    free = F.col("limit") > F.col("weight") * F.col("level")
    placed = placed.withColumn("rank", F.row_number().over(everywhere.orderBy(F.col("limit") / F.col("weight"), F.col("source").asc_nulls_last())))
    placed = placed.withColumn("final", F.min(F.when(free, F.struct("rank", "level"))).over(everywhere)["level"])
    target = F.when(F.col("limit") > F.col("weight") * F.col("final"), F.col("weight") * F.col("final")).otherwise(F.col("limit").cast("double"))
    return placed.select("source", "source_size", "kind", target.alias("target"))


def demand_time(share: Column, schedule: Schedule) -> Column:
    """The time at which the normalised integral of ``schedule`` reaches ``share`` (beyond 1: share itself)."""
    areas, total = [], 0.0
    for (t0, m0), (t1, m1) in zip(schedule, schedule[1:], strict=False):
        areas.append((total, t0, m0, (m1 - m0) / (t1 - t0)))
        total += (m0 + m1) * (t1 - t0) / 2
    out = share
    for start, t0, m0, slope in areas:
        d = F.greatest(share * total - start, F.lit(0.0))
        root = F.sqrt(F.greatest(F.lit(m0 * m0) + d * 2 * slope, F.lit(0.0)))
        inside = F.when(d > 0, F.lit(t0) + d * 2 / (root + m0)).otherwise(F.lit(t0))
        out = F.when((share >= start / total) & (share < 1), inside).otherwise(out)
    return out


def assign(docs: DataFrame, plan: Curriculum = Curriculum(), whole: bool = False) -> DataFrame:
    """Per row: doc_id, source, text_hash, size, source_size, target, taken, copies (array of words, position), first_position.

    A copy starts at the sum of sizes before it and is taken as far as the target reaches, so that a source's taken words equal its
    rounded target; with ``whole`` a copy is taken as a whole if its middle lies below the target. Null text has size 0;
    a null source is a source of its own, last; repeated rows count as so many documents; an empty table gives no rows.
    """
    sized = stage(sizes(docs), "sizes")
    shares = stage(targets(sized, plan), "targets")
    placed = grouped_offsets(sized, ["source"], "size", "order", ["doc_id", "size", "text_hash"])
    rows = placed.join(shares, placed["source"].eqNullSafe(shares["source"])).drop(shares["source"])
    budget = F.round("target").cast("long")

    def copy(turn: Column) -> Column:
        start = F.col("offset") + turn * F.col("source_size")
        cut = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), budget - start))
        words = F.when(start + F.floor(F.col("size") / 2) < budget, F.col("size")).otherwise(F.lit(0).cast("long")) if whole else cut
        share = F.when(budget > 0, start / budget).otherwise(F.lit(1.0))
        time = share
        for i, schedule in enumerate(plan.schedules):
            time = F.when(F.col("kind") % len(plan.schedules) == i, demand_time(share, schedule)).otherwise(time)
        return F.struct(words.alias("words"), time.alias("position"))

    rows = rows.withColumn("all", F.array(*[copy(F.lit(i).cast("long")) for i in range(plan.most)]))
    rows = rows.withColumn("first_position", F.col("all")[0]["position"]).withColumn("copies", F.filter("all", lambda c: c["words"] > 0))
    taken = F.aggregate("copies", F.lit(0).cast("long"), lambda s, c: s + c["words"])
    return rows.select("doc_id", "source", "text_hash", "size", "source_size", "target", taken.alias("taken"), "copies", "first_position")


def by_position(df: DataFrame, position: str) -> DataFrame:
    """Range-sorted: partitions follow each other in training time, each sorted."""
    return df.repartitionByRange(position).sortWithinPartitions(position)


def mixture(docs: DataFrame, plan: Curriculum = Curriculum()) -> DataFrame:
    """The rows to train on, all columns of ``docs``, whole texts in training order: a row as often as it is taken."""
    with scratch(docs.sparkSession):
        taken = assign(docs, plan, whole=True).select("doc_id", "text_hash", "copies.position")
        taken = stage(taken.where(F.size("position") > 0), "taken", keep=True)
        repeated = not taken.groupBy("doc_id", "text_hash").count().where("count > 1").isEmpty()
    marked = docs.withColumn("__hash", F.xxhash64("text"))
    if repeated:
        marked = marked.dropDuplicates(["doc_id", "__hash"])
    copies = taken.select(F.col("doc_id").alias("__id"), F.col("text_hash").alias("__plan"), F.col("position").alias("__positions"))
    joined = marked.join(copies, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__hash") == F.col("__plan")))
    return by_position(joined.select(*docs.columns, F.explode("__positions").alias("__position")), "__position").drop("__position")
