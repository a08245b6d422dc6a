"""Prefix sums within groups, of which one may hold a third of all rows, without one task ever sorting a whole group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def grouped_offsets(rows: DataFrame, group: list[str], value: str | None, order: str, ties: list[str], out: str = "offset", buckets: int = 4096) -> DataFrame:
    """Add ``out``: the sum of ``value`` (None: the number of rows) over the rows before this one in its group.

    ``order`` is a long column spread evenly over 0 .. 2**32-1 (a hash). Its high bits make ``buckets`` blocks;
    block totals are summed within the group (at most ``buckets`` rows each), rows only within a block.
    """
    width = (1 << 32) // buckets
    amount: Column = F.lit(1).cast("long") if value is None else F.col(value)
    blocks = rows.withColumn("__block", F.floor(F.col(order) / F.lit(width)).cast("int")).withColumn("__amount", amount)
    null_safe = [F.coalesce(F.col(g).cast("string"), F.lit("")).alias(f"__g{i}") for i, g in enumerate(group)] + [F.col(g).isNull().alias(f"__n{i}") for i, g in enumerate(group)]
    keys = [f"__g{i}" for i in range(len(group))] + [f"__n{i}" for i in range(len(group))]
    blocks = blocks.select("*", *null_safe)
    totals = blocks.groupBy(*keys, "__block").agg(F.sum("__amount").alias("__sum"))
    before = Window.partitionBy(*keys).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    starts = totals.select(*keys, "__block", F.coalesce(F.sum("__sum").over(before), F.lit(0)).alias("__start"))
    within = Window.partitionBy(*keys, "__block").orderBy(order, *ties).rowsBetween(Window.unboundedPreceding, -1)
    summed = blocks.withColumn("__within", F.coalesce(F.sum("__amount").over(within), F.lit(0)))
    joined = summed.join(starts, [*keys, "__block"])
    return joined.withColumn(out, (F.col("__start") + F.col("__within")).cast("long")).drop(*keys, "__block", "__amount", "__within", "__start")
