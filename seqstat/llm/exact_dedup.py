"""Exact deduplication by a tree-merge of sorted digest runs, in DataFrame operations only.

Every input partition makes one run: its digests, sorted and each held once with the smallest id and the number of
rows. Runs are then merged ``fan_in`` at a time, level by level, until one is left; each level is one exchange keyed by
(run, digest), a sort that merges the runs it gathers, and one streaming pass over neighbours: no table of digests is held in
memory, and a digest that a third of all rows share arrives as one row per run and never as its rows. A digest is
verified by a second, independent hash and the text's length: rows merge at a level only if all three agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqstat.llm.shared import SPACES, scratch, stage

KEY = ["digest", "check", "octets"]


def normalised(text: Column) -> Column:
    """Null counts as empty; every run of white space becomes one space."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " ")


def digest_columns(text: Column) -> list[Column]:
    t = normalised(text)
    return [F.unhex(F.sha2(t, 256)).alias("digest"), F.xxhash64(t).alias("check"), F.octet_length(t).alias("octets")]


def merge_runs(runs: DataFrame, fan_in: int = 16) -> DataFrame:
    """(digest, check, octets, keep_id, group_size) from leaf rows (run, digest, check, octets, doc_id).

    The smallest id is kept as a struct (ids before nulls), for which Spark aggregates sorted neighbours instead of hashing.
    """
    last = runs.agg(F.max("run")).first()[0] or 0
    merged = runs.select("run", *KEY, F.struct(F.col("doc_id").isNull().alias("none"), "doc_id").alias("first"), F.lit(1).cast("long").alias("rows"))
    while True:
        merged = merged.groupBy("run", *KEY).agg(F.min("first").alias("first"), F.sum("rows").alias("rows"))
        if not last:
            return merged.select(*KEY, F.col("first.doc_id").alias("keep_id"), F.col("rows").alias("group_size"))
        merged = merged.withColumn("run", F.floor(F.col("run") / fan_in).cast("int"))
        last //= fan_in


def exact_groups(docs: DataFrame, fan_in: int = 16) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, keep_id, group_size, kept, digest.

    Null and empty texts are one group; rows repeated under one doc_id are all kept with it (``keep_first`` leaves one); a
    null doc_id is kept only in a group without other ids; an empty table gives no rows; other columns are ignored.
    """
    leaf = docs.select("doc_id", *digest_columns(F.col("text"))).withColumn("run", F.spark_partition_id())
    rows = stage(leaf.sortWithinPartitions("digest"), "digest-runs")
    verdicts = rows.select("run", *KEY).distinct().join(merge_runs(rows, fan_in), KEY)
    out = rows.join(verdicts, ["run", *KEY])
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "digest")


def keep_first(docs: DataFrame, fan_in: int = 16) -> DataFrame:
    """The rows of ``docs`` that stay, all columns, one per distinct text; repeated rows leave one."""
    with scratch(docs.sparkSession):
        kept = stage(exact_groups(docs, fan_in).where("kept").select("doc_id", "digest"), "kept", keep=True)
    marked = docs.withColumn("__digest", digest_columns(F.col("text"))[0])
    ids = kept.select(F.col("doc_id").alias("__id"), F.col("digest").alias("__kept"))
    repeated = not kept.groupBy("doc_id", "digest").count().where("count > 1").isEmpty()
    out = marked.join(ids.distinct() if repeated else ids, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__digest") == F.col("__kept")), "left_semi")
    return (out.dropDuplicates(["doc_id", "__digest"]) if repeated else out).drop("__digest")
