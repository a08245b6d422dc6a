"""Connected components of an edge table by repeated contraction; nothing is gathered in one task or on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.llm.shared import scratch, stage


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): every node of ``edges`` with the smallest node that it reaches.

    Each round, a node hooks onto the neighbour with the least hash of that round (itself if it is least), hooks
    are followed twice more, and the edges are drawn anew between what remains. Hashes differ from round to round, so
    chains shrink as fast as stars. A round's tables are written to the shared folder.
    """
    live = stage(edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b").distinct(), "edges")
    with scratch(edges.sparkSession):
        return stage(_contracted(live), "components", keep=True)


def _contracted(live: DataFrame) -> DataFrame:
    labels = live.select(F.col("a").alias("node")).union(live.select("b")).distinct().withColumn("label", F.col("node"))
    turn = 0
    while not live.isEmpty():
        turn += 1
        rank = lambda c: F.struct(F.xxhash64(F.lit(turn), c).alias("h"), F.col(c).alias("v"))  # noqa: E731,B023
        both = live.union(live.select("b", "a"))
        hooks = both.groupBy("a").agg(F.min(rank("b")).alias("best")).select(F.col("a").alias("u"), F.least(F.col("best"), rank("a"))["v"].alias("p"))
        hooks = stage(hooks, "hooks")
        for _ in range(2):
            up = hooks.select(F.col("u").alias("p"), F.col("p").alias("pp"))
            hooks = hooks.join(up, "p").select("u", F.col("pp").alias("p"))
        hooks = stage(hooks, "roots")
        left, right = hooks.select(F.col("u").alias("a"), F.col("p").alias("pa")), hooks.select(F.col("u").alias("b"), F.col("p").alias("pb"))
        drawn = live.join(left, "a").join(right, "b").where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b"))
        labels = stage(labels.join(hooks.withColumnsRenamed({"u": "label", "p": "root"}), "label", "left").select("node", F.coalesce("root", "label").alias("label")), "labels")
        live = stage(drawn.distinct(), "edges")
    least = labels.groupBy("label").agg(F.min("node").alias("component"))
    return labels.join(least, "label").select("node", "component")
