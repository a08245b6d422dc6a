"""Maximal and closed n-grams, and what they stand for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqstat.operators.encode import Options, Prepared
from seqstat.operators.suffix import count_suffixes, suffix_scan
from seqstat.operators.suffix_kernel import CLOSED, MAXIMAL
from seqstat.sources.tables import stage


def _two_passes(p: Prepared, tau: int, sigma: int, keep: str, opts: Options) -> DataFrame:
    """Filter by extensions to the right in the kernel, then by extensions to the left. The second is complete with extensions by one term:
    where a gram that passed the first has a frequent longer one around it, nothing follows it there, so its own extension by one
    term to the left passed too. Keys are whole grams, so no hot term gathers them."""
    first = stage(suffix_scan(p, tau, sigma, opts, keep), "one-sided")
    key = ["ids"] if keep == MAXIMAL else ["ids", "cf"]  # an extension never has a larger cf
    longer = first.where(F.size("ids") > 1).select(F.slice("ids", F.lit(2), F.size("ids") - 1).alias("ids"), "cf")
    return first.join(longer.select(*key), key, "left_anti")


def maximal(p: Prepared, tau: int, sigma: int, opts: Options = Options()) -> DataFrame:
    """(ids, cf) of frequent n-grams of at most sigma terms that no other such n-gram contains."""
    return _two_passes(p, tau, sigma, MAXIMAL, opts)


def closed(p: Prepared, tau: int, sigma: int, opts: Options = Options()) -> DataFrame:
    """(ids, cf) of those that no other with the same cf contains."""
    return _two_passes(p, tau, sigma, CLOSED, opts)


def condense_stats(stats: DataFrame, mode: str) -> DataFrame:
    """Maximal or closed rows of complete stats (ids, cf): only extensions by one term can tell, as cf falls with length."""
    cut: list[Column] = [F.slice("ids", F.lit(1), F.size("ids") - 1), F.slice("ids", F.lit(2), F.size("ids") - 1)]
    longer = stats.where(F.size("ids") > 1)
    parents = longer.select(cut[0].alias("ids"), "cf").unionByName(longer.select(cut[1].alias("ids"), "cf"))
    best = parents.groupBy("ids").agg(F.max("cf").alias("best"))
    if mode == "maximal":
        return stats.join(best, "ids", "left_anti")
    return stats.join(best, "ids", "left").where(F.col("best").isNull() | (F.col("best") < F.col("cf"))).select("ids", "cf")


def sub_grams(df: DataFrame, *carry: str) -> DataFrame:
    starts = df.select(*carry, "ids", F.explode(F.sequence(F.lit(1), F.size("ids"))).alias("i"))
    cut = starts.select(*carry, F.slice("ids", F.col("i"), F.size("ids")).alias("ids"))
    return cut.select(*carry, "ids", F.explode(F.sequence(F.lit(1), F.size("ids"))).alias("n")).select(*carry, F.slice("ids", F.lit(1), F.col("n")).alias("ids"))


def expand_closed(found: DataFrame) -> DataFrame:
    """All frequent n-grams with exact counts: each has the largest cf of the closed ones around it."""
    return sub_grams(found, "cf").groupBy("ids").agg(F.max("cf").alias("cf"))


def expand_maximal(found: DataFrame) -> DataFrame:
    """All frequent n-grams, without counts."""
    return sub_grams(found).distinct()


__all__ = ["closed", "condense_stats", "count_suffixes", "expand_closed", "expand_maximal", "maximal", "sub_grams"]
