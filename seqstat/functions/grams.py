"""Pure Column builders over term arrays, a table function, and their SQL names."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def suffixes(terms: Column, sigma: int) -> Column:
    """Array of the suffixes, each cut to sigma terms."""
    return F.transform(F.sequence(F.lit(1), F.size(terms)), lambda i: F.slice(terms, i, F.lit(sigma)))


def prefixes(terms: Column) -> Column:
    return F.transform(F.sequence(F.lit(1), F.size(terms)), lambda n: F.slice(terms, F.lit(1), n))


def ngrams(terms: Column, sigma: int) -> Column:
    """Array of all runs of 1..sigma terms; empty arrays give none."""
    some = F.flatten(F.transform(suffixes(terms, sigma), prefixes))
    return F.when(F.size(terms) > 0, some).otherwise(F.array().cast("array<array<string>>"))


def lcp(a: Column, b: Column) -> Column:
    """Length of the longest common prefix."""
    same = F.zip_with(F.slice(a, F.lit(1), F.least(F.size(a), F.size(b))), F.slice(b, F.lit(1), F.least(F.size(a), F.size(b))), lambda x, y: x == y)
    first = F.array_position(same, F.lit(False))
    return F.when(first > 0, first - 1).otherwise(F.size(same)).cast("int")


def is_prefix(r: Column, s: Column) -> Column:
    return F.slice(s, F.lit(1), F.size(r)) == r


def is_suffix(r: Column, s: Column) -> Column:
    return (F.size(r) <= F.size(s)) & (F.slice(s, F.greatest(F.size(s) - F.size(r) + 1, F.lit(1)), F.size(r)) == r)


def occurs(r: Column, s: Column) -> Column:
    """How often r occurs in s, overlaps included."""
    starts = F.sequence(F.lit(1), F.greatest(F.size(s) - F.size(r) + 1, F.lit(1)))
    return F.when(F.size(r) > F.size(s), F.lit(0)).otherwise(F.size(F.filter(starts, lambda p: F.slice(s, p, F.size(r)) == r)))


def contains(s: Column, r: Column) -> Column:
    return occurs(r, s) > 0


def gram(terms: Column) -> Column:
    return F.array_join(terms, " ")


class SuffixRows:
    """Table function: the suffixes of a blank-separated text, cut to sigma terms."""

    def eval(self, text: str, sigma: int):
        terms = (text or "").split()
        for i in range(len(terms)):
            yield i, " ".join(terms[i : i + sigma])


def register(spark: SparkSession) -> None:
    """SQL names: suffix_rows (LATERAL), gram_of, lcp_of, occurrences."""
    spark.udtf.register("suffix_rows", F.udtf(SuffixRows, returnType="start int, suffix string"))
    spark.sql("create or replace temporary function gram_of(a array<string>) returns string return array_join(a, ' ')")
    spark.sql("create or replace temporary function occurrences(r array<string>, s array<string>) returns int return case when size(r) > size(s) then 0 else size(filter(sequence(1, size(s) - size(r) + 1), p -> slice(s, p, size(r)) = r)) end")
