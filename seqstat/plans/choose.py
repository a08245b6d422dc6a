"""Choice of a method by exact record counts, guards, and limits pushed into parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.operators.direct import direct_count
from seqstat.operators.encode import Options, Prepared
from seqstat.operators.suffix import suffix_scan
from seqstat.plans.measures import expected_direct, expected_suffix


class TooManyRows(ValueError):
    """Raised where an enumerating method would make far more rows than there are terms."""


def estimate(p: Prepared, tau: int, sigma: int) -> tuple[int, int]:
    """Rows of direct counting and of the suffix method."""
    return expected_direct(p, sigma).first()[0], expected_suffix(p, tau).first()[0]


def guard(p: Prepared, tau: int, sigma: int, factor: int = 50) -> None:
    rows, terms = estimate(p, tau, sigma)
    if rows > factor * max(1, terms):
        raise TooManyRows(f"direct counting would make {rows} rows of {terms} terms; use suffix_scan")


def choose(p: Prepared, tau: int, sigma: int | None, opts: Options = Options()) -> tuple[str, DataFrame]:
    """Direct counting where lengths of one or two make few rows that combine well; the suffix method otherwise."""
    if sigma is not None and sigma <= 2:
        rows, terms = estimate(p, tau, sigma)
        if rows <= 2 * terms:
            return "direct", direct_count(p, tau, sigma, opts)
    return "suffix", suffix_scan(p, tau, sigma, opts)


def limits(tau: int, sigma: int, max_n: int | None = None, min_cf: int | None = None) -> tuple[int, int]:
    """A later filter on length or frequency as parameters of the method itself. Not for maximal or closed results, which are
    relative to the original parameters."""
    return max(tau, min_cf or tau), min(sigma, max_n or sigma)


def with_prefix(p: Prepared, ids: list[int], tau: int, sigma: int, opts: Options = Options()) -> DataFrame:
    """(ids, cf) of grams that begin with some ids: only suffixes that begin so are exchanged."""
    from seqstat.operators.direct import suffix_rows
    from seqstat.operators.suffix import count_suffixes

    start = F.array(*map(F.lit, ids))
    rows = suffix_rows(p.runs, sigma).where(F.slice("ids", F.lit(1), F.lit(len(ids))) == start)
    counted = count_suffixes(rows.select("ids", F.array(F.lit(1).cast("bigint")).alias("w")), p, tau, sigma, opts)
    return counted.where(F.size("ids") >= len(ids)).select("ids", F.col("w")[0].alias("cf"))
