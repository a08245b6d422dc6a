"""Suffix sort-and-aggregate: one row per term, its suffix cut to sigma terms; sorted in descending order within a placement that
keeps prefixes together, and counted in one pass."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqstat.operators.direct import suffix_rows
from seqstat.operators.encode import Options, Prepared
from seqstat.operators.suffix_kernel import ALL, MAXIMAL, StackKernel, VectorKernel, run
from seqstat.sources.tables import stage


def partitions_of(df: DataFrame, opts: Options) -> int:
    return opts.partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def weighted_bins(p: Prepared, n: int) -> tuple[dict[int, int], set[int]]:
    """(first bin of each heavy term, terms that are spread over all bins). A term's suffix rows are its cf, known exactly.

    Only terms of over a tenth of a bin's load are listed, at most 10 n of them; the others are dealt by hash.
    """
    total = p.dictionary.agg(F.sum("cf")).first()[0] or 0
    heavy = p.dictionary.where(F.col("cf") * 10 * n > total).select("id", "cf").orderBy(F.desc("cf"), "id").limit(10 * n).collect()
    load = np.zeros(n)
    bins, spread = {}, set()
    for row in heavy:
        if row["cf"] * n > total:
            spread.add(row["id"])
            load += row["cf"] / n
        else:
            bins[row["id"]] = int(load.argmin())
            load[bins[row["id"]]] += row["cf"]
    return bins, spread


def place(rows: DataFrame, p: Prepared, opts: Options) -> tuple[DataFrame, set[int]]:
    """Rows exchanged so that a prefix's suffixes meet, sorted in descending order; and the terms whose own count was left out.

    first_term: hash of the first term (a hot term is one task); bins: weighted bins, hot terms spread by their second
    term; range: ranges of the whole suffix, with open rows at the boundaries.
    """
    n, first = partitions_of(rows, opts), F.col("ids")[0]
    if opts.partitioner == "first_term":
        placed, spread = rows.repartition(n, first), set()
    elif opts.partitioner == "bins":
        bins, spread = weighted_bins(p, n)
        where: Column = F.pmod(F.xxhash64(first), F.lit(n)).cast("int")
        if bins:
            known = F.create_map(*[F.lit(x) for pair in bins.items() for x in pair])
            where = F.coalesce(known[first], where)
        if spread:
            second = F.pmod(F.xxhash64(F.get("ids", F.lit(1))), F.lit(n)).cast("int")
            where = F.when(first.isin(*spread), second).otherwise(where)
        placed = rows.repartitionById(n, where)
    elif opts.partitioner == "whole":  # a negative control: prefixes are torn apart
        placed, spread = rows.repartition(n, "ids"), set()
    else:
        placed, spread = rows.repartitionByRange(n, F.col("ids").desc()), set()
    return placed.sortWithinPartitions(F.col("ids").desc()), spread


def aggregate_sorted(placed: DataFrame, tau: int, width: int, weights: int, keep: str, repair: bool, kernel: str) -> DataFrame:
    """(ids, w, open, best) of the kernel over each partition; ``placed`` has ids and w ARRAY<BIGINT> of ``weights`` numbers."""

    def kernels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = (StackKernel if kernel == "stack" else VectorKernel)(tau, width, weights, keep, repair)

        def rows() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
            for batch in batches:
                ids, w = batch.column("ids"), batch.column("w")
                yield ids.flatten().to_numpy(), np.diff(ids.offsets.to_numpy()).astype(np.int64), w.flatten().to_numpy().reshape(-1, weights)

        for flat, lengths, sums, opened, best in run(made, rows()):
            offsets = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat.astype(np.int32)))
            vectors = pa.ListArray.from_arrays(pa.array(np.arange(len(sums) + 1, dtype=np.int32) * weights), pa.array(sums.ravel()))
            yield pa.RecordBatch.from_arrays([lists, vectors, pa.array(opened), pa.array(best)], ["ids", "w", "open", "best"])

    return placed.select("ids", "w").mapInArrow(kernels, "ids array<int>, w array<bigint>, open boolean, best bigint")


def total(w: Column) -> Column:
    return F.aggregate(w, F.lit(0).cast("bigint"), lambda s, x: s + x)


def added(w: Column, n: int) -> Column:
    """Sum of weight vectors in a group."""
    return F.array(*[F.sum(w[i]) for i in range(n)])


def count_suffixes(rows: DataFrame, p: Prepared, tau: int, sigma: int, opts: Options, weights: int = 1, keep: str = ALL) -> DataFrame:
    """(ids, w) from suffix rows (ids, w): place, sort, count, repair; with ``local_combine`` equal suffixes are added up first, at
    the price of another exchange."""
    if opts.partitioner == "bins" and (keep != ALL or weights > 1):
        raise ValueError("weighted bins count occurrences alone: take range or first_term")
    if opts.local_combine:
        rows = rows.groupBy("ids").agg(added(F.col("w"), weights).alias("w"))
    placed, spread = place(rows, p, opts)
    repair = opts.partitioner == "range"
    counted = aggregate_sorted(placed, tau, sigma, weights, keep, repair, opts.kernel)
    if repair:
        counted = stage(counted, "counted")
        closed = counted.where(~F.col("open")).select("ids", "w")
        mended = counted.where("open").groupBy("ids").agg(added(F.col("w"), weights).alias("w"), F.max("best").alias("best")).where(total(F.col("w")) >= tau)
        if keep != ALL:  # an open gram's extensions are complete in one partition (best) or open themselves
            longer = mended.where(F.size("ids") > 1).groupBy(F.slice("ids", F.lit(1), F.size("ids") - 1).alias("ids")).agg(F.max(total(F.col("w"))).alias("more"))
            known = F.greatest("best", F.coalesce("more", F.lit(0).cast("bigint")))
            mended = mended.join(longer, "ids", "left").where(known < (F.lit(tau) if keep == MAXIMAL else total(F.col("w"))))
        return closed.unionByName(mended.select("ids", "w"))
    if spread:
        alone = (F.size("ids") == 1) & F.col("ids")[0].isin(*spread)
        own = p.dictionary.where(F.col("id").isin(*spread) & (F.col("cf") >= tau)).select(F.array("id").alias("ids"), F.array("cf").alias("w"))
        return counted.where(~alone).select("ids", "w").unionByName(own)
    return counted.select("ids", "w")


def suffix_scan(p: Prepared, tau: int, sigma: int | None, opts: Options = Options(), keep: str = ALL) -> DataFrame:
    """(ids, cf); keep: all, prefix_maximal or prefix_closed. sigma None: any length."""
    if sigma is None:
        return suffix_unbounded(p, tau, opts)
    rows = suffix_rows(p.runs, sigma).select("ids", F.array(F.lit(1).cast("bigint")).alias("w"))
    return count_suffixes(rows, p, tau, sigma, opts, keep=keep).select("ids", F.col("w")[0].alias("cf"))


def suffix_unbounded(p: Prepared, tau: int, opts: Options = Options(), first: int = 8) -> DataFrame:
    """All lengths by doubling: a pass counts up to its length, and the next one reads only stretches of starts whose gram of that
    length is frequent, each as long as its last start's gram. Any longer frequent gram lies within one stretch."""
    runs, sigma, least, found = p.runs, first, 1, None
    while True:
        part = Prepared(runs, p.dictionary, p.meta)
        stats = stage(suffix_scan(part, tau, sigma, opts).where(F.size("ids") >= least), "stats")
        found = stats if found is None else found.unionByName(stats)
        whole = stats.where(F.size("ids") == sigma).select("ids")
        if whole.isEmpty():
            return found
        runs = stage(surviving_runs(runs, whole, sigma), "runs")
        least, sigma = sigma + 1, 2 * sigma


def surviving_runs(runs: DataFrame, whole: DataFrame, sigma: int) -> DataFrame:
    """Stretches of neighbouring starts whose gram of sigma terms is in ``whole``, longer than sigma terms."""
    from seqstat.operators.levelwise_scan import windows

    base = runs.select("doc_id", F.col("pos").alias("run"), "ids")
    starts = windows(runs.select("doc_id", F.col("pos").alias("run"), "pos", "ids"), sigma, "doc_id", "run").join(whole, "ids", "left_semi")
    at = F.col("pos") - F.col("run")
    stretch = at - F.row_number().over(Window.partitionBy("doc_id", "run").orderBy("pos"))  # the same for neighbouring starts
    pieces = starts.withColumn("z", stretch).groupBy("doc_id", "run", "z").agg(F.min(at).alias("a"), F.max(at).alias("b"))
    cut = base.join(pieces, ["doc_id", "run"]).select("doc_id", (F.col("run") + F.col("a")).alias("pos"), F.slice("ids", (F.col("a") + 1).cast("int"), (F.col("b") - F.col("a") + sigma).cast("int")).alias("ids"))
    return cut.where(F.size("ids") > sigma)


def suffix_prefix_hash(p: Prepared, tau: int, sigma: int, opts: Options = Options()) -> DataFrame:
    """(ids, cf): the same rows and first-term placement, but every prefix goes into a hash table (memory for all n-grams of a partition)."""
    rows = suffix_rows(p.runs, sigma).select("ids", F.col("ids")[0].alias("first"))
    placed = rows.repartition(partitions_of(rows, opts), "first")
    prefixes = placed.select("first", "ids", F.explode(F.sequence(F.lit(1), F.size("ids"))).alias("n")).select("first", F.slice("ids", F.lit(1), F.col("n")).alias("ids"))
    return prefixes.groupBy("first", "ids").agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau).select("ids", "cf")


def suffix_rollup(p: Prepared, tau: int, sigma: int) -> DataFrame:
    """(ids, cf) as a ROLLUP over the first sigma terms. Padding and rolled-up nulls look alike, so a group counts only if it has as many
    terms as grouped columns."""
    if sigma > 8:
        raise ValueError("a rollup multiplies rows by sigma + 1: use suffix_scan beyond 8")
    names = [f"t{i}" for i in range(sigma)]
    wide = suffix_rows(p.runs, sigma).select(*[F.get("ids", F.lit(i)).alias(n) for i, n in enumerate(names)])
    rolled = wide.rollup(*names).agg(F.count(F.lit(1)).alias("cf"), F.grouping_id().alias("gid"))
    ids = F.filter(F.array(*names), lambda x: x.isNotNull())
    grouped = F.lit(sigma) - F.bit_count("gid")
    return rolled.where((F.col("cf") >= tau) & (F.size(ids) == grouped) & (grouped > 0)).select(ids.alias("ids"), "cf")
