"""Beyond occurrence counts: document frequencies, inverted indexes, time series and other metadata."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.operators.direct import by_document, direct_documents, gram_rows, in_turns, suffix_rows
from seqstat.operators.encode import Options, Prepared
from seqstat.operators.levelwise_index import levelwise_index
from seqstat.operators.suffix import count_suffixes, suffix_scan


def document_frequency(p: Prepared, tau: int, sigma: int, method: str = "suffix", opts: Options = Options()) -> DataFrame:
    """(ids, df) of the n-grams of df >= tau.

    suffix: a document's sorted suffixes give, for each neighbouring pair, its common prefix with weight -1, so that plain
    sums count documents; direct: rows combined within documents; index: lengths of lists of
    documents, whose entries are combined within a document before they cross the network, in turns over first terms.
    """
    if method == "direct":
        return direct_documents(p, 1, sigma).where(F.col("df") >= tau).select("ids", "df")
    if method == "index":

        def lengths(rows: DataFrame) -> DataFrame:
            entries = rows.groupBy("ids", "doc_id").agg(F.count(F.lit(1)).alias("tf"))
            lists = entries.groupBy("ids").agg(F.collect_list("doc_id").alias("documents"))
            return lists.select("ids", F.size("documents").cast("bigint").alias("df")).where(F.col("df") >= tau)

        return in_turns(replace(p, runs=by_document(p.runs, sigma)), sigma, lengths, "doc_id")
    rows = suffix_rows(p.runs, sigma, "doc_id").select("doc_id", "ids")
    placed = rows.repartition("doc_id").sortWithinPartitions("doc_id", "ids")

    def corrections(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_doc, last = None, np.empty(0, np.int32)
        for batch in batches:
            docs, lists = batch.column(0).to_pylist(), batch.column(1)
            out = []
            for doc, row in zip(docs, lists, strict=True):
                ids = row.values.to_numpy()
                if doc == last_doc and last_doc is not None:
                    n = min(len(ids), len(last))
                    differ = np.flatnonzero(ids[:n] != last[:n])
                    if common := int(differ[0]) if len(differ) else n:
                        out.append(ids[:common])
                last_doc, last = doc, ids
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.int32()))], ["ids"])

    less = placed.mapInArrow(corrections, "ids array<int>").select("ids", F.array(F.lit(-1).cast("bigint")).alias("w"))
    both = rows.select("ids", F.array(F.lit(1).cast("bigint")).alias("w")).unionByName(less)
    return count_suffixes(both, p, tau, sigma, opts).select("ids", F.col("w")[0].alias("df"))


def ngram_index(p: Prepared, tau: int, sigma: int, what: str = "tf", opts: Options = Options()) -> DataFrame:
    """(ids, doc_id, tf) or, one row per occurrence, (ids, doc_id, pos), of the frequent n-grams."""
    frequent = suffix_scan(p, tau, sigma, opts).select("ids")
    rows = gram_rows(p.runs, sigma, "doc_id").join(frequent, "ids", "left_semi")
    if what == "positions":
        return rows.select("ids", "doc_id", "pos")
    return rows.groupBy("ids", "doc_id").agg(F.count(F.lit(1)).alias("tf"))


def time_series(p: Prepared, tau: int, sigma: int, period: str = "period", method: str = "suffix", opts: Options = Options(), most: int = 64) -> DataFrame:
    """(ids, period, cf) without zeros; tau holds for the sum over periods.

    suffix: equal suffixes of a period are added up first and the kernel's accumulators are vectors, one number per period (at most
    ``most`` periods, else direct); direct: the period is carried by every n-gram.
    """
    known = [r[0] for r in p.runs.select(period).distinct().orderBy(period).limit(most + 1).collect()] if method == "suffix" else []
    if method == "direct" or len(known) > most:
        parts = gram_rows(p.runs, sigma, period).groupBy("ids", period).agg(F.count(F.lit(1)).alias("cf"))
        frequent = parts.groupBy("ids").agg(F.sum("cf").alias("all")).where(F.col("all") >= tau).select("ids")
        return parts.join(frequent, "ids", "left_semi").select("ids", F.col(period).alias("period"), "cf")
    if not known:
        return p.runs.select("ids", F.col(period).alias("period"), F.lit(0).cast("bigint").alias("cf")).where("false")
    rows = suffix_rows(p.runs, sigma, period)
    flags = F.array(*[F.when(F.col(period).eqNullSafe(F.lit(v)), 1).otherwise(0).cast("bigint") for v in known])
    counted = count_suffixes(rows.select("ids", flags.alias("w")), p, tau, sigma, opts, weights=len(known))
    names = F.array(*[F.lit(v) for v in known])
    flat = counted.select("ids", F.explode(F.arrays_zip(names.alias("period"), F.col("w").alias("cf"))).alias("z"))
    return flat.select("ids", F.col("z.period").alias("period"), F.col("z.cf").alias("cf")).where("cf > 0")


def metadata_stats(p: Prepared, tau: int, sigma: int, by: str, opts: Options = Options()) -> DataFrame:
    """(ids, <by>, cf) per value of a meta column."""
    return time_series(p, tau, sigma, by, opts=opts).withColumnRenamed("period", by)


__all__ = ["document_frequency", "levelwise_index", "metadata_stats", "ngram_index", "time_series"]
