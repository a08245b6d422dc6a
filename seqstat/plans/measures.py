"""Cost measures: time, records and bytes between the phases, rounds; and their analytic counterparts."""

from __future__ import annotations

import inspect
import json
import statistics
import time
import urllib.request
from collections.abc import Callable
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from seqstat.operators.direct import gram_rows, suffix_rows, within_documents
from seqstat.operators.encode import Prepared, build_dictionary, varbyte_size
from seqstat.operators.levelwise_index import levelwise_index, postings
from seqstat.operators.levelwise_scan import level_one, prune, windows
from seqstat.sources.tables import stage


@dataclass
class Measure:
    method: str
    seconds: float = 0.0
    records_logical: int = 0
    bytes_logical: int = 0
    records_shuffle: int = 0
    bytes_shuffle: int = 0
    rounds: int = 1
    rows: int = 0
    peak_task: int = 0


def timed(name: str, make: Callable[[], DataFrame]) -> Measure:
    """Wall-clock from the method's start to its complete result, all jobs included (one run on an otherwise idle machine)."""
    spark = SparkSession.getActiveSession()
    before = stages(spark)  # a method's own rounds count as well
    began = time.monotonic()
    observed = Observation()
    df = make()
    df.observe(observed, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
    seconds = time.monotonic() - began
    after = stages(spark)
    out = Measure(name, seconds, rows=observed.get["rows"])
    own = [after[k] for k in after.keys() - before.keys()]
    out.records_shuffle = sum(x["shuffleWriteRecords"] for x in own)
    out.bytes_shuffle = sum(x["shuffleWriteBytes"] for x in own)
    out.rounds = sum(x["shuffleWriteRecords"] > 0 for x in own)
    out.peak_task = max((x["peakExecutionMemory"] // max(1, x["numCompleteTasks"]) for x in own), default=0)
    return out


def stages(spark: SparkSession | None) -> dict[tuple[int, int], dict]:
    """All stages so far by id and attempt, from the application's REST address; none without the UI. Their peak execution memory is a
    sum over tasks, so ``peak_task`` is the mean task of the stage that holds the most."""
    if spark is None or not spark.sparkContext.uiWebUrl:
        return {}
    sc = spark.sparkContext
    port = sc.uiWebUrl.rsplit(":", 1)[1].rstrip("/")
    with urllib.request.urlopen(f"http://127.0.0.1:{port}/api/v1/applications/{sc.applicationId}/stages?status=complete", timeout=10) as page:
        return {(x["stageId"], x["attemptId"]): x for x in json.load(page)}


def logical(rows: DataFrame) -> tuple[int, int]:
    """Records and bytes (7-bit groups) of rows with an ids column, as they would leave the first phase."""
    found = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(varbyte_size(F.col("ids"))), F.lit(0))).first()
    return found[0], found[1]


def records(p: Prepared, method: str, tau: int, sigma: int, K: int = 4) -> list[tuple[int, int, int]]:
    """(round, records, bytes) that a method sends between its phases, counted on its real rows."""
    if method == "direct":
        return [(1, *logical(gram_rows(p.runs, sigma)))]
    if method == "suffix":
        return [(1, *logical(suffix_rows(p.runs, sigma)))]
    if method == "index":
        top = min(K, sigma)
        out = [(1, *logical(within_documents(p.runs, top)))]
        numbers = F.aggregate("plist", F.lit(0).cast("long"), lambda s, e: s + 8 + 8 * F.size(e["positions"]))

        def joined(k: int, level: DataFrame) -> None:
            """A level meets itself: each gram's list is sent twice, by its tail and by its head, whole or as rows of one occurrence."""
            size = varbyte_size(F.col("ids")) + (numbers if "plist" in level.columns else F.lit(16))
            found = level.agg(F.count_distinct("ids"), F.coalesce(F.sum(size), F.lit(0))).first()
            out.append((k + 2 - top, 2 * found[0], 2 * found[1]))

        levelwise_index(p, tau, sigma, K, "nested", seen=joined)
        return out
    out, level = [(1, *logical(windows(p.runs, 1)))], level_one(p, tau)
    for k in range(2, sigma + 1):
        rows = windows(p.runs, k)
        rows = prune(rows, level, k, "auto") if k > 2 else rows
        out.append((k, *logical(rows)))
        level = stage(rows.groupBy("ids").agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau), "level")
        if level.isEmpty():
            break
    return out


def expected_direct(p: Prepared, sigma: int) -> DataFrame:
    """Sum of cf over all n-grams, from the runs' lengths alone."""
    n = F.size("ids").cast("bigint")
    whole = F.least(n, F.lit(sigma).cast("bigint"))
    return p.runs.agg(F.coalesce(F.sum(whole * n - (whole * (whole - 1) / 2).cast("bigint")), F.lit(0)).alias("records"))


def expected_suffix(p: Prepared, tau: int) -> DataFrame:
    """Sum of cf over the terms that are left."""
    return p.dictionary.where(F.col("cf") >= tau).agg(F.coalesce(F.sum("cf"), F.lit(0)).alias("records"))


def expected_index(stats: DataFrame, lists: DataFrame, K: int, sigma: int) -> DataFrame:
    """Sum of df up to K terms, and twice the frequent n-grams of K to sigma-1 terms. ``lists``: a row for each n-gram and document."""
    n = F.size("ids")
    again = stats.where((n >= K) & (n < sigma)).agg((2 * F.count(F.lit(1))).alias("more"))
    first = lists.where(n <= K).agg(F.count(F.lit(1)).alias("first"))
    return first.crossJoin(again).select((F.col("first") + F.col("more")).alias("records"))


def expected_scan(all_counts: DataFrame, tau: int) -> DataFrame:
    """Sum of cf over n-grams all of whose proper parts are frequent (``all_counts``: ids, cf, nothing filtered)."""
    frequent = all_counts.where(F.col("cf") >= tau).select("ids")
    rows, n = all_counts, F.size("ids")
    for side in (F.slice("ids", F.lit(1), n - 1), F.slice("ids", F.lit(2), n - 1)):
        longer = rows.where(n > 1).join(frequent.withColumnRenamed("ids", "part"), side == F.col("part"), "left_semi")
        rows = rows.where(n == 1).unionByName(longer)
    return rows.agg(F.coalesce(F.sum("cf"), F.lit(0)).alias("records"))


def corpus_profile(corpus: DataFrame) -> DataFrame:
    """Documents, term occurrences, distinct terms, sequences, mean and standard deviation of their lengths."""
    n = F.size("terms")
    sizes = corpus.agg(F.count_distinct("doc_id").alias("documents"), F.coalesce(F.sum(n.cast("bigint")), F.lit(0)).alias("occurrences"), F.count(F.lit(1)).alias("sequences"), F.round(F.avg(n), 4).alias("mean_len"), F.round(F.stddev_pop(n), 4).alias("sd_len"))
    terms = corpus.select(F.explode("terms").alias("term")).agg(F.count_distinct("term").alias("distinct_terms"))
    return sizes.crossJoin(terms).select("documents", "occurrences", "distinct_terms", "sequences", "mean_len", "sd_len")


def output_buckets(stats: DataFrame) -> DataFrame:
    """(len_bucket, cf_bucket, grams): how many results per power of ten of length and frequency, by exact integer logarithms."""
    log = lambda c: (F.length(c.cast("string")) - 1).cast("bigint")
    return stats.groupBy(log(F.col("n")).alias("len_bucket"), log(F.col("cf")).alias("cf_bucket")).agg(F.count(F.lit(1)).alias("grams"))


def entries_held(all_counts: DataFrame, tau: int, sigma: int, K: int = 4) -> DataFrame:
    """(method, held): what one task of a method keeps at once, in entries. ``all_counts``: ids, cf of all n-grams, nothing filtered.

    scan: the frequent n-grams of its largest level but the last; index: the occurrences in the longest list of at most ``K`` terms;
    suffix_hash: the n-grams that begin with one term; suffix: the terms of the longest path.
    """
    n = F.size("ids")
    levels = all_counts.where((F.col("cf") >= tau) & (n < sigma)).groupBy(n.alias("n")).agg(F.count(F.lit(1)).alias("x"))
    firsts = all_counts.groupBy(F.col("ids")[0].alias("first")).agg(F.count(F.lit(1)).alias("x"))
    most = lambda df, x: df.agg(F.coalesce(F.max(x), F.lit(0)).cast("bigint").alias("held"))
    parts = {"scan": most(levels, "x"), "index": most(all_counts.where(n <= K), "cf"), "suffix_hash": most(firsts, "x"), "suffix": most(all_counts, n)}
    rows = [df.select(F.lit(name).alias("method"), "held") for name, df in parts.items()]
    return rows[0].union(rows[1]).union(rows[2]).union(rows[3])


def byte_orders(texts: DataFrame, lengths: tuple[int, ...]) -> DataFrame:
    """(terms, method, records, bytes) for the first so many terms of every text (column terms) that has the most of ``lengths``, at unbounded
    length: n-grams take bytes with the cube of a document's length, suffixes with its square.

    Term i of n begins n-i+1 n-grams and one suffix, and stands in i (n-i+1) n-grams and i suffixes; its id is that of the dictionary of
    all texts. So the rows are reckoned from each term's place and id, and none is written out.
    """
    octets = build_dictionary(texts, 1).select("term", varbyte_size(F.array("id")).alias("octets"))
    long = texts.where(F.size("terms") >= max(lengths))
    placed = long.select(F.posexplode(F.slice("terms", 1, max(lengths))).alias("at", "term")).groupBy("at", "term").agg(F.count(F.lit(1)).alias("n"))
    sizes = placed.join(octets, "term").groupBy((F.col("at") + 1).cast("long").alias("i")).agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("octets")).alias("octets"))
    grown = sizes.select("*", F.explode(F.array(*[F.lit(x).cast("long") for x in lengths])).alias("terms")).where("i <= terms")
    after = F.col("terms") - F.col("i") + 1
    parts = []
    for method, begun in (("direct", after), ("suffix", F.lit(1))):
        sent = grown.groupBy("terms").agg(F.sum(F.col("n") * begun).cast("bigint").alias("records"), F.sum(F.col("octets") * F.col("i") * begun).cast("bigint").alias("bytes"))
        parts.append(sent.select("terms", F.lit(method).alias("method"), "records", "bytes"))
    return parts[0].union(parts[1])


def growth(orders: DataFrame) -> DataFrame:
    """``byte_orders`` with the power of the length by which records and bytes grew since the length before."""
    w = Window.partitionBy("method").orderBy("terms")
    power = lambda c: F.round(F.log(F.col(c) / F.lag(c).over(w)) / F.log(F.col("terms") / F.lag("terms").over(w)), 2)
    return orders.select("*", power("records").alias("records_power"), power("bytes").alias("bytes_power"))


def methods() -> dict[str, Callable[[Prepared, int, int], DataFrame]]:
    from seqstat.operators.direct import direct_count
    from seqstat.operators.levelwise_scan import levelwise_scan
    from seqstat.operators.suffix import suffix_scan

    return {"direct": direct_count, "scan": levelwise_scan, "index": lambda *a: levelwise_index(*a, 4)[0], "suffix": suffix_scan}


def effort() -> dict[str, int]:
    """Lines of our own code that each method needs beside the engine's operators: its module, and the suffix method's kernel."""
    from seqstat.operators import direct, levelwise_index, levelwise_scan, suffix, suffix_kernel

    parts = {"direct": [direct], "scan": [levelwise_scan], "index": [levelwise_index], "suffix": [suffix, suffix_kernel]}
    lines = lambda m: sum(bool(x.strip()) and not x.strip().startswith("#") for x in inspect.getsource(m).splitlines())
    return {name: sum(map(lines, modules)) for name, modules in parts.items()}


def protocol(spark: SparkSession, repeats: int) -> dict[str, str]:
    """The conditions of a measurement."""
    sc = spark.sparkContext
    asked = {"shuffle_partitions": "spark.sql.shuffle.partitions", "adaptive": "spark.sql.adaptive.enabled", "max_partition_bytes": "spark.sql.files.maxPartitionBytes"}
    return {"spark": sc.version, "master": sc.master, "slots": str(sc.defaultParallelism), "repeats": str(repeats)} | {k: spark.conf.get(v) for k, v in asked.items()}


def compare(p: Prepared, tau: int, sigma: int, names: tuple[str, ...] = ("direct", "scan", "index", "suffix"), repeats: int = 1) -> list[Measure]:
    """Each method on the same prepared corpus, so that preparation is in none of the times; of several runs the one of median time."""
    make, out = methods(), []
    for name in names:
        runs = [timed(name, lambda n=name: make[n](p, tau, sigma)) for _ in range(repeats)]
        middle = statistics.median_low([m.seconds for m in runs])
        out.append(next(m for m in runs if m.seconds == middle))
    return out


def speedup(measures: list[Measure], own: str = "suffix") -> dict[str, float]:
    base = next(m.seconds for m in measures if m.method == own)
    return {m.method: round(m.seconds / base, 2) for m in measures}


def as_row(m: Measure) -> dict:
    return asdict(m)


__all__ = ["Measure", "byte_orders", "compare", "corpus_profile", "effort", "entries_held", "expected_direct", "expected_index", "expected_scan", "expected_suffix", "growth", "logical", "methods", "output_buckets", "postings", "protocol", "records", "speedup", "timed"]
