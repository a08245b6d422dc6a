"""Windowed, sessioned and stateful n-gram counts over a stream of events; each has a batch twin over the whole table.

Thresholds hold when results are read, never while they are kept: a count below the threshold may pass it later.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from seqstat.sources.tables import shared_folder, table


def source(spark: SparkSession, sf_dir: str, closing: bool = False, repeats: int = 1, rows: int = 1_000_000) -> DataFrame:
    """The events table replayed as a stream of Parquet files, written one after another in time order; ts as a timestamp.

    A file, written by one task, holds about ``rows`` events at most; there are four at least. Events without a time are left out, as no
    window holds them. With ``repeats`` each event is sent so many times. With ``closing`` an event two days after the last one ends the stream: it lifts the watermark past all windows and sessions before
    it, so that they are handed on, and its own stay open.
    """
    path = f"{shared_folder(spark)}/seqstat/stream-{uuid.uuid4().hex}"
    events = batch(spark, sf_dir)
    files = max(4, -(-events.count() // rows))
    cuts = events.select(F.unix_micros("ts").alias("m")).approxQuantile("m", [i / files for i in range(1, files)], 0.01)
    for low, high in zip([float("-inf"), *cuts], [*cuts, float("inf")], strict=True):
        part = events.where((F.unix_micros("ts") >= low) & (F.unix_micros("ts") < high))
        part.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.lit(repeats)))).drop("__copy").coalesce(1).write.mode("append").parquet(path)
    if closing:
        last = events.agg(F.max("ts").alias("ts")).where("ts is not null").select((F.col("ts") + F.expr("interval 2 days")).alias("ts"))
        row = last.select(*["ts" if f.name == "ts" else F.lit(None).cast(f.dataType).alias(f.name) for f in events.schema])
        row.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)


def batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").where("user_id is not null and ts is not null").withColumn("ts", F.col("ts").cast("timestamp"))


def finished(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a query over all that is there and return what its sink got. Append goes to files; the other modes to a last-write table."""
    spark = df.sparkSession
    base = f"{shared_folder(spark)}/seqstat/sink-{uuid.uuid4().hex}"
    writer = df.writeStream.option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")

    def keep(part: DataFrame, number: int) -> None:
        part.withColumn("__batch", F.lit(number)).write.mode("append").parquet(f"{base}/out")

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.parquet(f"{base}/out")


def windowed_counts(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts of event types per window and type; events later than ``late`` are dropped."""
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    counted = marked.groupBy(span.alias("w"), F.col("event_type").alias("gram")).agg(F.count(F.lit(1)).alias("cf"))
    return counted.select(F.unix_seconds("w.start").alias("start"), "gram", "cf")


def session_sequences(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """One sequence of event types per user and session."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    listed = marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("e"))
    return listed.select("user_id", F.unix_seconds("w.start").alias("start"), F.array_join("e.event_type", " ").alias("terms"))


def dedupe(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, though a source repeats it within the watermark."""
    twice = events.unionByName(events) if not events.isStreaming else events
    if events.isStreaming:
        return twice.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return twice.dropDuplicates(["event_id"])


def enrich(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: events with their customer's segment."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "event_type", "c_mktsegment")


CARRIED = "gram string, n int, cf bigint"


def carry_counts(events: DataFrame, sigma: int = 2) -> DataFrame:
    """(gram, n, cf) parts to be summed: a user's last sigma-1 types are kept as state, so that n-grams span micro-batches. Rows of
    a micro-batch are ordered by time and id within a user."""
    out = T._parse_datatype_string(CARRIED)
    state = T._parse_datatype_string("tail array<string>")

    def step(key: tuple, parts: Iterator[pd.DataFrame], kept: GroupState) -> Iterator[pd.DataFrame]:
        tail = list(kept.get[0]) if kept.exists else []
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        terms = tail + rows["event_type"].tolist()
        counts: dict[tuple[str, ...], int] = {}
        for end in range(len(tail), len(terms)):
            for n in range(1, min(sigma, end + 1) + 1):
                gram = tuple(terms[end - n + 1 : end + 1])
                counts[gram] = counts.get(gram, 0) + 1
        kept.update((terms[-(sigma - 1) :] if sigma > 1 else [],))
        yield pd.DataFrame([(" ".join(g), len(g), c) for g, c in counts.items()], columns=["gram", "n", "cf"])

    return events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(step, out, state, "append", GroupStateTimeout.NoTimeout)


def carry_counts_batch(events: DataFrame, sigma: int = 2) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    terms = [F.lag("event_type", k).over(order) for k in range(sigma - 1, 0, -1)] + [F.col("event_type")]
    parts = None
    for n in range(1, sigma + 1):
        picked = events.select(F.array(*terms[sigma - n :]).alias("t")).where(~F.exists("t", lambda x: x.isNull()))
        part = picked.groupBy(F.array_join("t", " ").alias("gram")).agg(F.lit(n).alias("n"), F.count(F.lit(1)).alias("cf"))
        parts = part if parts is None else parts.unionByName(part)
    return parts


def merge_batch(path: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: add a micro-batch's counts as one more part, named by its number, so that a retry replaces it."""

    def merge(part: DataFrame, number: int) -> None:
        part.groupBy("gram").agg(F.count(F.lit(1)).alias("cf")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return merge


def merged(spark: SparkSession, path: str, tau: int) -> DataFrame:
    """All parts added up, and only then held against the threshold."""
    parts = spark.read.schema("gram string, cf bigint, batch int").parquet(path)
    return parts.groupBy("gram").agg(F.sum("cf").alias("cf")).where(F.col("cf") >= tau)


def incremental(events: DataFrame, tau: int = 1) -> DataFrame:
    spark = events.sparkSession
    base = f"{shared_folder(spark)}/seqstat/merge-{uuid.uuid4().hex}"
    named = events.select(F.col("event_type").alias("gram"))
    named.writeStream.option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).foreachBatch(merge_batch(f"{base}/parts")).start().awaitTermination()
    return merged(spark, f"{base}/parts", tau)


def queries() -> dict:
    """Streams run to their end, and their batch twins."""
    customers = lambda s, d: table(s, d, "customer", "c_custkey", "c_mktsegment")
    total = lambda df: df.groupBy("gram", F.col("n").cast("bigint").alias("n")).agg(F.sum("cf").alias("cf"))
    grams = lambda df: df.groupBy("gram").agg(F.count(F.lit(1)).alias("cf"))
    return {
        "stream_tumbling": lambda s, d: finished(windowed_counts(source(s, d, closing=True))),
        "stream_tumbling_batch": lambda s, d: windowed_counts(batch(s, d)),
        "stream_sliding": lambda s, d: finished(windowed_counts(source(s, d, closing=True), "1 hour", "15 minutes")),
        "stream_sliding_batch": lambda s, d: windowed_counts(batch(s, d), "1 hour", "15 minutes"),
        "stream_session": lambda s, d: finished(session_sequences(source(s, d, closing=True))),
        "stream_session_batch": lambda s, d: session_sequences(batch(s, d)),
        "stream_late": lambda s, d: finished(windowed_counts(source(s, d), late="0 seconds")),
        "stream_dedupe": lambda s, d: finished(dedupe(source(s, d, repeats=2)).select("event_id", "event_type")),
        "stream_dedupe_batch": lambda s, d: dedupe(batch(s, d)).select("event_id", "event_type"),
        "stream_enrich": lambda s, d: finished(enrich(source(s, d), customers(s, d))),
        "stream_enrich_batch": lambda s, d: enrich(batch(s, d), customers(s, d)),
        "stream_carry": lambda s, d: total(finished(carry_counts(source(s, d)))),
        "stream_carry_batch": lambda s, d: total(carry_counts_batch(batch(s, d))),
        "stream_merge": lambda s, d: incremental(source(s, d)),
        "stream_merge_batch": lambda s, d: grams(batch(s, d).select(F.col("event_type").alias("gram"))),
    }


def oracle_sql() -> dict[str, str]:
    events = "from events where user_id is not null"
    tumbling = f"select cast(floor(epoch_us(ts) / 3600000000) as bigint) * 3600 as start, event_type gram, count(*) cf {events} group by 1, 2"
    sliding = f"select cast(floor(epoch_us(ts) / 900000000) as bigint) * 900 - o * 900 as start, event_type gram, count(*) cf from events, (values (0), (1), (2), (3)) s(o) where user_id is not null group by 1, 2"
    carry = f"with o as (select event_type b, lag(event_type) over (partition by user_id order by ts, event_id) a {events}) select b gram, cast(1 as bigint) n, count(*) cf from o group by b union all select a || ' ' || b, cast(2 as bigint), count(*) from o where a is not null group by 1"
    dedupe_sql = f"select event_id, event_type {events}"
    enriched = "select event_id, event_type, c_mktsegment from events join customer on user_id = c_custkey"
    session = f"""with o as (select *, case when ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 1 else 0 end brk {events}),
g as (select *, sum(brk) over (partition by user_id order by ts, event_id) sid from o)
select user_id, cast(floor(epoch_us(min(ts)) / 1000000) as bigint) as start, string_agg(event_type, ' ' order by ts, event_id) terms from g group by user_id, sid"""
    return {
        "stream_tumbling": tumbling,
        "stream_tumbling_batch": tumbling,
        "stream_sliding": sliding,
        "stream_sliding_batch": sliding,
        "stream_session": session,
        "stream_session_batch": session,
        "stream_dedupe": dedupe_sql,
        "stream_dedupe_batch": dedupe_sql,
        "stream_enrich": enriched,
        "stream_enrich_batch": enriched,
        "stream_carry": carry,
        "stream_carry_batch": carry,
        "stream_merge": f"select event_type gram, count(*) cf {events} group by 1",
        "stream_merge_batch": f"select event_type gram, count(*) cf {events} group by 1",
    }
