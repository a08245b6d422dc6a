"""Text to token sequences: boilerplate removal, sentence barriers, tokens; and sequences of other terms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Sentence barrier and token patterns.
BARRIER = r"[.!?\n]+"
TOKEN = r"[\p{L}\p{N}]+"
#: Positions of a document's next sequence lie so far on that no two sequences touch.
STRIDE = 1 << 32


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def sentences(text: Column) -> Column:
    return F.split(text, BARRIER)


def main_text(html: Column) -> Column:
    """The article's text: scripts, styles, lists of links and advertisements go, block tags become barriers."""
    body = F.regexp_extract(html, r"(?s)<article[^>]*>(.*?)</article>", 1)
    body = F.regexp_replace(body, r"(?s)<!--.*?-->|<(script|style|nav|aside|ul)\b.*?</(script|style|nav|aside|ul)>|<div class=.?ad.*?</div>", "\n")
    body = F.regexp_replace(body, r"(?i)</?(p|div|h[1-6]|li|ul|ol|br|section|blockquote|td|tr|table)\b[^>]*>", "\n")
    bare = F.regexp_replace(body, r"<[^>]*>", "")
    for entity, mark in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        bare = F.replace(bare, F.lit(entity), F.lit(mark))
    return bare


def from_text(df: DataFrame, key: str, text: Column, *meta: Column) -> DataFrame:
    """corpus: doc_id, seq_no, pos (of the first term), terms, meta columns. Null and blank texts give no sequence."""
    split = df.select(F.col(key).cast("long").alias("doc_id"), *meta, F.posexplode(sentences(text)).alias("seq_no", "__s"))
    kept = [c for c in split.columns if c != "__s"]
    some = split.where(F.lower("__s").rlike(TOKEN))  # a filter on the terms would be pushed down and find them all twice
    return placed(some.select(*kept, tokens(F.col("__s")).alias("terms")))


def from_sequences(df: DataFrame) -> DataFrame:
    """Rows (doc_id, seq_no, terms, ...) as a corpus; empty sequences are dropped."""
    return placed(df.where(F.size("terms") > 0))


def placed(df: DataFrame) -> DataFrame:
    return df.withColumn("pos", F.col("seq_no").cast("long") * STRIDE)


def documents(spark, sf_dir: str, *meta: Column) -> DataFrame:
    from seqstat.sources.tables import table

    return from_text(table(spark, sf_dir, "documents"), "doc_id", F.col("text"), *meta)


def pages(spark, sf_dir: str) -> DataFrame:
    from seqstat.sources.tables import table

    return from_text(table(spark, sf_dir, "pages"), "page_id", main_text(F.col("html")))


def benchmark(spark, sf_dir: str) -> DataFrame:
    from seqstat.sources.tables import table

    return from_text(table(spark, sf_dir, "benchmark"), "item_id", F.col("text"))


def conversations(spark, sf_dir: str) -> DataFrame:
    """One document per conversation; every sentence of every turn is a sequence."""
    from seqstat.sources.tables import table

    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.posexplode(sentences(F.col("text"))).alias("__i", "__s"))
    rows = turns.select(F.col("conv_id").alias("doc_id"), (F.col("turn") * 100_000 + F.col("__i")).alias("seq_no"), "role", tokens(F.col("__s")).alias("terms"))
    return from_sequences(rows)


def event_days(spark, sf_dir: str, barrier: bool = True) -> DataFrame:
    """Event types of a user in time order; with ``barrier`` a sequence for each calendar day (meta: day)."""
    from seqstat.sources.tables import table

    rows = table(spark, sf_dir, "events", "user_id", "ts", "event_id", "event_type").where("user_id is not null")
    day = F.to_date("ts").alias("day")
    keys = ["user_id", day] if barrier else ["user_id"]
    listed = rows.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type")))["event_type"].alias("terms"))
    number = F.datediff("day", F.lit("1970-01-01")) if barrier else F.lit(0)
    return from_sequences(listed.select(F.col("user_id").alias("doc_id"), number.alias("seq_no"), *(["day"] if barrier else []), "terms"))


def customer_orders(spark, sf_dir: str) -> DataFrame:
    """Part types of a customer's orders, an order per sequence (meta: year). Lines that agree in all keys are alike."""
    from seqstat.sources.tables import table

    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    parts = table(spark, sf_dir, "part", "p_partkey", "p_type")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    line = F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "p_type")
    listed = joined.groupBy("o_custkey", "o_orderkey", "o_orderdate").agg(F.sort_array(F.collect_list(line))["p_type"].alias("terms"))
    return from_sequences(listed.select(F.col("o_custkey").alias("doc_id"), F.col("o_orderkey").alias("seq_no"), F.year("o_orderdate").cast("long").alias("period"), "terms"))


def literal(spark, *texts: str) -> DataFrame:
    """A corpus of literal documents of blank-separated terms, numbered from 1."""
    rows = [(i, 0, t.split()) for i, t in enumerate(texts, 1)]
    return from_sequences(spark.createDataFrame(rows, "doc_id long, seq_no int, terms array<string>"))
