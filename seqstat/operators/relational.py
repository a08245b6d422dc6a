"""Operators around the counting methods: scans, joins, aggregates, windows, sets and functions on the given tables.

Each key takes (spark, sf_dir). Joins against tables whose size isn't known to be small are left to the planner.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqstat.functions import grams, text
from seqstat.operators.direct import direct_count
from seqstat.operators.encode import Options, decode, prepare
from seqstat.sources.tables import shared_folder, stage, table, write_stats

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a function under its name, with its SQL."""

    def put(function):
        QUERIES[function.__name__] = function
        if sql:
            ORACLES[function.__name__] = sql
        return function

    return put


TOK = r"(select doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) t from documents)"
PTOK = r"(select item_id doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) t from benchmark)"


def stats(spark: SparkSession, sf_dir: str, tau: int = 5, sigma: int = 3) -> DataFrame:
    """gram, n, cf of the documents: the input of many keys below."""
    p = prepare(text.documents(spark, sf_dir), tau, Options())
    found = direct_count(p, tau, sigma).select("ids", F.size("ids").cast("bigint").alias("n"), "cf")
    return decode(found, p.dictionary)


def stats_sql(select: str, tau: int = 5, sigma: int = 3) -> str:
    from seqstat.plans.oracle import stats_cte

    return f"{stats_cte(tau, sigma)} {select}"


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of a timestamp without zone, whatever the session's zone."""
    whole = F.datediff(ts, F.lit("1970-01-01")).cast("bigint") * 86400 + F.hour(ts) * 3600 + F.minute(ts) * 60
    return whole * 1_000_000 + (F.date_part(F.lit("SECOND"), ts) * 1_000_000).cast("bigint")


def vocabulary(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    """term, cf of the words of ``documents`` or ``benchmark``."""
    words = table(spark, sf_dir, source).select(F.explode(text.tokens(F.col("text"))).alias("term"))
    return words.groupBy("term").agg(F.count(F.lit(1)).alias("cf"))


# Scans, sinks and filters.
@query("select doc_id, lang, n_chars from documents")
def scan_documents(spark, d):
    return table(spark, d, "documents", "doc_id", "lang", "n_chars")


@query("select unnest(['csv', 'json', 'orc', 'parquet']) format, (select count(*) from region) as rows")
def scan_formats(spark, d):
    """The regions written to and read from four formats, with an explicit schema."""
    from seqstat.sources.tables import read

    regions, out = table(spark, d, "region", "r_regionkey", "r_name"), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = f"{shared_folder(spark)}/seqstat/formats-{uuid.uuid4().hex}/{fmt}"
        regions.write.format(fmt).option("header", True).save(path)
        got = read(spark, fmt, path, "r_regionkey int, r_name string").agg(F.lit(fmt).alias("format"), F.count("r_name").alias("rows"))
        out = got if out is None else out.unionByName(got)
    return out


@query(stats_sql("select gram, cf from stats where n = 2 and cf >= 10 and gram like 'th%'"))
def filter_stats(spark, d):
    """A filter on length and frequency goes into the method's parameters, one on the gram stays."""
    from seqstat.plans.choose import limits

    tau, sigma = limits(5, 3, max_n=2, min_cf=10)
    return stats(spark, d, tau, sigma).where((F.col("n") == 2) & F.col("gram").startswith("th")).select("gram", "cf")


@query("select doc_id from documents where n_chars between 1000 and 5000 and lang in ('en', 'de')")
def filter_long_docs(spark, d):
    return table(spark, d, "documents").where(F.col("n_chars").between(1000, 5000) & F.col("lang").isin("en", "de")).select("doc_id")


@query(r"select page_id, regexp_extract(url, '^https?://([^/]+)', 1) host from pages where regexp_matches(url, '^https?://')")
def rlike_urls(spark, d):
    return table(spark, d, "pages", "page_id", "url").where(F.col("url").rlike("^https?://")).select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"))


@query(stats_sql("select n, count(*) as grams, cast(sum(cf) as bigint) occurrences from stats group by n"))
def sink_by_length(spark, d):
    """Statistics written partitioned by length and read back: a filter on n prunes folders."""
    path = f"{shared_folder(spark)}/seqstat/by-length-{uuid.uuid4().hex}"
    write_stats(stats(spark, d), path)
    return spark.read.schema("gram string, cf bigint, n bigint").parquet(path).groupBy("n").agg(F.count(F.lit(1)).alias("grams"), F.sum("cf").alias("occurrences"))


@query("select doc_id, lang from documents where length(trim(text)) > 0")
def drop_blank(spark, d):
    return table(spark, d, "documents").where(F.length(F.trim(F.coalesce("text", F.lit("")))) > 0).select("doc_id", "lang")


# Joins.
@query("select quality, toxic, count(*) docs, round(avg(n_chars), 4) mean_chars from documents join labels using (doc_id) group by quality, toxic")
def join_docs_labels(spark, d):
    joined = table(spark, d, "documents", "doc_id", "n_chars").join(table(spark, d, "labels"), "doc_id")
    return joined.groupBy("quality", "toxic").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg("n_chars"), 4).alias("mean_chars"))


SEGMENTS = "select c_mktsegment segment, count(*) orders, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) cents from orders join customer on o_custkey = c_custkey group by c_mktsegment"


def _segments(spark, d, hint: str) -> DataFrame:
    customers = table(spark, d, "customer", "c_custkey", "c_mktsegment").hint(hint)
    joined = table(spark, d, "orders", "o_custkey", "o_totalprice").join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("orders"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


@query(SEGMENTS)
def join_hash(spark, d):
    return _segments(spark, d, "shuffle_hash")


@query(SEGMENTS)
def join_merge(spark, d):
    return _segments(spark, d, "merge")


@query(SEGMENTS)
def join_planned(spark, d):
    """The planner broadcasts by its own size check."""
    customers = table(spark, d, "customer", "c_custkey", "c_mktsegment")
    joined = table(spark, d, "orders", "o_custkey", "o_totalprice").join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("orders"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


@query("select doc_id from documents where doc_id in (select doc_id from labels)")
def semi_labeled(spark, d):
    return table(spark, d, "documents", "doc_id").join(table(spark, d, "labels", "doc_id"), "doc_id", "left_semi")


@query("select doc_id from documents where doc_id not in (select doc_id from labels)")
def anti_labeled(spark, d):
    return table(spark, d, "documents", "doc_id").join(table(spark, d, "labels", "doc_id"), "doc_id", "left_anti")


@query("select d.doc_id, coalesce(quality, -1) quality from documents d left join labels l on d.doc_id = l.doc_id")
def left_join_labels(spark, d):
    joined = table(spark, d, "documents", "doc_id").join(table(spark, d, "labels", "doc_id", "quality"), "doc_id", "left")
    return joined.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"))


@query(f"with a as (select t term, count(*) c from {TOK} group by t), b as (select t term, count(*) c from {PTOK} group by t) select coalesce(a.term, b.term) term, coalesce(a.c, 0) cf_documents, coalesce(b.c, 0) cf_benchmark from a full join b on a.term = b.term")
def full_vocab(spark, d):
    a, b = (vocabulary(spark, d, s).withColumnRenamed("cf", f"cf_{s}") for s in ("documents", "benchmark"))
    return a.join(b, "term", "full").na.fill(0)


@query(stats_sql("select gram, cf from stats where n = 2", 10, 2))
def candidate_prune(spark, d):
    """Bigrams counted only where both terms are frequent."""
    from seqstat.operators.levelwise_scan import level_one, prune, windows

    p = prepare(text.documents(spark, d), 1, Options())
    rows = prune(windows(p.runs, 2), level_one(p, 10), 2, "auto")
    counted = rows.groupBy("ids").agg(F.count(F.lit(1)).alias("cf")).where("cf >= 10")
    return decode(counted, p.dictionary)


@query(stats_sql("select r.gram r, s.gram s from stats r join stats s on r.n < s.n and (' ' || s.gram || ' ') like ('% ' || r.gram || ' %')", 100, 3))
def theta_subsumption(spark, d):
    """Pairs in which one gram contains another: s's parts are joined to r on equality, not each with each."""
    found = stage(stats(spark, d, 100, 3), "grams")
    terms = F.split("gram", " ")
    parts = found.select(F.col("gram").alias("s"), F.explode(F.array_distinct(F.transform(grams.ngrams(terms, 3), grams.gram))).alias("r")).where("r <> s")
    return parts.join(found.select(F.col("gram").alias("r")), "r").select("r", "s")


BANDS = [(5, 10), (10, 20), (20, 50), (50, 100), (100, 1000), (1000, 1 << 40)]


@query(stats_sql(f"select lo as band, count(*) as grams from stats join (values {', '.join(map(str, BANDS))}) b(lo, hi) on cf >= lo and cf < hi group by lo"))
def range_cf_bands(spark, d):
    bands = spark.createDataFrame(BANDS, "lo bigint, hi bigint")
    return stats(spark, d).join(F.broadcast(bands), (F.col("cf") >= F.col("lo")) & (F.col("cf") < F.col("hi"))).groupBy(F.col("lo").alias("band")).agg(F.count(F.lit(1)).alias("grams"))


@query("select p.event_id purchase_id, count(e.event_id) errors from events p left join events e on e.user_id = p.user_id and e.event_type = 'error' and e.ts >= p.ts - interval 10 minutes and e.ts < p.ts where p.event_type = 'purchase' group by p.event_id")
def interval_purchase(spark, d):
    """Errors of a user in the 10 minutes before a purchase: equal 10-minute bins and the one before make it an equi-join."""
    events = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    slot = F.floor(micros(F.col("ts")) / F.lit(600_000_000))
    bought = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("ts").alias("at"), "user_id", F.explode(F.array(slot, slot - 1)).alias("slot"))
    errors = events.where("event_type = 'error'").select("user_id", "ts", "event_id", slot.alias("slot"))
    near = (F.col("ts") >= F.col("at") - F.expr("interval 10 minutes")) & (F.col("ts") < F.col("at"))
    joined = bought.join(errors, ["user_id", "slot"], "left").withColumn("hit", near)
    return joined.groupBy("purchase_id").agg(F.count_if("hit").alias("errors"))


@query("select a.event_id, epoch_us(b.ts) last_error from events a asof left join (select user_id, ts from events where event_type = 'error') b on a.user_id = b.user_id and a.ts > b.ts")
def asof_last_error(spark, d):
    """The latest earlier error of the same user, in one sorted pass."""
    events = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    earlier = Window.partitionBy("user_id").orderBy(micros(F.col("ts"))).rangeBetween(Window.unboundedPreceding, -1)
    error = F.when(F.col("event_type") == "error", micros(F.col("ts")))
    return events.select("event_id", F.last(error, ignorenulls=True).over(earlier).alias("last_error"))


@query("select t.tau, s.sigma, cast(t.tau * s.sigma as bigint) cell from (select distinct cast(l_quantity as int) tau from lineitem) t, (select distinct l_linenumber sigma from lineitem) s")
def cross_grid(spark, d):
    """A parameter grid: each quantity of the lines with each line number (few values, however many lines)."""
    lines = table(spark, d, "lineitem", "l_quantity", "l_linenumber")
    taus, sigmas = lines.select(F.col("l_quantity").cast("int").alias("tau")).distinct(), lines.select(F.col("l_linenumber").alias("sigma")).distinct()
    return taus.crossJoin(sigmas).select("tau", "sigma", (F.col("tau") * F.col("sigma")).cast("bigint").alias("cell"))


# Aggregates.
@query("select event_type, count(*) n, cast(sum(cast(round(value * 100) as bigint)) as bigint) cents, round(avg(value), 4) mean from events group by event_type")
def agg_partial(spark, d):
    return table(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("cents"), F.round(F.avg("value"), 4).alias("mean"))


@query("select source, count(*) docs, min(doc_id) first_doc, max(doc_id) last_doc, md5(string_agg(cast(doc_id as varchar), ',' order by doc_id)) ids from documents group by source")
def agg_sort(spark, d):
    """Sorted lists per group, for groups that are known to be small."""
    ids = F.array_join(F.sort_array(F.collect_list("doc_id")), ",")
    return table(spark, d, "documents", "source", "doc_id").groupBy("source").agg(F.count(F.lit(1)).alias("docs"), F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc"), F.md5(ids).alias("ids"))


@query("select lang, count(distinct source) sources, count(distinct md5(text)) texts from documents group by lang")
def agg_distinct(spark, d):
    return table(spark, d, "documents", "lang", "source", "text").select("lang", "source", F.md5("text").alias("h")).groupBy("lang").agg(F.count_distinct("source").alias("sources"), F.count_distinct("h").alias("texts"))


@query("select lang, count_if(toxic = 1) toxic, count_if(quality = 1) good from documents join labels using (doc_id) group by lang")
def agg_filtered(spark, d):
    joined = table(spark, d, "documents", "doc_id", "lang").join(table(spark, d, "labels"), "doc_id")
    return joined.groupBy("lang").agg(F.count_if(F.col("toxic") == 1).alias("toxic"), F.count_if(F.col("quality") == 1).alias("good"))


def _cubed(spark, d, how: str) -> DataFrame:
    docs = table(spark, d, "documents", "lang", "source", "n_chars")
    return getattr(docs, how)("lang", "source").agg(F.grouping_id().cast("bigint").alias("gid"), F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("chars"))


def _cube_sql(how: str) -> str:
    return f"select lang, source, cast(grouping(lang, source) as bigint) gid, count(*) docs, cast(sum(n_chars) as bigint) chars from documents group by {how}"


@query(_cube_sql("cube (lang, source)"))
def cube_lang_source(spark, d):
    return _cubed(spark, d, "cube")


@query(_cube_sql("rollup (lang, source)"))
def rollup_lang_source(spark, d):
    return _cubed(spark, d, "rollup")


@query(_cube_sql("grouping sets ((lang), (source))"))
def gsets_lang_source(spark, d):
    table(spark, d, "documents", "lang", "source", "n_chars").createOrReplaceTempView("docs_for_sets")
    return spark.sql("select lang, source, cast(grouping_id(lang, source) as bigint) gid, count(*) docs, sum(n_chars) chars from docs_for_sets group by grouping sets ((lang), (source))")


BIGRAM_SQL = """with o as (select user_id, ts, event_type, lead(event_type) over (partition by user_id, cast(ts as date) order by ts, event_id) nx from events where user_id is not null),
g as (select event_type || ' ' || nx gram, cast(floor((epoch_us(ts) - epoch_us(timestamp '2024-01-01')) / 604800000000) as bigint) as week, cast(ts as date) as day from o where nx is not null)"""


def event_bigrams(spark, d) -> DataFrame:
    """Each pair of neighbouring events of a user and day: gram, week, day."""
    events = table(spark, d, "events", "user_id", "ts", "event_id", "event_type").where("user_id is not null")
    order = Window.partitionBy("user_id", F.to_date("ts")).orderBy("ts", "event_id")
    pairs = events.withColumn("nx", F.lead("event_type").over(order)).where("nx is not null")
    week = F.floor((micros(F.col("ts")) / 1_000_000 - 1704067200) / 604800).cast("bigint")
    return pairs.select(F.concat_ws(" ", "event_type", "nx").alias("gram"), week.alias("week"), F.to_date("ts").alias("day"))


@query(f"{BIGRAM_SQL} select gram, count_if(week = 0) w0, count_if(week = 1) w1, count_if(week = 2) w2, count_if(week = 3) w3, count_if(week = 4) w4 from g group by gram")
def pivot_period(spark, d):
    wide = event_bigrams(spark, d).groupBy("gram").pivot("week", [0, 1, 2, 3, 4]).count().na.fill(0)
    return wide.select("gram", *[F.col(str(w)).alias(f"w{w}") for w in range(5)])


@query()
def approx_vocab(spark, d):
    """Sketches in one pass: distinct terms and quantiles of their lengths."""
    words = table(spark, d, "documents").select(F.explode(text.tokens(F.col("text"))).alias("t"))
    return words.agg(F.approx_count_distinct("t").alias("terms"), F.percentile_approx(F.length("t"), [0.5, 0.9, 0.99]).alias("quantiles"))


# Windows, order and sets.
@query(stats_sql("select gram, n, row_number() over w rn, rank() over (partition by n order by cf desc) rk, dense_rank() over (partition by n order by cf desc) dr, cast(ntile(4) over w as bigint) q from stats window w as (partition by n order by cf desc, gram)", 20, 3))
def win_rank(spark, d):
    w, by_cf = Window.partitionBy("n").orderBy(F.desc("cf"), "gram"), Window.partitionBy("n").orderBy(F.desc("cf"))
    ranks = [f.cast("bigint").alias(a) for f, a in ((F.row_number().over(w), "rn"), (F.rank().over(by_cf), "rk"), (F.dense_rank().over(by_cf), "dr"), (F.ntile(4).over(w), "q"))]
    return stats(spark, d, 20, 3).select("gram", "n", *ranks)


DAILY = f"{BIGRAM_SQL}, s as (select gram, cast(datediff('day', date '1970-01-01', day) as bigint) d, count(*) cf from g group by gram, day)"


def daily(spark, d) -> DataFrame:
    return event_bigrams(spark, d).groupBy("gram", F.datediff("day", F.lit("1970-01-01")).cast("bigint").alias("d")).agg(F.count(F.lit(1)).alias("cf"))


@query(f"{DAILY} select gram, d, cf, cf - lag(cf) over w change, lead(cf) over w nxt from s window w as (partition by gram order by d)")
def win_lag_lead(spark, d):
    w = Window.partitionBy("gram").orderBy("d")
    return daily(spark, d).select("gram", "d", "cf", (F.col("cf") - F.lag("cf").over(w)).alias("change"), F.lead("cf").over(w).alias("nxt"))


@query(f"{DAILY} select gram, d, cast(sum(cf) over (partition by gram order by d rows between 2 preceding and current row) as bigint) moving from s")
def win_rows_frame(spark, d):
    return daily(spark, d).select("gram", "d", F.sum("cf").over(Window.partitionBy("gram").orderBy("d").rowsBetween(-2, 0)).alias("moving"))


@query(f"{DAILY} select gram, d, cast(sum(cf) over (partition by gram order by d range between 6 preceding and current row) as bigint) weekly from s")
def win_range_frame(spark, d):
    return daily(spark, d).select("gram", "d", F.sum("cf").over(Window.partitionBy("gram").orderBy("d").rangeBetween(-6, 0)).alias("weekly"))


@query(stats_sql("select gram, n, cast(sum(cf) over (partition by n order by cf desc, gram rows unbounded preceding) as bigint) mass from stats", 20, 3))
def win_running_share(spark, d):
    return stats(spark, d, 20, 3).select("gram", "n", F.sum("cf").over(Window.partitionBy("n").orderBy(F.desc("cf"), "gram").rowsBetween(Window.unboundedPreceding, 0)).alias("mass"))


@query(stats_sql("select gram, n, cf from stats order by cf desc, gram limit 20"))
def topk_ngrams(spark, d):
    return stats(spark, d).orderBy(F.desc("cf"), "gram").limit(20)


@query(stats_sql("select gram, n, cf from stats qualify row_number() over (partition by n order by cf desc, gram) <= 5"))
def topk_per_length(spark, d):
    return stats(spark, d).withColumn("r", F.row_number().over(Window.partitionBy("n").orderBy(F.desc("cf"), "gram"))).where("r <= 5").drop("r")


@query(stats_sql("select gram, n, cf from stats", 20, 3))
def sort_global(spark, d):
    return stats(spark, d, 20, 3).orderBy(F.desc("cf"), "gram")


@query(stats_sql("select gram, n, cf from stats order by cf desc, gram limit 10 offset 20", 20, 3))
def limit_offset(spark, d):
    return stats(spark, d, 20, 3).orderBy(F.desc("cf"), "gram").offset(20).limit(10)


def _sets(spark, d) -> tuple[DataFrame, DataFrame]:
    return tuple(table(spark, d, s).select(F.explode(text.tokens(F.col("text"))).alias("term")) for s in ("documents", "benchmark"))


def _set_sql(how: str) -> str:
    return f"select t term from {TOK} {how} select t from {PTOK}"


@query(_set_sql("union"))
def vocab_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@query(_set_sql("intersect"))
def vocab_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@query(_set_sql("except"))
def vocab_except(spark, d):
    a, b = _sets(spark, d)
    return a.subtract(b)


@query(f"select term, count(*) c from ({_set_sql('union all')}) group by term")
def vocab_union_all(spark, d):
    a, b = _sets(spark, d)
    return a.unionByName(b).groupBy("term").agg(F.count(F.lit(1)).alias("c"))


@query(f"select term, count(*) c from ({_set_sql('intersect all')}) group by term")
def vocab_intersect_all(spark, d):
    a, b = _sets(spark, d)
    return a.intersectAll(b).groupBy("term").agg(F.count(F.lit(1)).alias("c"))


@query(f"select term, count(*) c from ({_set_sql('except all')}) group by term")
def vocab_except_all(spark, d):
    a, b = _sets(spark, d)
    return a.exceptAll(b).groupBy("term").agg(F.count(F.lit(1)).alias("c"))


@query("select min(doc_id) doc_id, count(*) copies from documents group by text")
def distinct_texts(spark, d):
    return table(spark, d, "documents", "doc_id", "text").groupBy(F.sha2("text", 256)).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).select("doc_id", "copies")


# Functions.
@query("select doc_id, lower(source) a, substr(text, 1, 5) b, length(text) c, strlen(text) e, replace(source, 'src', 'S') f, levenshtein(lang, source) g, translate(lang, 'en', 'EN') h, concat_ws('-', lang, source) i from documents")
def fn_string(spark, d):
    t = table(spark, d, "documents", "doc_id", "text", "lang", "source")
    return t.select("doc_id", F.lower("source").alias("a"), F.substring("text", 1, 5).alias("b"), F.length("text").cast("bigint").alias("c"), F.octet_length("text").cast("bigint").alias("e"), F.replace("source", F.lit("src"), F.lit("S")).alias("f"), F.levenshtein("lang", "source").cast("bigint").alias("g"), F.translate("lang", "en", "EN").alias("h"), F.concat_ws("-", "lang", "source").alias("i"))


@query("select o_orderkey, year(o_orderdate) a, month(o_orderdate) b, datediff('day', date '1970-01-01', cast(date_trunc('month', o_orderdate) as date)) c, datediff('day', date '1995-01-01', cast(o_orderdate as date)) e from orders")
def fn_date(spark, d):
    t = table(spark, d, "orders", "o_orderkey", "o_orderdate")
    return t.select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("a"), F.month("o_orderdate").cast("bigint").alias("b"), F.datediff(F.trunc("o_orderdate", "month"), F.lit("1970-01-01")).cast("bigint").alias("c"), F.datediff("o_orderdate", F.lit("1995-01-01")).cast("bigint").alias("e"))


@query("select p_partkey, cast(floor(p_retailprice) as bigint) a, length(cast(p_partkey as varchar)) - 1 b, p_partkey % 7 c, round(p_retailprice, 1) e, greatest(p_size, 10) f, lower(hex(p_partkey)) g from part")
def fn_math(spark, d):
    t = table(spark, d, "part", "p_partkey", "p_retailprice", "p_size")
    return t.select("p_partkey", F.floor("p_retailprice").alias("a"), (F.length(F.col("p_partkey").cast("string")) - 1).cast("bigint").alias("b"), F.pmod("p_partkey", F.lit(7)).alias("c"), F.round("p_retailprice", 1).alias("e"), F.greatest("p_size", F.lit(10)).alias("f"), F.lower(F.hex("p_partkey")).alias("g"))


@query(r"""with t as (select item_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') w from benchmark)
select item_id, len(w) a, array_to_string(w[2:4], ' ') b, array_to_string(list_reverse(w)[1:3], ' ') c, len(list_filter(w, lambda x: length(x) > 5)) e, len(list_distinct(w)) f, coalesce(list_position(w, 'the'), 0) g, list_contains(w, 'of') h from t""")
def fn_array(spark, d):
    w = F.col("w")
    t = table(spark, d, "benchmark").select("item_id", text.tokens(F.col("text")).alias("w"))
    return t.select("item_id", F.size(w).cast("bigint").alias("a"), F.array_join(F.slice(w, 2, 3), " ").alias("b"), F.array_join(F.slice(F.reverse(w), 1, 3), " ").alias("c"), F.size(F.filter(w, lambda x: F.length(x) > 5)).cast("bigint").alias("e"), F.size(F.array_distinct(w)).cast("bigint").alias("f"), F.array_position(w, "the").alias("g"), F.array_contains(w, "of").alias("h"))


@query(f"{DAILY} select gram, cast(sum(cf) as bigint) total, count(*) as days from s group by gram")
def fn_map(spark, d):
    """Daily counts as a map per gram, and back."""
    maps = daily(spark, d).groupBy("gram").agg(F.map_from_entries(F.collect_list(F.struct("d", "cf"))).alias("m"))
    doubled = F.map_zip_with("m", F.transform_values("m", lambda k, v: v), lambda k, a, b: a + b)
    return maps.select("gram", (F.aggregate(F.map_values(doubled), F.lit(0).cast("bigint"), lambda s, x: s + x) / 2).cast("bigint").alias("total"), F.size("m").cast("bigint").alias("days"))


@query("select event_id, cast(json_extract_string(props, '$.k') as bigint) k from events")
def fn_json(spark, d):
    return table(spark, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("select doc_id, md5(text) a, sha256(text) b from documents")
def fn_hash(spark, d):
    return table(spark, d, "documents", "doc_id", "text").select("doc_id", F.md5("text").alias("a"), F.sha2("text", 256).alias("b"))


BENCH = r"w as (select item_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') w from benchmark), b as (select item_id, w, unnest(range(1, len(w) + 1)) b from w)"


def bench_terms(spark, d) -> DataFrame:
    return table(spark, d, "benchmark").select("item_id", text.tokens(F.col("text")).alias("w")).where(F.size("w") > 0)


@query(f"with {BENCH}, s as (select item_id, w[b:b + 2] s from b), p as (select item_id, s, unnest(range(1, len(s) + 1)) n from s) select item_id, array_to_string(s[1:n], ' ') gram from p")
def fn_ngrams(spark, d):
    return bench_terms(spark, d).select("item_id", F.explode(grams.ngrams(F.col("w"), 3)).alias("g")).select("item_id", grams.gram(F.col("g")).alias("gram"))


@query(f"with {BENCH} select item_id, array_to_string(w[b:b + 3], ' ') suffix from b")
def fn_suffixes(spark, d):
    return bench_terms(spark, d).select("item_id", F.explode(grams.suffixes(F.col("w"), 4)).alias("s")).select("item_id", grams.gram(F.col("s")).alias("suffix"))


@query(f"with {BENCH}, s as (select item_id, w[b:b + 3] s from b), o as (select item_id, array_to_string(s, ' ') g, s, lead(s) over (partition by item_id order by array_to_string(s, ' ')) nx from s) select item_id, g gram, cast(case when nx is null then 0 else coalesce(list_position([s[i] is not distinct from nx[i] and s[i] is not null for i in [1, 2, 3, 4]] || [false], false) - 1, 0) end as bigint) lcp from o")
def fn_lcp(spark, d):
    """Common prefixes of neighbouring suffixes in order."""
    s = bench_terms(spark, d).select("item_id", F.explode(grams.suffixes(F.col("w"), 4)).alias("s")).withColumn("gram", grams.gram(F.col("s")))
    ahead = F.lead("s").over(Window.partitionBy("item_id").orderBy("gram"))
    return s.withColumn("nx", ahead).select("item_id", "gram", F.coalesce(grams.lcp(F.col("s"), F.col("nx")), F.lit(0)).cast("bigint").alias("lcp"))


@query(f"with {BENCH} select item_id, count_if(w[b:b] = ['the']) the, count_if(w[b:b + 1] = ['of', 'the']) of_the from b group by item_id")
def fn_occurs(spark, d):
    w = F.col("w")
    return bench_terms(spark, d).select("item_id", grams.occurs(F.array(F.lit("the")), w).cast("bigint").alias("the"), grams.occurs(F.array(F.lit("of"), F.lit("the")), w).cast("bigint").alias("of_the"))


@query("select event_id, cast(round(value * 2, 4) as double) doubled from events")
def udf_scalar(spark, d):
    """A vectorised scalar function."""

    @F.pandas_udf("double")
    def double(v: pd.Series) -> pd.Series:
        return (v * 2).round(4)

    return table(spark, d, "events", "event_id", "value").select("event_id", F.round(double("value"), 4).alias("doubled"))


@query("select event_type, max(value) - min(value) span from events group by event_type")
def udaf_series(spark, d):
    """A grouped-aggregate function over groups of one day, combined by built-in aggregates: no group is unbounded."""

    @F.pandas_udf("double")
    def highest(v: pd.Series) -> float:
        return float(v.max())

    days = table(spark, d, "events", "event_type", "ts", "value").groupBy("event_type", F.to_date("ts").alias("day")).agg(highest("value").alias("hi"))
    low = table(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.min("value").alias("lo"))
    return days.groupBy("event_type").agg(F.max("hi").alias("hi")).join(low, "event_type").select("event_type", (F.col("hi") - F.col("lo")).alias("span"))


@query(f"with {BENCH} select item_id, b - 1 as start, array_to_string(w[b:b + 2], ' ') suffix from b")
def udtf_suffix_rows(spark, d):
    """The table function in SQL."""
    grams.register(spark)
    bench_terms(spark, d).select("item_id", grams.gram(F.col("w")).alias("line")).createOrReplaceTempView("bench_lines")
    return spark.sql("select item_id, cast(start as bigint) start, suffix from bench_lines, lateral suffix_rows(line, 3)")


@query(r"select item_id, cast(list_sum(list_transform(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'), lambda x: length(x))) as bigint) letters from benchmark")
def arrow_lengths(spark, d):
    """Batches of Arrow columns in and out."""
    import pyarrow.compute as pc

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pc.utf8_length(batch.column(1)).cast(pa.int64())], ["item_id", "letters"])

    return bench_terms(spark, d).select("item_id", F.array_join("w", "").alias("t")).mapInArrow(run, "item_id long, letters long")


@query("select label, count(*) vectors, max(len(embedding)) dims, min(vec_id) first_id from embeddings group by label")
def nested_embeddings(spark, d):
    return table(spark, d, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("vectors"), F.max(F.size("embedding")).cast("bigint").alias("dims"), F.min("vec_id").alias("first_id"))


@query("""with o as (select o_custkey, o_orderpriority a, lead(o_orderpriority) over (partition by o_custkey order by o_orderdate, o_orderkey) b from orders)
select r_name region, a || ' > ' || b gram, count(*) cf from o join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey where b is not null group by 1, 2""")
def join_geo(spark, d):
    """Order-priority bigrams of customers by region."""
    order = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    pairs = table(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderdate", "o_orderpriority").withColumn("nx", F.lead("o_orderpriority").over(order)).where("nx is not null")
    places = table(spark, d, "nation", "n_nationkey", "n_regionkey").join(table(spark, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    customers = table(spark, d, "customer", "c_custkey", "c_nationkey").join(places, F.col("c_nationkey") == F.col("n_nationkey"))
    return pairs.join(customers, F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("r_name").alias("region"), F.concat_ws(" > ", "o_orderpriority", "nx").alias("gram")).agg(F.count(F.lit(1)).alias("cf"))


@query("select year(o_orderdate) as year, cast(sum(cast(o_totalprice as decimal(18, 2))) as decimal(28, 2)) total from orders group by 1")
def decimal_totals(spark, d):
    return table(spark, d, "orders", "o_orderdate", "o_totalprice").groupBy(F.year("o_orderdate").cast("bigint").alias("year")).agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("decimal(28,2)").alias("total"))
