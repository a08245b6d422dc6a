"""Queries of the counting methods, their variants, measures and workloads; with DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqstat.functions import text
from seqstat.operators import aggregate, condense, relational
from seqstat.operators.direct import direct_count, within_documents
from seqstat.operators.encode import Options, Prepared, build_dictionary, decode, prepare
from seqstat.operators.levelwise_index import levelwise_index, locate
from seqstat.operators.levelwise_scan import levelwise_scan
from seqstat.operators.suffix import suffix_prefix_hash, suffix_rollup, suffix_scan
from seqstat.plans import choose, measures, oracle
from seqstat.sources import tables
from seqstat.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]

#: The language-model and analytics settings on ``documents``: least frequency and greatest length.
LM, ANALYTICS = (10, 5), (10, 100)


def named(stats: DataFrame, p: Prepared, *others: str) -> DataFrame:
    """gram, n and further columns from ids."""
    counted = stats.withColumn("n", F.size("ids").cast("bigint"))
    return decode(counted.select("ids", "n", *[c for c in others or ("cf",) if c != "n"]), p.dictionary)


def over(make: Callable[[Prepared, int, int], DataFrame], tau: int, sigma: int, corpus: Callable = text.documents, opts: Options = Options(), *others: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = prepare(corpus(spark, sf_dir), tau, opts)
        return named(make(p, tau, sigma), p, *others)

    return query


QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(key: str, query: Query, sql: str | None = None) -> None:
    QUERIES[key] = query
    if sql:
        ORACLES[key] = sql


METHODS: dict[str, tuple[Callable, Options]] = {
    "direct_count_lm": (lambda p, t, s: direct_count(p, t, s), Options()),
    "direct_count_nocombine": (lambda p, t, s: direct_count(p, t, s, Options(local_combine=False)), Options()),
    "direct_count_nosplit": (lambda p, t, s: direct_count(p, t, s), Options(split_rare=False)),
    "scan_lm": (lambda p, t, s: levelwise_scan(p, t, s), Options()),
    "scan_broadcast_lm": (lambda p, t, s: levelwise_scan(p, t, s, "broadcast"), Options()),
    "scan_shuffle_lm": (lambda p, t, s: levelwise_scan(p, t, s, "shuffle"), Options()),
    "scan_merge_lm": (lambda p, t, s: levelwise_scan(p, t, s, "merge"), Options()),
    "scan_bloom_lm": (lambda p, t, s: levelwise_scan(p, t, s, "bloom"), Options()),
    "scan_carried_lm": (lambda p, t, s: levelwise_scan(p, t, s, carry_survivors=True), Options()),
    "scan_generated_lm": (lambda p, t, s: levelwise_scan(p, t, s, candidates="generated"), Options()),
    "index_lm_k4": (lambda p, t, s: levelwise_index(p, t, s, 4)[0], Options()),
    "index_lm_k3": (lambda p, t, s: levelwise_index(p, t, s, 3)[0], Options()),
    "index_lm_k2": (lambda p, t, s: levelwise_index(p, t, s, 2)[0], Options()),
    "index_lm_k5": (lambda p, t, s: levelwise_index(p, t, s, 5)[0], Options()),
    "index_sharded_lm": (lambda p, t, s: levelwise_index(p, t, s, 3, shards=4)[0], Options()),
    "index_positions_lm": (lambda p, t, s: levelwise_index(p, t, s, 4, positions_below_K=True)[0], Options()),
    "index_flat_lm": (lambda p, t, s: levelwise_index(p, t, s, 2, "flat")[0], Options()),
    "index_flat_k1_lm": (lambda p, t, s: levelwise_index(p, t, s, 1)[0], Options()),
    "suffix_lm_first_term": (lambda p, t, s: suffix_scan(p, t, s, Options(partitioner="first_term")), Options()),
    "suffix_lm_bins": (lambda p, t, s: suffix_scan(p, t, s, Options(partitioner="bins")), Options()),
    "suffix_lm_range": (lambda p, t, s: suffix_scan(p, t, s), Options()),
    "suffix_lm_combine": (lambda p, t, s: suffix_scan(p, t, s, Options(local_combine=True)), Options()),
    "suffix_lm_stack": (lambda p, t, s: suffix_scan(p, t, s, Options(kernel="stack")), Options()),
    "suffix_lm_nosplit": (lambda p, t, s: suffix_scan(p, t, s), Options(split_rare=False)),
    "suffix_lm_join_encoding": (lambda p, t, s: suffix_scan(p, t, s), Options(how="join")),
    "suffix_hash_lm": (suffix_prefix_hash, Options()),
    "suffix_rollup_lm": (suffix_rollup, Options()),
    "chosen_lm": (lambda p, t, s: choose.choose(p, t, s)[1], Options()),
    "condense_expand_closed_lm": (lambda p, t, s: condense.expand_closed(condense.closed(p, t, s)), Options()),
}
for key, (make, opts) in METHODS.items():
    add(key, over(make, *LM, text.documents, opts), oracle.stats(*LM))

for tau in (3, 5, 20, 40, 50, 100):
    add(f"vary_tau_{tau}", over(lambda p, t, s: suffix_scan(p, t, s), tau, 5), oracle.stats(tau, 5))
for sigma in (10, 50):
    add(f"vary_sigma_{sigma}", over(lambda p, t, s: suffix_scan(p, t, s), 10, sigma), oracle.stats(10, sigma))
add("suffix_analytics", over(lambda p, t, s: suffix_scan(p, t, s), *ANALYTICS), oracle.stats(*ANALYTICS))
add("scan_analytics", over(lambda p, t, s: levelwise_scan(p, t, s), *ANALYTICS), oracle.stats(*ANALYTICS))
add("index_analytics", over(lambda p, t, s: levelwise_index(p, t, s, 4)[0], *ANALYTICS), oracle.stats(*ANALYTICS))
add("direct_analytics", over(lambda p, t, s: direct_count(p, t, s), *ANALYTICS), oracle.stats(*ANALYTICS))
OTHERS = {"direct": direct_count, "scan": levelwise_scan, "index": lambda p, t, s: levelwise_index(p, t, s, 4)[0]}
for name, make in OTHERS.items():
    for tau in (5, 20, 40, 50, 100):
        add(f"vary_tau_{tau}_{name}", over(make, tau, 5), oracle.stats(tau, 5))
    for sigma in (10, 50):
        add(f"vary_sigma_{sigma}_{name}", over(make, 10, sigma), oracle.stats(10, sigma))
    add(f"pages_lm_{name}", over(make, 20, 5, text.pages), oracle.stats(20, 5, oracle.sequences(oracle.PAGES)))
    for percent in (25, 50, 75):
        part = lambda a, b, n=percent: text.from_text(tables.sample(tables.table(a, b, "documents"), n), "doc_id", F.col("text"))
        add(f"sample_{percent}_{name}", over(make, *LM, part), oracle.stats(*LM, oracle.sequences(oracle.sampled(percent))))
add("suffix_unbounded", over(lambda p, t, s: suffix_scan(p, t, None), 40, 0))

for mode in ("prefix_maximal", "prefix_closed"):
    add(mode, over(lambda p, t, s, m=mode: suffix_scan(p, t, s, keep=m), *LM), oracle.condensed(*LM, mode))
add("maximal", over(condense.maximal, *LM), oracle.condensed(*LM, "maximal"))
add("closed", over(condense.closed, *LM), oracle.condensed(*LM, "closed"))
for mode in ("maximal", "closed"):
    add(f"{mode}_relational", over(lambda p, t, s, m=mode: condense.condense_stats(suffix_scan(p, t, s), m), *LM), oracle.condensed(*LM, mode))
    add(f"{mode}_analytics", over(condense.maximal if mode == "maximal" else condense.closed, *ANALYTICS), oracle.condensed(*ANALYTICS, mode))
add("expand_closed", over(lambda p, t, s: condense.expand_closed(condense.closed(p, t, s)), *LM), oracle.stats(*LM))
add("expand_maximal", over(lambda p, t, s: condense.expand_maximal(condense.maximal(p, t, s)), *LM, text.documents, Options(), "n"), f"{oracle.stats_cte(*LM)} select gram, n from stats")

DF_SQL = f"{oracle.ctes(*LM)} select gram, n, count(distinct doc_id) df from grams group by gram, n having count(distinct doc_id) >= {LM[0]}"
for method in ("suffix", "direct", "index"):
    add(f"df_{method}", over(lambda p, t, s, m=method: aggregate.document_frequency(p, t, s, m), *LM, text.documents, Options(), "df"), DF_SQL)
add("ngram_tf_index", over(lambda p, t, s: aggregate.ngram_index(p, t, s), 40, 3, text.documents, Options(), "doc_id", "tf"), f"{oracle.stats_cte(40, 3)} select g.gram, g.n, doc_id, count(*) tf from grams g join stats s on g.gram = s.gram group by g.gram, g.n, doc_id")


def positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per occurrence: sentence and place of its first term."""
    p = prepare(text.documents(spark, sf_dir), 100, Options())
    found = named(aggregate.ngram_index(p, 100, 3, "positions"), p, "doc_id", "pos")
    return found.select("gram", "n", "doc_id", F.shiftright("pos", 32).alias("seq_no"), F.col("pos").bitwiseAND(text.STRIDE - 1).alias("at"))


add("ngram_positions", positions, f"{oracle.stats_cte(100, 3)} select g.gram, g.n, doc_id, seq_no, pos as at from grams g join stats s on g.gram = s.gram")


def located(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), 2, Options())
    return locate(p, 2, ["of", "the"]).select("doc_id", F.shiftright("pos", 32).alias("seq_no"), F.col("pos").bitwiseAND(text.STRIDE - 1).alias("at"))


add("locate_gram", located, f"with {oracle.sequences()}, p as (select doc_id, seq_no, w, unnest(range(1, len(w))) b from seqs) select doc_id, seq_no, b - 1 as at from p where w[b] = 'of' and w[b + 1] = 'the'")


# Series and metadata.
def year_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with a synthetic year, 1987 + doc_id mod 21: the table has no date."""
    return text.documents(spark, sf_dir, (1987 + F.pmod("doc_id", F.lit(21))).cast("bigint").alias("period"))


def by_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.documents(spark, sf_dir, F.col("lang"))


def by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.documents(spark, sf_dir, F.col("source"))


def event_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.event_days(spark, sf_dir).withColumn("period", F.datediff("day", F.lit("1970-01-01")).cast("bigint")).drop("day")


def series_sql(tau: int, sigma: int, seqs: str, extra: str) -> str:
    return f"{oracle.ctes(tau, sigma, seqs, extra)}, hot as (select gram from grams group by gram having count(*) >= {tau}) select gram, n, {extra}, count(*) cf from grams where gram in (select gram from hot) group by gram, n, {extra}"


YEARS = oracle.sequences("select doc_id, 1987 + doc_id % 21 period, text from documents", "period")
DAYS = oracle.EVENT_DAYS.replace("select user_id doc_id, cast(ts as date) as day,", "select user_id doc_id, cast(datediff('day', date '1970-01-01', cast(ts as date)) as bigint) period,")
LANGS, SOURCES = (oracle.sequences(f"select doc_id, {c}, text from documents", c) for c in ("lang", "source"))
for method in ("suffix", "direct"):
    tail = "" if method == "suffix" else "_direct"
    series = lambda p, t, s, m=method: aggregate.time_series(p, t, s, method=m)
    add(f"series_year_text{tail}", over(series, 20, 3, year_text, Options(), "period", "cf"), series_sql(20, 3, YEARS, "period"))
    add(f"series_day_events{tail}", over(series, 20, 3, event_days, Options(), "period", "cf"), series_sql(20, 3, DAYS, "period"))
    add(f"series_year_orders{tail}", over(series, 20, 3, text.customer_orders, Options(), "period", "cf"), series_sql(20, 3, oracle.ORDERS, "period"))
add("metadata_lang", over(lambda p, t, s: aggregate.metadata_stats(p, t, s, "lang"), 20, 3, by_language, Options(), "lang", "cf"), series_sql(20, 3, LANGS, "lang"))
add("metadata_source", over(lambda p, t, s: aggregate.metadata_stats(p, t, s, "source"), 40, 3, by_source, Options(), "source", "cf"), series_sql(40, 3, SOURCES, "source"))


def quotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Long n-grams over the (synthetic) years: first and last year, and in how many years they occur."""
    p = prepare(year_text(spark, sf_dir), 10, Options())
    series = aggregate.time_series(p, 10, 20).where(F.size("ids") >= 10)
    spread = series.groupBy("ids").agg(F.min("period").alias("first_year"), F.max("period").alias("last_year"), F.count(F.lit(1)).alias("years"), F.sum("cf").alias("cf"))
    return named(spread, p, "first_year", "last_year", "years", "cf")


add("quotations_spread", quotations, f"{oracle.ctes(10, 20, YEARS, 'period')} select gram, n, min(period) first_year, max(period) last_year, count(distinct period) as years, count(*) cf from grams where n >= 10 group by gram, n having count(*) >= 10")

# Other corpora.
add("pages_lm", over(lambda p, t, s: suffix_scan(p, t, s), 20, 5, text.pages), oracle.stats(20, 5, oracle.sequences(oracle.PAGES)))
add("pages_analytics", over(lambda p, t, s: suffix_scan(p, t, s), 20, 100, text.pages), oracle.stats(20, 100, oracle.sequences(oracle.PAGES)))
add("conversations_lm", over(lambda p, t, s: suffix_scan(p, t, s), 5, 5, text.conversations), oracle.stats(5, 5, oracle.sequences(oracle.CONVERSATIONS)))
add("benchmark_lm", over(lambda p, t, s: suffix_scan(p, t, s), 3, 5, text.benchmark), oracle.stats(3, 5, oracle.sequences(oracle.BENCHMARK)))
add("events_ngrams", over(lambda p, t, s: suffix_scan(p, t, s), 5, 5, lambda a, b: text.event_days(a, b).drop("day")), oracle.stats(5, 5, oracle.EVENT_DAYS))
add("events_user_ngrams", over(lambda p, t, s: suffix_scan(p, t, s), 5, 5, lambda a, b: text.event_days(a, b, False)), oracle.stats(5, 5, oracle.EVENT_USERS))
add("orders_ngrams", over(lambda p, t, s: suffix_scan(p, t, s), 5, 5, lambda a, b: text.customer_orders(a, b).drop("period")), oracle.stats(5, 5, oracle.ORDERS))
for percent in (25, 50, 75):
    part = lambda a, b, n=percent: text.from_text(tables.sample(tables.table(a, b, "documents"), n), "doc_id", F.col("text"))
    add(f"sample_{percent}", over(lambda p, t, s: suffix_scan(p, t, s), *LM, part), oracle.stats(*LM, oracle.sequences(oracle.sampled(percent))))


# Preparation and measures.
def dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_dictionary(text.documents(spark, sf_dir), 1).select("term", F.col("id").cast("bigint").alias("id"), "cf")


add("dictionary", dictionary, f"with {oracle.sequences()}, c as (select t term, count(*) cf from (select unnest(w) t from seqs) group by t) select term, row_number() over (order by cf desc, term) id, cf from c")


def rare_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), LM[0], Options())
    return p.runs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("runs"), F.sum(F.size("ids")).alias("terms"), F.max(F.size("ids")).cast("bigint").alias("longest"))


add("rare_split_runs", rare_runs, f"with {oracle.sequences()}, {oracle.runs(LM[0])} select doc_id, count(*) runs, cast(sum(len(w)) as bigint) terms, max(len(w)) longest from runs group by doc_id")


def encoded(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), LM[0], Options())
    return decode(p.runs.select("doc_id", "pos", "ids"), p.dictionary, "ids", "terms").select("doc_id", F.shiftright("pos", 32).alias("seq_no"), F.col("pos").bitwiseAND(text.STRIDE - 1).alias("at"), "terms")


add("encoded_corpus", encoded, f"with {oracle.sequences()}, {oracle.runs(LM[0])} select doc_id, seq_no, start as at, array_to_string(w, ' ') terms from runs")

for name, corpus, seqs in (("documents", text.documents, oracle.sequences()), ("pages", text.pages, oracle.sequences(oracle.PAGES)), ("benchmark", text.benchmark, oracle.sequences(oracle.BENCHMARK)), ("events", lambda a, b: text.event_days(a, b).drop("day"), oracle.EVENT_DAYS)):
    sql = f"with {seqs} select count(distinct doc_id) documents, cast(sum(len(w)) as bigint) occurrences, (select count(distinct t) from (select unnest(w) t from seqs)) distinct_terms, count(*) sequences, round(avg(len(w)), 4) mean_len, round(stddev_pop(len(w)), 4) sd_len from seqs"
    add(f"corpus_profile_{name}", lambda a, b, c=corpus: measures.corpus_profile(c(a, b)), sql)


def buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), 5, Options())
    return measures.output_buckets(suffix_scan(p, 5, 100).select(F.size("ids").alias("n"), "cf"))


add("output_buckets", buckets, f"{oracle.stats_cte(5, 100)} select length(cast(n as varchar)) - 1 len_bucket, length(cast(cf as varchar)) - 1 cf_bucket, count(*) grams from stats group by 1, 2")


def buckets_unbounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), 40, Options())
    return measures.output_buckets(suffix_scan(p, 40, None).select(F.size("ids").alias("n"), "cf"))


add("output_buckets_unbounded", buckets_unbounded)


def record_counts(method: str, tau: int = 10, sigma: int = 5, K: int = 4) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = prepare(text.documents(spark, sf_dir), tau, Options())
        if method == "direct":
            found = measures.expected_direct(p, sigma)
        elif method == "suffix":
            found = measures.expected_suffix(p, tau)
        elif method == "index":
            found = measures.expected_index(suffix_scan(p, tau, sigma), within_documents(p.runs, K), K, sigma)
        else:
            found = measures.expected_scan(tables.stage(direct_count(p, 1, sigma), "counts"), tau)
        return found.select(F.lit(method).alias("method"), "records")

    return query


def one_record(method: str, value: str) -> str:
    return f"{oracle.stats_cte(*LM)} select '{method}' as method, cast({value} as bigint) records"


add("records_direct", record_counts("direct"), one_record("direct", "(select count(*) from grams)"))
add("records_suffix", record_counts("suffix"), one_record("suffix", "(select count(*) from grams where n = 1)"))
add("records_index", record_counts("index"), one_record("index", "(select count(*) from (select distinct gram, doc_id from grams where n <= 4)) + 2 * (select count(*) from stats where n >= 4 and n < 5)"))
add("records_scan", record_counts("scan"), f"{oracle.stats_cte(*LM)}, whole as (select gram, n, count(*) cf from grams group by gram, n) select 'scan' as method, cast(sum(cf) as bigint) records from whole where n = 1 or (array_to_string(string_split(gram, ' ')[1:n - 1], ' ') in (select gram from stats) and array_to_string(string_split(gram, ' ')[2:n], ' ') in (select gram from stats))")


def measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records and bytes that each method really sends, round by round."""
    p = prepare(text.documents(spark, sf_dir), LM[0], Options())
    rows = [(m, k, n, b) for m in ("direct", "scan", "index", "suffix") for k, n, b in measures.records(p, m, *LM)]
    return spark.createDataFrame(rows, "method string, round int, records long, bytes long")


add("records_measured", measured)


def held(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = prepare(text.documents(spark, sf_dir), LM[0], Options())
    return measures.entries_held(tables.stage(direct_count(p, 1, LM[1]), "counts"), *LM)


HELD = {
    "scan": f"(select max(x) from (select count(*) x from whole where cf >= {LM[0]} and n < {LM[1]} group by n))",
    "index": "(select max(cf) from whole where n <= 4)",
    "suffix_hash": "(select max(x) from (select count(*) x from whole group by string_split(gram, ' ')[1]))",
    "suffix": "(select max(n) from whole)",
}
add("memory_held", held, f"{oracle.ctes(*LM)}, whole as materialized (select gram, n, count(*) cf from grams group by gram, n) " + " union all ".join(f"select '{m}' as method, cast({x} as bigint) held" for m, x in HELD.items()))

#: Lengths to which documents are cut to show how bytes grow.
STRESS = (25, 50, 100, 200)


def stress(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole of each document is one sequence here."""
    texts = tables.table(spark, sf_dir, "documents", "text").select(text.tokens(F.col("text")).alias("terms"))
    return measures.growth(measures.byte_orders(texts, STRESS))


SIZED = f"select unnest([{', '.join(map(str, STRESS))}]) terms"
add(
    "stress_bytes",
    stress,
    f"""with w as (select regexp_extract_all(lower(text), '{oracle.TOKEN}') w from documents), c as (select t term, count(*) cf from (select unnest(w) t from w) group by t),
    d as (select term, row_number() over (order by cf desc, term) id from c), l as ({SIZED}),
    p as (select unnest(w[1:{max(STRESS)}]) term, unnest(range(1, {max(STRESS)} + 1)) i from w where len(w) >= {max(STRESS)}),
    s as (select terms, i, case when id < 128 then 1 when id < 16384 then 2 when id < 2097152 then 3 when id < 268435456 then 4 else 5 end b from p join d using (term) join l on i <= terms),
    o as (select cast(terms as bigint) terms, 'direct' as method, cast(sum(terms - i + 1) as bigint) records, cast(sum(b * i * (terms - i + 1)) as bigint) bytes from s group by terms
    union all select terms, 'suffix', count(*), cast(sum(b * i) as bigint) from s group by terms),
    g as (select *, lag(records) over w r0, lag(bytes) over w b0, lag(terms) over w t0 from o window w as (partition by method order by terms))
    select terms, method, records, bytes, round(ln(records / r0) / ln(terms / t0), 2) records_power, round(ln(bytes / b0) / ln(terms / t0), 2) bytes_power from g""",
)


# Consumers.
def backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative frequency of the last term given those before it."""
    p = prepare(text.documents(spark, sf_dir), LM[0], Options())
    stats = tables.stage(suffix_scan(p, LM[0], 3), "stats")
    head = stats.select(F.col("ids").alias("head"), F.col("cf").alias("head_cf"))
    longer = stats.where(F.size("ids") > 1).join(head, F.slice("ids", F.lit(1), F.size("ids") - 1) == F.col("head"))
    return named(longer.select("ids", "cf", F.round(F.col("cf") / F.col("head_cf"), 6).alias("p")), p, "cf", "p")


add("backoff_lm", backoff, f"{oracle.stats_cte(LM[0], 3)} select s.gram, s.n, s.cf, round(s.cf / h.cf, 6) p from stats s join stats h on h.gram = array_to_string(string_split(s.gram, ' ')[1:s.n - 1], ' ') where s.n > 1")


def overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n-grams of 8 terms that ``benchmark`` and ``documents`` share, with their counts in either."""
    mark = lambda df, name: df.withColumn("side", F.lit(name))
    both = mark(text.documents(spark, sf_dir), "documents").unionByName(mark(text.benchmark(spark, sf_dir), "benchmark"))
    p = prepare(both, 2, Options())
    parts = aggregate.metadata_stats(p, 2, 8, "side").where(F.size("ids") == 8)
    sides = parts.groupBy("ids").agg(F.sum(F.when(F.col("side") == "documents", F.col("cf")).otherwise(0)).alias("cf_documents"), F.sum(F.when(F.col("side") == "benchmark", F.col("cf")).otherwise(0)).alias("cf_benchmark"))
    return named(sides.where("cf_documents > 0 and cf_benchmark > 0"), p, "cf_documents", "cf_benchmark")


SIDES = oracle.sequences("select doc_id, 'documents' side, text from documents union all select item_id, 'benchmark', text from benchmark", "side")
add("benchmark_overlap", overlap, f"with {SIDES}, b as (select side, w, unnest(range(1, len(w) - 6)) i from seqs where len(w) >= 8) select array_to_string(w[i:i + 7], ' ') gram, cast(8 as bigint) n, count_if(side = 'documents') cf_documents, count_if(side = 'benchmark') cf_benchmark from b group by 1 having count_if(side = 'documents') > 0 and count_if(side = 'benchmark') > 0")


def condensed_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many n-grams are frequent, closed and maximal, by setting. Both settings have one tau, so the longer one's n-grams, counted once,
    hold those of the shorter one."""
    tau, longest = ANALYTICS
    whole = tables.stage(suffix_scan(prepare(text.documents(spark, sf_dir), tau, Options()), tau, longest), "stats")
    rows = []
    for name, sigma in (("language_model", LM[1]), ("analytics", longest)):
        stats = whole.where(F.size("ids") <= sigma)
        rows.append((name, stats.count(), condense.condense_stats(stats, "closed").count(), condense.condense_stats(stats, "maximal").count()))
    return spark.createDataFrame(rows, "setting string, frequent long, closed long, maximal long")


def sizes_sql(name: str, tau: int, sigma: int) -> str:
    count = lambda sql: f"(select count(*) from ({sql}))"
    return f"select '{name}' as setting, {count(oracle.stats(tau, sigma))} frequent, {count(oracle.condensed(tau, sigma, 'closed'))} closed, {count(oracle.condensed(tau, sigma, 'maximal'))} maximal"


add("condensed_sizes", condensed_sizes, f"{sizes_sql('language_model', *LM)} union all {sizes_sql('analytics', *ANALYTICS)}")


def prefix_push(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grams that begin with 'of', by a filter on the suffix rows."""
    p = prepare(text.documents(spark, sf_dir), 20, Options())
    found = p.dictionary.where(F.col("term") == "of").select("id").collect()
    return named(choose.with_prefix(p, [r["id"] for r in found] or [0], 20, 4), p)


add("prefix_pushdown", prefix_push, f"{oracle.stats_cte(20, 4)} select gram, n, cf from stats where gram = 'of' or gram like 'of %'")


def queries() -> dict[str, Query]:
    return QUERIES | relational.QUERIES | stream.queries()


def oracle_sql() -> dict[str, str]:
    return ORACLES | relational.ORACLES | stream.oracle_sql()
