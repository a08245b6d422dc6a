"""A cross-section of the registered queries against their SQL; bench and the driver run all of them."""

import pytest

import __spark_entry__ as entry

KEYS = [
    "direct_count_lm", "scan_bloom_lm", "index_sharded_lm", "suffix_lm_range", "suffix_lm_bins", "suffix_analytics", "maximal", "closed",
    "df_suffix", "ngram_positions", "series_year_text", "metadata_lang", "pages_lm", "events_ngrams", "orders_ngrams", "dictionary",
    "encoded_corpus", "corpus_profile_documents", "output_buckets", "records_index", "benchmark_overlap", "backoff_lm", "theta_subsumption",
    "interval_purchase", "asof_last_error", "cross_grid", "cube_lang_source", "pivot_period", "win_range_frame", "vocab_except_all", "fn_array", "fn_lcp",
    "udtf_suffix_rows", "prefix_maximal", "prefix_closed", "maximal_relational", "closed_relational", "closed_analytics", "condensed_sizes",
    "locate_gram", "memory_held", "stress_bytes", "vary_tau_40_index", "vary_tau_5_scan", "vary_sigma_50_index", "sample_50_scan", "sample_25_direct", "stream_tumbling", "stream_session", "stream_carry", "stream_dedupe", "stream_session_batch", "stream_merge",
]


@pytest.mark.parametrize("key", KEYS)
def test_against_sql(same, key):
    same(entry.queries()[key], entry.oracle_sql()[key])


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    found = entry.entry(spark)
    assert found.columns == ["gram", "n", "cf"] and found.count() > 0


def test_cross_grid_reads_lines(spark):
    plan = entry.queries()["cross_grid"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "l_quantity" in plan and "LocalRelation" not in plan
