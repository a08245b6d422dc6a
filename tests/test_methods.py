"""All methods on the running example, random corpora, edges and plans."""

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from seqstat.functions import text
from seqstat.operators import aggregate, condense
from seqstat.operators.direct import direct_count
from seqstat.operators.encode import Options, build_dictionary, decode, encode, prepare, sort_key, term_counts, varbyte_size
from seqstat.operators.levelwise_index import levelwise_index, locate
from seqstat.operators.levelwise_scan import levelwise_scan
from seqstat.operators.direct import suffix_rows
from seqstat.operators.suffix import place, suffix_prefix_hash, suffix_rollup, suffix_scan
from seqstat.plans import choose, measures

EXAMPLE = ("a x b x x", "b a x b x", "x b a x b")
ALL = {"a": 3, "b": 5, "x": 7, "a x": 3, "x b": 4, "a x b": 3}

METHODS = {
    "direct": direct_count,
    "direct raw": lambda p, t, s: direct_count(p, t, s, Options(local_combine=False)),
    "scan": lambda p, t, s: levelwise_scan(p, t, s, "broadcast"),
    "scan shuffled": lambda p, t, s: levelwise_scan(p, t, s, "shuffle"),
    "scan bloom": lambda p, t, s: levelwise_scan(p, t, s, "bloom"),
    "scan carried": lambda p, t, s: levelwise_scan(p, t, s, carry_survivors=True),
    "scan generated": lambda p, t, s: levelwise_scan(p, t, s, candidates="generated"),
    "index K=1": lambda p, t, s: levelwise_index(p, t, s, 1)[0],
    "index K=2": lambda p, t, s: levelwise_index(p, t, s, 2)[0],
    "index flat": lambda p, t, s: levelwise_index(p, t, s, 2, "flat")[0],
    "index sharded": lambda p, t, s: levelwise_index(p, t, s, 2, shards=3)[0],
    "suffix first": lambda p, t, s: suffix_scan(p, t, s, Options(partitioner="first_term")),
    "suffix bins": lambda p, t, s: suffix_scan(p, t, s, Options(partitioner="bins", partitions=3)),
    "suffix range": lambda p, t, s: suffix_scan(p, t, s, Options(partitions=3)),
    "suffix stack": lambda p, t, s: suffix_scan(p, t, s, Options(kernel="stack")),
    "suffix hash": suffix_prefix_hash,
    "suffix rollup": suffix_rollup,
    "suffix unbounded": lambda p, t, s: suffix_scan(p, t, None),
}


def grams(found, p, value="cf"):
    return {r["gram"]: r[value] for r in decode(found, p.dictionary).collect()}


@pytest.fixture(scope="module")
def example(spark):
    return prepare(text.literal(spark, *EXAMPLE), 3)


@pytest.mark.parametrize("method", METHODS)
def test_running_example(example, method):
    assert grams(METHODS[method](example, 3, 3), example) == ALL


def test_split_rare_off(spark):
    p = prepare(text.literal(spark, *EXAMPLE), 3, Options(split_rare=False))
    assert grams(suffix_scan(p, 3, 3), p) == ALL


def test_condensed(example):
    maximal, closed = condense.maximal(example, 3, 3), condense.closed(example, 3, 3)
    assert grams(maximal, example) == {"a x b": 3}
    assert grams(closed, example) == {"a x b": 3, "x b": 4, "b": 5, "x": 7}
    assert grams(suffix_scan(example, 3, 3, keep="prefix_maximal"), example).keys() == {"a x b", "x b", "b"}
    assert grams(suffix_scan(example, 3, 3, keep="prefix_closed"), example).keys() == {"a x b", "x b", "b", "x"}
    assert grams(condense.expand_closed(closed), example) == ALL
    assert {r["gram"] for r in decode(condense.expand_maximal(maximal), example.dictionary).collect()} == ALL.keys()
    stats = suffix_scan(example, 3, 3)
    assert grams(condense.condense_stats(stats, "maximal"), example) == {"a x b": 3}


@pytest.mark.parametrize("method", ["suffix", "direct", "index"])
def test_document_frequency(example, method):
    assert set(grams(aggregate.document_frequency(example, 3, 3, method), example, "df").values()) == {3}


def test_records(spark):
    p = prepare(text.literal(spark, *EXAMPLE), 3)
    count = lambda m, **k: [n for _, n, _ in measures.records(p, m, 3, 3, **k)]
    assert count("direct") == [36] and count("suffix") == [15] and count("scan") == [15, 12, 3]
    assert count("index", K=2) == [20, 4] and count("index", K=1) == [9, 6, 4]
    assert measures.expected_direct(p, 3).first()[0] == 36 and measures.expected_suffix(p, 3).first()[0] == 15
    assert measures.expected_scan(direct_count(p, 1, 3), 3).first()[0] == 30


def test_rare_terms_split(spark):
    p = prepare(text.literal(spark, "c b a z b a c", "c b a c b a"), 2)
    runs = {(r["doc_id"], r["pos"], len(r["ids"])) for r in p.runs.collect()}
    assert runs == {(1, 0, 3), (1, 4, 3), (2, 0, 6)}


def test_whole_suffix_placement_undercounts(spark):
    p = prepare(text.literal(spark, *EXAMPLE), 3)
    torn = [grams(suffix_scan(p, 3, 3, Options(partitioner="whole", partitions=n)), p) for n in (2, 3, 5)]
    assert any(t != ALL for t in torn)


def test_overlaps_and_edges(spark):
    p = prepare(text.literal(spark, "x x x"), 1)
    assert grams(suffix_scan(p, 1, 3), p) == {"x": 3, "x x": 2, "x x x": 1} == grams(direct_count(p, 1, 3), p)
    for texts in (("",), ("a",), ("é ß é",)):
        p = prepare(text.literal(spark, *texts), 2)
        assert grams(suffix_scan(p, 2, 4), p) == ({"é": 2} if "é" in texts[0] else {})
        assert grams(levelwise_scan(p, 2, 4), p) == grams(levelwise_index(p, 2, 4)[0], p) == grams(direct_count(p, 2, 4), p)


def test_null_and_blank_text(spark):
    df = spark.createDataFrame([(1, None), (2, ""), (3, " . "), (4, "A b. a B")], "doc_id long, text string")
    rows = text.from_text(df, "doc_id", df["text"]).collect()
    assert [(r["doc_id"], r["terms"]) for r in rows] == [(4, ["a", "b"]), (4, ["a", "b"])]


def test_random_equality_and_series(spark):
    rng = random.Random(3)
    for case in range(3):
        docs = [" ".join(rng.choice("abc") for _ in range(rng.randint(0, 12))) for _ in range(6)]
        tau, sigma = rng.randint(1, 3), rng.randint(2, 6)
        p = prepare(text.literal(spark, *docs), tau)
        want = Counter(" ".join(d.split()[i : i + n]) for d in docs for i in range(len(d.split())) for n in range(1, min(sigma, len(d.split()) - i) + 1))
        want = {g: c for g, c in want.items() if c >= tau}
        for method in ("direct", "scan carried", "index K=2", "suffix range", "suffix bins"):
            assert grams(METHODS[method](p, tau, sigma), p) == want, method
        closed = condense.closed(p, tau, sigma)
        assert grams(condense.expand_closed(closed), p) == want
        assert grams(condense.condense_stats(suffix_scan(p, tau, sigma), "closed"), p) == grams(closed, p)


def test_unbounded_lengths(spark):
    line = " ".join(f"w{i}" for i in range(60))
    p = prepare(text.literal(spark, line, "q " + line, line + " z"), 3)
    found = grams(suffix_scan(p, 3, None), p)
    assert len(found) == 60 * 61 // 2 and found[line] == 3


def test_dictionary_ids(spark):
    rows = build_dictionary(text.literal(spark, "b b a a c", "d"), 1).orderBy("id").collect()
    assert [(r["term"], r["id"], r["cf"]) for r in rows] == [("a", 1, 2), ("b", 2, 2), ("c", 3, 1), ("d", 4, 1)]


def test_sort_key_and_varbyte(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([([1, 300],), ([1],), ([2],)], "ids array<int>")
    keys = [bytes(r["k"]) for r in df.select("ids", sort_key(F.col("ids")).alias("k")).orderBy("ids").collect()]
    assert keys == sorted(keys)
    assert df.select(varbyte_size(F.col("ids")).alias("n")).first()["n"] == 3


def test_guard_and_choice(spark):
    p = prepare(text.literal(spark, *[" ".join(["a", "b"] * 200)] * 2), 2)
    with pytest.raises(choose.TooManyRows):
        choose.guard(p, 2, 200)
    assert choose.choose(p, 2, 5)[0] == "suffix" and choose.choose(p, 2, 2)[0] == "direct"
    assert choose.limits(5, 10, max_n=3, min_cf=7) == (7, 3)


def test_plans(spark, capsys):
    p = prepare(text.literal(spark, *EXAMPLE), 3)
    suffix_scan(p, 3, 3, Options(partitioner="first_term")).explain()
    plan = capsys.readouterr().out
    assert plan.count("Exchange") == 1 and "MapInArrow" in plan
    rows = suffix_rows(p.runs, 3).select("ids", F.array(F.lit(1).cast("bigint")).alias("w"))
    place(rows, p, Options())[0].explain()
    plan = capsys.readouterr().out
    assert plan.count("Exchange") == 1 and "rangepartitioning" in plan and "Aggregate" not in plan


@pytest.mark.parametrize("keep", ["prefix_maximal", "prefix_closed"])
def test_condensing_under_range_placement(spark, keep):
    """Open grams get their best extension from all partitions."""
    rng = random.Random(5)
    for case in range(4):
        docs = [" ".join(rng.choice("ab") for _ in range(rng.randint(4, 14))) for _ in range(6)]
        tau, sigma = rng.randint(1, 3), rng.randint(2, 5)
        p = prepare(text.literal(spark, *docs), tau)
        want = grams(suffix_scan(p, tau, sigma, Options(partitioner="first_term"), keep), p)
        for n in (2, 5, 9):
            assert grams(suffix_scan(p, tau, sigma, Options(partitions=n), keep), p) == want
    with pytest.raises(ValueError):
        suffix_scan(p, tau, sigma, Options(partitioner="bins"), keep)


def test_locate_joins_postings(spark):
    p = prepare(text.literal(spark, "a b c d e", "x a b c d e", "a b c d"), 1)
    found = locate(p, 1, "a b c d e".split(), K=2)
    assert {(r["doc_id"], r["pos"] & (text.STRIDE - 1)) for r in found.collect()} == {(1, 0), (2, 1)}
    assert locate(p, 3, "a b c d e".split(), K=2).collect() == []


def test_decoding_by_join_keeps_rows_together(spark):
    """Rows that come in another order each time they are computed (as after an exchange) keep their own terms."""
    import numpy as np
    import pyarrow as pa

    def shuffled(batches):
        for batch in batches:
            yield batch.take(pa.array(np.random.default_rng().permutation(batch.num_rows)))

    words = spark.range(1, 501).select(F.concat(F.lit("t"), F.col("id")).alias("term"), F.col("id").cast("int").alias("id"))
    rows = spark.range(1, 501).select(F.array(F.col("id").cast("int"), (501 - F.col("id")).cast("int")).alias("ids"), F.col("id").alias("cf"))
    rows = rows.unionByName(spark.createDataFrame([([], 0)], "ids array<int>, cf long"))
    want = {(f"t{i} t{501 - i}", i) for i in range(1, 501)} | {("", 0)}
    for limit in (0, 1000):  # by a join, by lookup
        found = decode(rows.mapInArrow(shuffled, "ids array<int>, cf long"), words, broadcast_terms=limit)
        assert sorted(tuple(r) for r in found.collect()) == sorted(want)


def test_posting_lists_meet_by_position(spark, monkeypatch, capsys):
    """A common overlap doesn't pair every list with every other one: entries are joined by document and position."""
    from seqstat.operators import levelwise_index as lists

    p = prepare(text.literal(spark, *[f"a{i} x b{i}" for i in range(40)]), 1)
    level = lists.postings(lists.windows(p.runs, 2, "doc_id"), 1)
    joined = []
    monkeypatch.setattr(lists, "stage", lambda df, name: joined.append(df) or df)
    assert lists.extend_nested(level, 3, 1).count() == 40
    joined[0].explain("simple")
    joins = [x for x in capsys.readouterr().out.splitlines() if "Join [doc_id" in x]
    assert len(joins) == 1 and "pos#" in joins[0]
    monkeypatch.undo()
    assert grams(levelwise_index(p, 1, 3, 2, shards=2)[0], p) == grams(direct_count(p, 1, 3), p)


def test_direct_counting_in_turns(spark, monkeypatch, capsys):
    from seqstat.operators import direct

    p = prepare(text.literal(spark, *EXAMPLE), 3)
    written, stage = [], direct.stage
    monkeypatch.setattr(direct, "stage", lambda df, name, keep: written.append(name) or stage(df, name, keep))
    assert grams(direct_count(p, 3, 3, turn_bytes=100), p) == ALL and len(written) > 3
    direct_count(p, 3, 3).explain()
    assert "partial_count" in capsys.readouterr().out


def test_documents_combine_before_any_exchange_of_grams(spark, capsys):
    from seqstat.operators.direct import within_documents

    p = prepare(text.literal(spark, *EXAMPLE), 3)
    rows = within_documents(p.runs, 3)
    assert rows.count() == 29
    rows.explain()
    plan = capsys.readouterr().out
    assert plan.count("Exchange") == 1 and "hashpartitioning(doc_id" in plan


def test_condensed_sizes_count_once(spark, monkeypatch):
    from conftest import SF

    from seqstat import queries

    calls, scan = [], queries.suffix_scan
    monkeypatch.setattr(queries, "suffix_scan", lambda *a, **k: calls.append(a) or scan(*a, **k))
    assert queries.condensed_sizes(spark, SF).count() == 2 and len(calls) == 1


def test_index_frequencies_in_turns(spark, monkeypatch, capsys):
    """Lists take a row for each n-gram and document, dealt by document first; the result is the same in many turns."""
    from functools import partial

    p = prepare(text.literal(spark, *EXAMPLE), 3)
    want = grams(aggregate.document_frequency(p, 2, 3, "direct"), p, "df")
    aggregate.document_frequency(p, 2, 3, "index").explain()
    assert "hashpartitioning(doc_id" in capsys.readouterr().out
    monkeypatch.setattr(aggregate, "in_turns", partial(aggregate.in_turns, turn_bytes=500))
    assert grams(aggregate.document_frequency(p, 2, 3, "index"), p, "df") == want


def test_stress_bytes_are_those_of_the_rows(spark):
    """Reckoned from places and ids, as many records and bytes as the rows of either method have; from the given table."""
    import __spark_entry__ as entry
    from seqstat.functions import text
    from seqstat.operators.direct import gram_rows, suffix_rows
    from seqstat.operators.encode import prepare
    from seqstat.plans import measures
    from seqstat.sources import tables

    sf = "/root/testdata/sf0.001"
    docs = tables.table(spark, sf, "documents", "doc_id", "text").select("doc_id", text.tokens(F.col("text")).alias("terms"))
    found = {(r["terms"], r["method"]): (r["records"], r["bytes"]) for r in measures.byte_orders(docs.select("terms"), (5, 10, 40)).collect()}
    p = prepare(text.from_sequences(docs.withColumn("seq_no", F.lit(0))), 1)
    long = p.runs.where(F.size("ids") >= 40)
    assert long.count() > 50
    for n in (5, 10, 40):
        cut = long.withColumn("ids", F.slice("ids", 1, n))
        assert found[n, "direct"] == measures.logical(gram_rows(cut, n)) and found[n, "suffix"] == measures.logical(suffix_rows(cut, n))
    plan = entry.queries()["stress_bytes"](spark, sf)._jdf.queryExecution().toString()
    assert "documents.parquet" in plan


def test_posting_lists_over_batches(spark):
    """A list that goes on over many batches stays one; lists are sorted by document and position; the last level is only counted."""
    from seqstat.operators import levelwise_index as lists

    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    try:
        p = prepare(text.literal(spark, *["a b " * 5 + f"c{i} d a b" for i in range(4)]), 1)
        found = {tuple(r["ids"]): r for r in lists.postings(lists.windows(p.runs, 2, "doc_id"), 2).collect()}
        name = {r["id"]: r["term"] for r in p.dictionary.collect()}
        found = {" ".join(name[i] for i in k): r for k, r in found.items()}
        assert set(found) == {"a b", "b a", "d a"} and found["a b"]["cf"] == 24
        at = [(e["doc_id"], [x & (text.STRIDE - 1) for x in e["positions"]]) for e in found["a b"]["plist"]]
        assert at == [(d, [0, 2, 4, 6, 8, 12]) for d in (1, 2, 3, 4)]
        joined = []
        stats, last = levelwise_index(p, 2, 4, 2, shards=3, seen=lambda k, level: joined.append(k))
        assert joined == [2, 3] and grams(stats, p) == grams(direct_count(p, 2, 4), p)
        assert {tuple(r["ids"]) for r in last.collect()} == {tuple(r["ids"]) for r in stats.where("size(ids) = 4").collect()}
        empty = p.runs.limit(0)
        assert lists.postings(lists.windows(empty, 2, "doc_id"), 1).count() == 0
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_generated_candidates_in_turns(spark, monkeypatch):
    """Candidates beyond the bytes of a turn are dealt over turns by the gram that begins them; none is lost."""
    from seqstat.operators import levelwise_scan as scan

    p = prepare(text.literal(spark, *EXAMPLE, "a b x a b", "b b a x x"), 2)
    want, turns = grams(direct_count(p, 2, 4), p), []
    level = scan.stage(direct_count(p, 2, 2).where("size(ids) = 2"), "level")
    assert scan.generated_number(level, 3) == scan.generated(level, 3).count() > 4
    keep = scan.stage
    monkeypatch.setattr(scan, "stage", lambda df, name, **kw: turns.append(name) or keep(df, name, **kw))
    monkeypatch.setattr(scan.counted_generated, "__defaults__", (100,))
    assert grams(levelwise_scan(p, 2, 4, candidates="generated"), p) == want
    assert turns.count("turn") > 4


def test_long_lists_leap(spark):
    """Lists of four terms or more give all lengths up to twice their own in one round; null ids and batch borders break no gram."""
    rng = random.Random(5)
    piece = [f"w{rng.randrange(6)}" for _ in range(37)]
    texts = [" ".join(piece[rng.randrange(6) :] + [f"u{i}"] + piece[: rng.randrange(20, 37)]) for i in range(9)]
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        p = prepare(text.literal(spark, *texts).withColumn("doc_id", F.when(F.col("doc_id") != 4, F.col("doc_id"))), 3)
        for sigma, levels in ((30, [4, 8, 16]), (13, [4, 8]), (None, [4, 8, 16, 32])):
            joined = []
            stats, last = levelwise_index(p, 3, sigma, 4, shards=2, seen=lambda k, level: joined.append(k))
            assert joined == levels and grams(stats, p) == grams(direct_count(p, 3, sigma or 80), p)
        assert last.count() == 0
        last = levelwise_index(p, 3, 13, 4)[1]
        assert {tuple(r["ids"]): r["cf"] for r in last.collect()} == {tuple(r["ids"]): r["cf"] for r in direct_count(p, 3, 13).where("size(ids) = 13").collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_joined_encoding_keeps_sequences_apart(spark):
    """Sequences of two sides that agree in document and position are encoded each for itself, by a join as by lookup."""
    side = lambda name, *texts: text.literal(spark, *texts).withColumn("side", F.lit(name))
    both = side("x", "a b r1 c a", "b c").unionByName(side("y", "c r2 b a a b", "c c r3 a"))
    known = build_dictionary(both, 2)
    found = [Counter((r["doc_id"], r["seq_no"], r["pos"], r["side"], tuple(r["ids"])) for r in encode(both, known, how).collect()) for how in ("arrow", "join")]
    assert found[0] == found[1] and sum(found[0].values()) == 7


def test_bloom_scan_in_turns(spark, monkeypatch):
    """Windows of the filtered scan are dealt over turns by their first term: each turn is written by itself and nothing is lost."""
    from seqstat.operators import levelwise_scan as scan

    p = prepare(text.literal(spark, *["a b c d a b c", "b c d a b", "c d a b c d", "d a b"] * 2), 2)
    written = []
    monkeypatch.setattr(scan, "stage", lambda df, name, keep=False, real=scan.stage: written.append(name) or real(df, name, keep))
    level = scan.counted_bloom(p, scan.level_one(p, 2), 2, 2, turn_bytes=500)
    assert written.count("turn") > 1
    level = scan.counted_bloom(p, level, 3, 2, turn_bytes=500)
    assert grams(level, p) == grams(direct_count(p, 2, 3).where("size(ids) = 3"), p)


def test_bloom_probe_queues_no_rows(spark):
    """A Python column function would keep whole rows in a queue on disk; the filter is asked in a pass over batches."""
    from seqstat.operators import levelwise_scan as scan

    p = prepare(text.literal(spark, "a b c", "a b c"), 2)
    plan = scan.prune(scan.windows(p.runs, 3), scan.levelwise_scan(p, 2, 2), 3, "bloom")._jdf.queryExecution().toString()
    assert "ArrowEvalPython" not in plan and "MapInArrow" in plan


def test_decoding_by_join_numbers_rows_once(spark):
    """Numbers of rows are written before use: whatever is computed again reads them and doesn't number the rows in another order."""
    computed = spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            computed.add(batch.num_rows)
            yield batch

    words = spark.range(1, 101).select(F.concat(F.lit("t"), F.col("id")).alias("term"), F.col("id").cast("int").alias("id"))
    rows = spark.range(1, 101).select(F.array(F.col("id").cast("int")).alias("ids"), F.col("id").alias("cf"))
    found = decode(rows.mapInArrow(counted, "ids array<int>, cf long"), words, broadcast_terms=0)
    for _ in range(2):
        assert sorted(tuple(r) for r in found.collect()) == sorted((f"t{i}", i) for i in range(1, 101))
    assert computed.value == 100


def test_tokens_are_found_once(spark):
    """Sentences without a token are dropped without finding all tokens of the others twice."""
    rows = spark.createDataFrame([(1, "A b. -- ! c\n\n"), (2, " .,;"), (3, None), (4, "")], "id long, text string")
    corpus = text.from_text(rows, "id", F.col("text"))
    assert [(r["doc_id"], r["seq_no"], r["pos"], r["terms"]) for r in corpus.orderBy("pos").collect()] == [(1, 0, 0, ["a", "b"]), (1, 2, 2 * text.STRIDE, ["c"])]
    counts = term_counts(corpus)
    assert {r["term"]: r["cf"] for r in counts.collect()} == {"a": 1, "b": 1, "c": 1}
    assert counts._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[-1].count("regexp_extract_all") == 1


@pytest.mark.parametrize("K", [2, 3, 4])
def test_index_counts_short_grams_by_columns(spark, K):
    """Below K terms a column for each term is the key, as arrays miss the hash tables for keys of fixed width."""
    p = prepare(text.literal(spark, *["a b c d a b c", "b c d a b"] * 2), 2)
    stats = levelwise_index(p, 2, 5, K)[0]
    assert "keys=[ids" not in stats._jdf.queryExecution().executedPlan().toString()
    assert grams(stats, p) == grams(direct_count(p, 2, 5), p)
