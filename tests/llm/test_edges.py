"""Every operator on nulls, empty and long texts, ties, repeated rows, clashing extra columns, and empty tables."""

import hashlib

import pytest

import corpus_pipeline
from seqstat.llm import embedding_dedup, exact_dedup, language_id, mixing, packing, pii, secret_scan, simhash, token_count, toxicity

LONG = " ".join(f"word{i % 977} lorem" for i in range(12000))
ROWS = [
    (1, "a b c", "en", "s1"), (2, None, "en", "s1"), (3, "", None, None), (4, "a  b\tc", "en", "s2"), (5, "a b c", "fr", "s2"), (5, "a b c", "fr", "s2"),
    (6, "12 !!", None, None), (None, "x y", "en", None), (7, LONG, "en", "s1"), (8, "token = \"abcdef123\" mail me@example.com", "en", "s3"),
]
SCHEMA = "doc_id long, text string, lang string, source string"
OPERATORS = {
    "simhash": lambda d, s: simhash.fingerprint_components(d),
    "mixing": lambda d, s: mixing.assign(d),
    "tokens": lambda d, s: token_count.token_counts(d),
    "secrets": lambda d, s: secret_scan.find_secrets(d),
    "exact": lambda d, s: exact_dedup.exact_groups(d),
    "toxicity": lambda d, s: toxicity.score(d, s.createDataFrame([(1, 0), (8, 1)], "doc_id long, toxic int")),
    "language": lambda d, s: language_id.language_mixtures(d),
    "pii": lambda d, s: pii.find_pii(d),
}


@pytest.fixture(scope="module")
def docs(spark):
    from pyspark.sql import functions as F

    clashing = ["fp", "size", "offset", "rank", "order", "run", "digest", "label", "length", "h", "n", "score", "n_chars"]
    return spark.createDataFrame(ROWS, SCHEMA).select("*", *[F.lit(1).alias(c) for c in clashing])


@pytest.mark.parametrize("name", OPERATORS)
def test_one_row_each(spark, docs, name):
    found = OPERATORS[name](docs, spark).collect()
    assert sorted(str(r["doc_id"]) for r in found) == sorted(str(r[0]) for r in ROWS)
    assert OPERATORS[name](docs.limit(0), spark).collect() == []


def test_packing(spark, docs):
    found = packing.pack(docs).collect()
    assert len([r for r in found if r["doc_id"] == 2]) == 1 and {r["length"] for r in found if r["doc_id"] in (2, 3)} == {1}
    by_sequence = {}
    for r in found:
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by_sequence.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096
    assert packing.pack(docs.limit(0)).collect() == []


def test_exact_values(docs):
    found = {r["doc_id"]: r for r in exact_dedup.exact_groups(docs).collect()}
    assert found[4]["keep_id"] == 1 and found[5]["group_size"] == 4 and not found[5]["kept"]
    assert found[2]["keep_id"] == 2 and found[3]["keep_id"] == 2
    assert bytes(found[4]["digest"]) == hashlib.sha256(b"a b c").digest()
    kept = exact_dedup.keep_first(docs)
    assert kept.columns == docs.columns and kept.count() == 6


def test_simhash_values(docs):
    found = {r["doc_id"]: r for r in simhash.fingerprint_components(docs).collect()}
    assert found[2]["fp"] == found[3]["fp"] == 0 and found[3]["component_id"] == 2
    assert found[4]["component_id"] == found[5]["component_id"] == 1


def test_mixing_values(docs):
    rows = mixing.assign(docs).collect()
    total = sum(r["size"] for r in rows)
    by_source = {}
    for r in rows:
        assert r["taken"] <= 3 * r["size"]
        by_source.setdefault(r["source"], [r["target"], 0])[1] += r["taken"]
    assert abs(sum(t for t, _ in by_source.values()) - total) < 1e-6 * total
    assert all(abs(t - n) <= 1 for t, n in by_source.values())
    assert sorted(mixing.assign(docs).collect(), key=str) == sorted(rows, key=str)


def test_language_values(docs):
    found = {r["doc_id"]: r for r in language_id.language_mixtures(docs).collect()}
    assert found[2]["lang_pred"] == found[3]["lang_pred"] == found[6]["lang_pred"] == "und" and found[2]["score"] == 0
    assert found[1]["lang_pred"] in ("en", "fr")


def test_known_languages_move_no_text(spark, docs):
    known = language_id.keep_known(docs.select("doc_id", "text", "lang", "source", "n_chars"))
    plan = known._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan and known.count() == 7


def test_pipeline(spark, docs):
    left, counts = docs.select("doc_id", "text", "lang", "source", "n_chars"), []
    columns = left.columns
    for i, (_, function) in enumerate(corpus_pipeline.STAGES):
        left = function(spark, left, "")
        counts.append(left.count())
        if i + 1 < len(corpus_pipeline.STAGES):
            assert left.columns == columns
    assert counts[0] == 7 and counts[1] == 4
    empty = docs.select(*columns).limit(0)
    for _, function in corpus_pipeline.STAGES:
        assert function(spark, empty, "").count() == 0


def test_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 1.0]), (4, None), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [inf, 1.0]), (8, [None, 1.0]), (9, []), (10, [1.0, 0.0, 0.0]), (1, [1.0, 0.0]), (None, [1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    found = {r["vec_id"]: r for r in embedding_dedup.near_vectors(df).collect()}
    assert found[1]["n_links"] == 2 and found[2]["n_links"] == 2 and found[2]["component_id"] == 1 and not found[2]["kept"]
    for i in (3, 4, 5, 6, 7, 8, 9, 10):
        assert found[i]["n_links"] == 0 and found[i]["kept"]
    assert embedding_dedup.near_vectors(df.limit(0)).collect() == []
