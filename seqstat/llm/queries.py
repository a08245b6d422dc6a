"""Queries of the ten operators and of the pipeline, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqstat.llm import embedding_dedup, exact_dedup, language_id, mixing, packing, pii, secret_scan, simhash, spans, token_count, toxicity
from seqstat.llm.shared import documents


def op1_simhash_covering(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.fingerprint_components(documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_curriculum_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.by_position(mixing.assign(documents(spark, sf_dir)), "first_position")
    return mixed.select("doc_id", "size", "source_size", "target", "taken", F.round("first_position", 6).alias("position"), F.size("copies").cast("long").alias("copies"))


def op3_resync_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.token_counts(documents(spark, sf_dir))


def op4_markov_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spans.digest(secret_scan.find_secrets(documents(spark, sf_dir)), [k.name for k in secret_scan.BASE])


def op5_complement_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir))


def op6_digest_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = exact_dedup.exact_groups(documents(spark, sf_dir))
    return groups.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def op7_trie_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.score(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return scored.select("doc_id", "held_out", "score", "predicted")


def op8_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.language_mixtures(documents(spark, sf_dir)).select("doc_id", "held_out", "lang_pred", "score")


def op9_int8_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op10_bilstm_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spans.digest(pii.find_pii(documents(spark, sf_dir)), pii.BASE)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_simhash_covering": op1_simhash_covering,
    "op2_curriculum_mix": op2_curriculum_mix,
    "op3_resync_token_counts": op3_resync_token_counts,
    "op4_markov_secrets": op4_markov_secrets,
    "op5_complement_packing": op5_complement_packing,
    "op6_digest_tree": op6_digest_tree,
    "op7_trie_toxicity": op7_trie_toxicity,
    "op8_language_mixture": op8_language_mixture,
    "op9_int8_embedding_dedup": op9_int8_embedding_dedup,
    "op10_bilstm_pii": op10_bilstm_pii,
}

ORACLES: dict[str, str] = {
    "op2_curriculum_mix": r"""
with sized as (
  select doc_id, source, cast(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as bigint) size,
         cast('0x' || substr(md5(coalesce(cast(doc_id as varchar), '')), 1, 8) as bigint) ord
  from documents),
totals as (select source, cast(sum(size) as bigint) source_size from sized group by source),
known as (
  select source, source_size, 3 * source_size lim, (row_number() over (order by source nulls last) - 1) % 3 as kind,
         [5, 2, 1][1 + (row_number() over (order by source nulls last) - 1) % 3] w
  from totals),
levels as (
  select *, row_number() over (order by lim / w, source nulls last) rk,
         cast(sum(source_size) over () - coalesce(sum(lim) over b, 0) as double) / cast(sum(w) over () - coalesce(sum(w) over b, 0) as double) lv
  from known window b as (order by lim / w, source nulls last rows between unbounded preceding and 1 preceding)),
fixed as (select *, (select lv from levels where lim > w * lv order by rk limit 1) fin from levels),
aims as (select source, source_size, kind, case when lim > w * fin then w * fin else cast(lim as double) end target from fixed),
placed as (
  select s.*, coalesce(sum(size) over (partition by source order by ord, doc_id, size rows between unbounded preceding and 1 preceding), 0) before
  from sized s),
cuts as (
  select doc_id, size, source_size, target, kind, cast(round(target) as bigint) as budget, cast(before as bigint) as before,
         [greatest(0, least(size, cast(round(target) as bigint) - before - e * source_size)) for e in [0, 1, 2]] as words
  from placed p join aims a on p.source is not distinct from a.source),
shares as (select *, case when budget > 0 then before / budget else cast(1 as double) end as share from cuts)
select doc_id, size, source_size, target, cast(list_sum(words) as bigint) taken, cast(len([x for x in words if x > 0]) as bigint) copies,
       round(case when share >= 1 then share
                  when kind = 0 then 2 * share / (sqrt(2.25 - 2 * share) + 1.5)
                  when kind = 1 and share < 0.375 then 2 * share / (sqrt(0.25 + 2 * share) + 0.5)
                  when kind = 1 then 0.5 + 2 * (share - 0.375) / (sqrt(1 + 2 * (share - 0.375)) + 1)
                  else share end, 6) as position
from shares""",
    "op6_digest_tree": r"""
with t as (select doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) h from documents)
select doc_id, min(doc_id) over g keep_id, count(*) over g group_size, doc_id = min(doc_id) over g kept, h text_sha256
from t window g as (partition by h)""",
    "op9_int8_embedding_dedup": """
with recursive v as (select vec_id, embedding::double[] e from embeddings),
links as (select a.vec_id a, b.vec_id b from v a join v b on a.vec_id <> b.vec_id and list_cosine_similarity(a.e, b.e) >= 0.95),
reach as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a)
select vec_id, (select count(*) from links l where l.a = v.vec_id) n_links,
       least(vec_id, coalesce((select min(b) from reach r where r.a = v.vec_id), vec_id)) component_id,
       least(vec_id, coalesce((select min(b) from reach r where r.a = v.vec_id), vec_id)) = vec_id kept
from v""",
}


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES["pipeline"] = pipeline


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
