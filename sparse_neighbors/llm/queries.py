"""One query per operator of this subpackage over its whole table, and DuckDB SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import maxent_lm, mixing, ngram_join, packing, progressive_jpeg, quality, token_files, toxicity, url_filter, vector_dedup
from .shared import table


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.jaccard_components(table(spark, sf_dir, "documents"), k=3, num=9, den=10)


URL_RULES = [url_filter.Rule(v, k) for v, k in (("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/"))]


def op2_maxent_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxent_lm.score_texts(table(spark, sf_dir, "documents"))


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file; the package that has them is on every machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), end_id=0, capacity=2048)


def op3_progressive_jpeg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return progressive_jpeg.store_texts(table(spark, sf_dir, "documents"))


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), threshold=0.3)


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.round_trip(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), end_id=2)


def op7_vector_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_dedup.near_duplicates(table(spark, sf_dir, "embeddings"), cosine=0.93)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), threshold=0.7)


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages"), URL_RULES)


def op10_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_plan(table(spark, sf_dir, "documents"), weights=(5, 2, 1), share=1.5, most=2)


QUERIES = {
    "op1_ngram_jaccard_join": op1_ngram_jaccard_join,
    "op2_maxent_lm_scores": op2_maxent_lm_scores,
    "op3_progressive_jpeg": op3_progressive_jpeg,
    "op4_best_fit_packing": op4_best_fit_packing,
    "op5_quality_classifier": op5_quality_classifier,
    "op6_token_files": op6_token_files,
    "op7_vector_near_duplicates": op7_vector_near_duplicates,
    "op8_toxicity": op8_toxicity,
    "op9_url_filter": op9_url_filter,
    "op10_source_mixing": op10_source_mixing,
}

OP9_SQL = r"""
with rests as (
  select page_id, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
parts as (
  select page_id,
    translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from rests),
ruled as (
  select page_id, host, path, case
    when (host = 'example.com' or host like '%.example.com') and starts_with(path, '/en/7') then 'example.com/en/7'
    when (host = 'com' or host like '%.com') and starts_with(path, '/en/') then 'com/en/'
    when (host = 'example.net' or host like '%.example.net') and starts_with(path, '/de/8') then 'example.net/de/8'
    when (host = 'net' or host like '%.net') and starts_with(path, '/de/') then 'net/de/'
    when (host = 'org' or host like '%.org') and starts_with(path, '/es/') then 'org/es/' end as rule from parts)
select page_id, host, path, rule,
  case when rule in ('com/en/', 'example.net/de/8', 'org/es/') then 'block' else 'allow' end as verdict from ruled
"""

OP10_SQL = r"""
with sized as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size from documents),
sources as (select source, sum(size)::bigint as source_size from sized group by source),
weighed as (
  select source, source_size, 2.0::double * source_size as cap,
    [5.0, 2.0, 1.0][((row_number() over (order by source nulls last) - 1) % 3 + 1)::int]::double as weight from sources),
levels as (
  select *, (1.5::double * (sum(source_size) over ())::double
      - coalesce(sum(cap) over (order by cap / weight, source nulls last rows between unbounded preceding and 1 preceding), 0))
      / sum(weight) over (order by cap / weight, source nulls last rows between current row and unbounded following) as level from weighed),
targets as (
  select source, source_size,
    least(cap, max(level) over () * weight) as target from levels),
rated as (
  select d.doc_id, d.size, t.source_size, t.target, case when t.source_size > 0 then t.target / t.source_size else 0 end as rate,
    ('0x' || substr(md5(coalesce(d.doc_id::varchar, '') || ':mix'), 1, 13))::bigint::double / 4503599627370496.0::double as u
  from sized d join targets t on d.source is not distinct from t.source)
select doc_id, size, source_size, target,
  (size * (floor(rate) + case when u < rate - floor(rate) then 1 else 0 end))::bigint as taken from rated
"""

ORACLES: dict[str, str] = {"op9_url_filter": OP9_SQL, "op10_source_mixing": OP10_SQL}
