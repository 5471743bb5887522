"""Registered queries of the training-data operators, production parameters, whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from relmine.llm.common import table


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.bpe import round_trip

    return round_trip(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.tokencount import token_counts

    return token_counts(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), limit=4096)


def op3_kneser_ney_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.quality import quality

    return quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("tid")


def op4_block_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.neighbours import nearest

    vectors = table(spark, sf_dir, "embeddings")
    return nearest(vectors, vectors.where("vec_id % 50 = 0"), k=5)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.toxicity import toxicity

    return toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.extraction import extract

    return extract(table(spark, sf_dir, "pages"))


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.substrings import deduplicated

    return deduplicated(table(spark, sf_dir, "documents"), window=50)


def op8_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), shingle=4, bits=4)


def op9_language_fusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.language import identify

    return identify(table(spark, sf_dir, "pages"), table(spark, sf_dir, "documents"))


def op10_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from relmine.llm.decontaminate import contamination

    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), size=13, share=20)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_bpe_round_trip": op1_bpe_round_trip,
    "op2_token_counts": op2_token_counts,
    "op3_kneser_ney_quality": op3_kneser_ney_quality,
    "op4_block_nearest": op4_block_nearest,
    "op5_toxicity": op5_toxicity,
    "op6_html_extraction": op6_html_extraction,
    "op7_substring_dedup": op7_substring_dedup,
    "op8_simhash_near_dedup": op8_simhash_near_dedup,
    "op9_language_fusion": op9_language_fusion,
    "op10_benchmark_decontamination": op10_benchmark_decontamination,
}

_OP10_SQL = r"""
with dw as (
  select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from documents),
bw as (
  select item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from benchmark),
bwin as (
  select distinct item_id, least(13, len(w)) as n, array_to_string(w[i:i + 12], ' ') as win
  from (select item_id, w, unnest(range(1, greatest(1, len(w) - 12) + 1)) as i from bw where len(w) > 0)),
sizes as (select distinct n from bwin),
dwin as (
  select doc_id, i, n, array_to_string(w[i:i + n - 1], ' ') as win
  from (select doc_id, w, n, unnest(range(1, len(w) - n + 2)) as i from dw, sizes where len(w) >= n)),
occ as (select d.doc_id, d.i, d.n, b.item_id from dwin d join bwin b on d.n = b.n and d.win = b.win),
hit as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + n)) as p from occ) group by 1),
its as (select doc_id, count(*) as n_items, string_agg(cast(item_id as varchar), ',' order by cast(item_id as varchar)) as ids
        from (select distinct doc_id, item_id from occ) group by 1)
select dw.doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
       sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) as contaminated
from dw left join hit using (doc_id) left join its using (doc_id)
"""

_OP7_SQL = r"""
with dw as (
  select doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
win as (
  select doc_id, i, md5(array_to_string(w[i:i + 49], ' ')) as h
  from (select doc_id, w, unnest(range(1, len(w) - 48)) as i from dw where len(w) >= 50)),
least_doc as (select h, min(doc_id) as d from win group by h),
gone as (select distinct doc_id, unnest(range(i, i + 50)) as p from win join least_doc using (h) where d < doc_id),
per_doc as (select doc_id, list(p) as ps from gone group by doc_id),
kept as (
  select dw.doc_id, w, list_filter(list_transform(range(1, len(w) + 1), lambda i: case when list_contains(coalesce(ps, []), i) then null else w[i] end), lambda x: x is not null) as k
  from dw left join per_doc using (doc_id))
select doc_id, cast(len(w) as bigint) as n_words, cast(len(w) - len(k) as bigint) as n_removed, sha256(coalesce(array_to_string(k, ' '), '')) as kept_sha256 from kept
"""

ORACLE_SQL: dict[str, str] = {"op7_substring_dedup": _OP7_SQL, "op10_benchmark_decontamination": _OP10_SQL}
