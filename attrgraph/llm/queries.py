"""The queries op1_ to op10_ over whole tables, with production parameters, and their SQL."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from attrgraph.llm import fmindex, language, lm, minhash, neighbours, pages, pieces, planes, quality, secrets

PIECE_MODEL = public_tokenizers.path("piece_bpe_32k.model")
BYTE_TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "kept")


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify_languages(_table(spark, sf_dir, "documents"))


def op3_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_and_decode(_table(spark, sf_dir, "documents"), PIECE_MODEL)


def op4_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.search(_table(spark, sf_dir, "embeddings"))


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planes.write_and_read(_table(spark, sf_dir, "documents"), BYTE_TOKENIZER)


def op6_pseudo_likelihood(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_documents(_table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score_quality(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op8_contamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fmindex.find_contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op9_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pages.extract_main_text(_table(spark, sf_dir, "pages")).select("page_id", "url", "text", "n_chars")


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(_table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_near_duplicates, op2_language, op3_pieces, op4_neighbours, op5_token_files, op6_pseudo_likelihood, op7_quality, op8_contamination, op9_main_text, op10_secrets)}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES = {
    "op1_near_duplicates": rf"""
with recursive words as (
  select doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') as w from documents
), sets as (
  select doc_id, case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
    else list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) end as s from words
), rows_of as (
  select doc_id, len(s) as n, unnest(s) as shingle from sets
), pairs as (
  select a.doc_id as a, b.doc_id as b, min(a.n) as na, min(b.n) as nb, count(*) as common
  from rows_of a join rows_of b on a.shingle = b.shingle and a.doc_id <> b.doc_id group by all
), links as (
  select a, b from pairs where 100 * common >= 75 * (na + nb - common)
), reach as (
  select doc_id as id, doc_id as root from documents
  union
  select l.b, r.root from reach r join links l on l.a = r.id
), parts as (
  select id, min(root) as component_id from reach group by id
)
select s.doc_id, cast(len(s.s) as bigint) as n_shingles, p.component_id, p.component_id = s.doc_id as kept
from sets s join parts p on p.id = s.doc_id""",
    "op8_contamination": rf"""
with dw as (
  select doc_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents
), bw as (
  select item_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark where item_id is not null
), windows as (
  select item_id, least(10, len(w)) as size, unnest(list_transform(range(1, len(w) - least(10, len(w)) + 2), lambda i: array_to_string(w[i:i + least(10, len(w)) - 1], ' '))) as g
  from bw where len(w) > 0
), sizes as (
  select distinct size from windows
), grams as (
  select doc_id, size, unnest(range(1, len(w) - size + 2)) as i, w from dw, sizes where len(w) >= size
), found as (
  select doc_id, i, grams.size as size, item_id from grams join windows on windows.size = grams.size and windows.g = array_to_string(w[i:i + grams.size - 1], ' ')
), hit as (
  select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + size)) as p from found) group by doc_id
), items as (
  select doc_id, count(*) as n_items, string_agg(item, ',' order by item) as listed from (select distinct doc_id, cast(item_id as varchar) as item from found) group by doc_id
)
select dw.doc_id, cast(len(dw.w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
  sha256(coalesce(listed, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from dw left join hit using (doc_id) left join items using (doc_id)""",
}
