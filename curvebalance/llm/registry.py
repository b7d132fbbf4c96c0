"""Queries opN_<name> of the corpus operators, over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from . import common as C, jaccard_join, language_id, line_dedup, mixing, packing, token_store, tokens, url_filter, vector_search, warc, webp

RULES = tuple(map(url_filter.Rule.parse, ("allow com/", "block example.com/en/", "allow www.example.com/en/", "block net/es/", "block net/fr/")))


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(_table(spark, sf_dir, "documents"), words=5, num=80, den=100).select("doc_id", "n_shingles", "component_id")


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return packing.pack_documents(docs, tokens.vocabulary("byte_bpe_50k.json"), tokens.vocabulary("byte_bpe_50k.tiktoken"), capacity=2048, end_id=0)


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup(_table(spark, sf_dir, "documents").select("doc_id", "text"), least_words=1)


def op4_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = C.new_path(spark, "token-store")
    token_store.write(_table(spark, sf_dir, "documents"), path, tokens.vocabulary("word_bpe_49k.json"), end_id=1)
    return token_store.digests(token_store.read(spark, path)).select("doc_id", "start", "n_tokens", "ids_crc32")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = C.new_path(spark, "warc")
    index = warc.write(_table(spark, sf_dir, "pages"), folder, least_bytes=0)
    return warc.read(index, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(_table(spark, sf_dir, "pages"), list(RULES)).select("page_id", "host", "path", "rule", "verdict")


def op7_webp_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return webp.decoded(C.stash(webp.media_table(_table(spark, sf_dir, "documents")), "media"))


def op8_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_search.search(_table(spark, sf_dir, "embeddings"), "embedding", "vec_id % 20 = 0", k=20)


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_table(spark, sf_dir, "documents"), entropy=0.95, most_epochs=2.0).select("doc_id", "source", "tokens", "epoch", "block", "turn", "order")


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(_table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_jaccard_join, op2_best_fit_packing, op3_line_dedup, op4_token_store, op5_warc, op6_url_filter, op7_webp_columns, op8_vector_search, op9_mixing, op10_language_id)}

_URL_CTE = """
urls AS (
  SELECT page_id, url, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, coalesce(translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM urls
), judged AS (
  SELECT page_id, host, path, CASE
    WHEN (host = 'www.example.com' OR ends_with(host, '.www.example.com')) AND starts_with(path, '/en/') THEN 'www.example.com/en/'
    WHEN (host = 'example.com' OR ends_with(host, '.example.com')) AND starts_with(path, '/en/') THEN 'example.com/en/'
    WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/es/') THEN 'net/es/'
    WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/fr/') THEN 'net/fr/'
    WHEN (host = 'com' OR ends_with(host, '.com')) AND starts_with(path, '/') THEN 'com/' END AS rule FROM parts
)"""

ORACLE_SQL: dict[str, str] = {
    "op6_url_filter": f"WITH {_URL_CTE} SELECT page_id, host, path, rule, CASE WHEN rule IN ('example.com/en/', 'net/es/', 'net/fr/') THEN 'block' ELSE 'allow' END AS verdict FROM judged",
}
