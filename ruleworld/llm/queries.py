"""Registered queries of the training-data operators, with production parameters, and their SQL where SQL can tell."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleworld.llm import decontaminate, exact_dedup, html_extract, language, packing, quality, sharding, simhash, token_codec, warc
from ruleworld.sources.scratch import table

VOCABULARY = "byte_bpe_50k.json"


def op1_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = simhash.near_groups(table(spark, sf_dir, "documents"), words=4, radius=4)
    return groups.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_minimax_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_rows(table(spark, sf_dir, "documents"), shards=40).drop("first")


def op3_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def op4_exact_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = exact_dedup.exact_groups(table(spark, sf_dir, "documents"), keep="largest")
    return groups.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op5_warc_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    where, manifest = warc.write_archives(table(spark, sf_dir, "pages"), least=100)
    return warc.read_archives(where, manifest).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents"))


def op7_benchmark_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), window=10)


def op8_packed_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), VOCABULARY, end_id=1, capacity=2048)


def op9_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_codec.round_trip(table(spark, sf_dir, "documents"), VOCABULARY, end_id=2)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    own = [op1_simhash_groups, op2_minimax_shards, op3_main_text, op4_exact_groups, op5_warc_archives, op6_language, op7_benchmark_hits, op8_packed_sequences, op9_site_quality, op10_token_files, pipeline]
    return {f.__name__: f for f in own}


_OP4 = """
SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
       doc_id = max(doc_id) OVER g AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents
WINDOW g AS (PARTITION BY coalesce(text, ''))
"""

_OP5 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
     d AS (SELECT page_id, strlen(body) AS payload_bytes, sha256(body) AS payload_digest FROM p),
     f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN first_id END AS refers_to
FROM f
"""

_WORDS = r"regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

_OP7 = f"""
WITH items AS (SELECT item_id, {_WORDS} AS w FROM benchmark WHERE text IS NOT NULL),
     sized AS (SELECT item_id, w, least(10, len(w)) AS m FROM items WHERE len(w) > 0),
     places AS (SELECT item_id, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM sized),
     windows AS (SELECT DISTINCT item_id, m, array_to_string(w[i : i + m - 1], ' ') AS k FROM places),
     docs AS (SELECT doc_id, coalesce({_WORDS}, []) AS w FROM documents),
     spots AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM docs),
     keys AS (SELECT doc_id, i, s.m, array_to_string(w[i : i + s.m - 1], ' ') AS k
              FROM spots, (SELECT DISTINCT m FROM windows) s WHERE i + s.m - 1 <= len(w)),
     hits AS (SELECT doc_id, i, m, item_id FROM keys JOIN windows USING (m, k)),
     hit_words AS (SELECT doc_id, count(DISTINCT p) AS n_hit
                   FROM (SELECT doc_id, unnest(range(i, i + m)) AS p FROM hits) GROUP BY doc_id),
     hit_items AS (SELECT doc_id, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids
                   FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS id FROM hits) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM docs d LEFT JOIN hit_words USING (doc_id) LEFT JOIN hit_items USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op4_exact_groups": _OP4, "op5_warc_archives": _OP5, "op7_benchmark_hits": _OP7}
