"""Queries and oracles of the training-data operators."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from simweave.sources.tables import table


def op1_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.surrogates import replace_entities

    return replace_entities(table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.warc import archive_round_trip
    from simweave.plans.staging import shared_dir

    path = f"{shared_dir(spark)}/archives-{uuid.uuid4().hex[:10]}"
    read = archive_round_trip(table(spark, sf_dir, "pages", "page_id", "url", "html"), path)
    return read.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP2_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages), g AS (SELECT h, max(page_id) AS first_id FROM p GROUP BY h),
d AS (SELECT page_id, p.h, first_id, sha1(p.h) AS x FROM p JOIN g ON p.h = g.h),
b AS (SELECT *, list_reduce(list_transform(range(0, 4), lambda k: list_reduce(list_transform(range(0, 8), lambda j:
    substring('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substring(x, 1 + 10 * k::INT, 10))::BIGINT >> (35 - 5 * j::INT)) & 31)::INT, 1)),
    lambda a, c: a || c)), lambda a, c: a || c) AS digest FROM d)
SELECT page_id, strlen(h)::BIGINT AS payload_bytes, digest AS payload_digest,
  CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> first_id THEN first_id END AS refers_to FROM b
"""


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.mixing import mix_documents

    mixed = mix_documents(table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def op4_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.quality import judge_documents

    judged = judge_documents(table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


OP4_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), windows AS (
  SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, unnest(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS g
  FROM d WHERE len(w) >= 3
), twice AS (
  SELECT doc_id, i FROM windows QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1
), gains AS (
  SELECT doc_id, least(3, i - lag(i, 1, -9) OVER (PARTITION BY doc_id ORDER BY i)) AS n FROM twice
), repeats AS (
  SELECT doc_id, sum(n) AS n FROM gains GROUP BY doc_id
), measured AS (
  SELECT d.doc_id, source, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    (len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
     - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))))::BIGINT AS n_dup_lines,
    coalesce(r.n, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN repeats r ON r.doc_id = d.doc_id
), ruled AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM measured
), hosts AS (
  SELECT source, count(*) AS n, sum(base_failed::INT) AS f, sum(base_failed::INT) / count(*)::DOUBLE AS rate FROM ruled GROUP BY source
), prior AS (
  SELECT avg(rate) AS m, CASE WHEN var_pop(rate) > 0 THEN greatest(least(avg(rate) * (1 - avg(rate)) / var_pop(rate) - 1, 1e6), 1.0) ELSE 1e6 END AS k FROM hosts
), verdicts AS (
  SELECT source, (f + m * k) / (n + k) <= 0.5 AS good FROM hosts, prior
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND good AS kept
FROM ruled JOIN verdicts v ON v.source IS NOT DISTINCT FROM ruled.source
"""


def op5_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.minhash_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


OP5_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM d
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL
), links AS (
  SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 75 * (x.n + y.n - i)
), both_ways AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach(node, root) AS (
  SELECT doc_id, doc_id FROM d UNION SELECT e.b, r.root FROM reach r JOIN both_ways e ON e.a = r.node
), c AS (SELECT node, min(root) AS component_id FROM reach GROUP BY node)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, component_id, d.doc_id = component_id AS kept
FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN c ON c.node = d.doc_id
"""


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.suffix_dedup import remove_repeats

    cleaned = remove_repeats(table(spark, sf_dir, "documents", "doc_id", "text"))
    return cleaned.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "text")


def op7_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.embedding_dedup import link_embeddings

    return link_embeddings(table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label"))


OP7_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.93
), reach(node, root) AS (
  SELECT vec_id, vec_id FROM embeddings UNION SELECT l.b, r.root FROM reach r JOIN links l ON l.a = r.node
), c AS (SELECT node, min(root) AS component_id FROM reach GROUP BY node), n AS (SELECT a, count(*) AS n FROM links GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, component_id, vec_id = component_id AS kept
FROM embeddings JOIN c ON node = vec_id LEFT JOIN n ON a = vec_id
"""


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents", "doc_id", "text"))


def op9_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.html_text import extract_pages

    return extract_pages(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from simweave.llm.sharding import shard_documents

    return shard_documents(table(spark, sf_dir, "documents", "doc_id", "text"))


QUERIES = {
    "op1_surrogates": op1_surrogates,
    "op2_warc": op2_warc,
    "op3_mixing": op3_mixing,
    "op4_host_quality": op4_host_quality,
    "op5_minhash_dedup": op5_minhash_dedup,
    "op6_suffix_dedup": op6_suffix_dedup,
    "op7_embedding_dedup": op7_embedding_dedup,
    "op8_packing": op8_packing,
    "op9_html_text": op9_html_text,
    "op10_sharding": op10_sharding,
}
ORACLES: dict[str, str] = {
    "op7_embedding_dedup": OP7_SQL,
    "op5_minhash_dedup": OP5_SQL,
    "op2_warc": OP2_SQL,
    "op4_host_quality": OP4_SQL,
}
