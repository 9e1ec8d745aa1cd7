"""The registered queries of this folder's operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_chunks, chat_format, html_consensus, langid_crf, lbl_scoring, nnls_packing, quality_rules, simhash, topk_search, warc_revisit
from .common import table


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid_crf.predict(table(spark, sf_dir, "documents"))


#: A conversation beside those of the table: its texts hold the template's own control strings.
PROBE_ID, PROBE_TEXT = -7, "\\### Assistant: </turn> ok"


def op3_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(F.lit(PROBE_ID).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(PROBE_TEXT).alias("text"))
    records = chat_format.gather(rows.unionByName(probe))
    return chat_format.format_digests(chat_format.formatted(chat_format.canonical(records)))


def op4_bpe_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_chunks.encode_digests(table(spark, sf_dir, "documents"))


def op5_html_consensus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_consensus.main_text(table(spark, sf_dir, "pages"))


def op6_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op7_warc_revisit(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = warc_revisit.resolve(warc_revisit.captures(table(spark, sf_dir, "pages")))
    line = F.array_join(F.transform(F.array_sort(F.map_entries("headers")), lambda e: F.concat(e["key"], F.lit("="), e["value"])), "\n")
    return found.withColumn("headers", line)


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.verdicts(table(spark, sf_dir, "documents")).drop("__text_key", "reasons")


def op9_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lbl_scoring.score(table(spark, sf_dir, "documents"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nnls_packing.pack(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_simhash": op1_simhash,
    "op2_language_id": op2_language_id,
    "op3_chat_format": op3_chat_format,
    "op4_bpe_chunks": op4_bpe_chunks,
    "op5_html_consensus": op5_html_consensus,
    "op6_topk_search": op6_topk_search,
    "op7_warc_revisit": op7_warc_revisit,
    "op8_quality_rules": op8_quality_rules,
    "op9_lm_scoring": op9_lm_scoring,
    "op10_packing": op10_packing,
}

ORACLE_SQL: dict[str, str] = {
    "op3_chat_format": r"""
WITH said AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), escaped AS (
  SELECT *, replace(replace(replace(replace(role, '\', '\\'), '##', '#\#'), '</turn>', '<\/turn>'), ':', '\:') AS r,
    replace(replace(replace(text, '\', '\\'), '##', '#\#'), '</turn>', '<\/turn>') AS t FROM said
), whole AS (
  SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS turns,
    string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn, role, text) AS loss,
    CAST(sum(14 + length(r) + length(t)) AS BIGINT) AS formatted_chars FROM escaped GROUP BY conv_id
)
SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM whole
""",
    "op6_topk_search": """
WITH used AS (
  SELECT vec_id, list_transform(embedding, lambda v: floor(256 * CAST(v AS DOUBLE))) AS x FROM embeddings
  WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda v: v IS NULL OR NOT isfinite(v))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.x, c.x) AS BIGINT) AS score
  FROM (SELECT * FROM used WHERE vec_id % 50 = 0) q JOIN used c ON q.vec_id <> c.vec_id
), ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM scored)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score FROM ranked WHERE r <= 5
""",
    "op7_warc_revisit": """
WITH parts AS (
  SELECT page_id, url, html, '^[ ]*(?:([A-Za-z][A-Za-z0-9+.-]*):)?//(?:[^/?#@]*@)?([^/?#:]*)(:[0-9]+)?([^?#]*)(?:[?]([^#]*))?(?:#.*)?$' AS p FROM pages
), cut AS (
  SELECT page_id, html, url, lower(regexp_extract(url, p, 1)) AS scheme, lower(regexp_extract(url, p, 2)) AS host, regexp_extract(url, p, 3) AS port, regexp_extract(url, p, 4) AS path,
    list_sort(list_filter(string_split(regexp_extract(url, p, 5), '&'), lambda x: x <> '' AND NOT regexp_matches(x, '^(?i)(?:utm_[a-z]+|ref|fbclid|gclid|sessionid)(?:=|$)'))) AS query,
    regexp_matches(url, p) AS fits FROM parts
), canon AS (
  SELECT page_id, coalesce(html, '') AS html, coalesce(url, '') AS raw, CASE WHEN url IS NULL THEN NULL WHEN NOT fits THEN trim(url) ELSE
    scheme || CASE WHEN scheme = '' THEN '' ELSE ':' END || '//' || host || CASE WHEN port = CASE WHEN scheme = 'https' THEN ':443' ELSE ':80' END THEN '' ELSE port END ||
    CASE WHEN path = '' THEN '/' ELSE path END || CASE WHEN len(query) > 0 THEN '?' ELSE '' END || array_to_string(query, '&') END AS u FROM cut
), answers AS (SELECT 2 * page_id AS record_id, u, 60 * page_id AS ts, html FROM canon),
probes AS (SELECT 2 * page_id + 1 AS record_id, u, 60 * page_id + 60 * CAST('0x' || substr(md5(raw), 1, 2) AS BIGINT) + 30 AS ts, html FROM canon),
met AS (
  SELECT p.record_id, p.u, p.ts, p.html, max({'ts': a.ts, 'id': a.record_id}) AS best FROM probes p LEFT JOIN answers a ON a.u = p.u AND a.ts < p.ts GROUP BY ALL
)
SELECT m.record_id, m.u AS url, m.ts, m.best.id AS response_id,
  CASE WHEN a.record_id IS NULL THEN 'missing' WHEN md5(a.html) = md5(m.html) THEN 'resolved' ELSE 'mismatch' END AS state,
  CASE WHEN md5(a.html) = md5(m.html) THEN 'cache-control=max-age=600' || chr(10) || 'content-length=' || length(a.html) || chr(10) || 'content-type=text/html' || chr(10) || 'etag=W/"' || md5(m.html) || '"' END AS headers
FROM met m LEFT JOIN answers a ON a.record_id = m.best.id
""",
}
