"""One query for each operator of the subpackage, over whole tables, with SQL where SQL can say the same."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format, fertility_rules, hilbert_shards, quality_net, queries_text, sentence_pieces, toxicity_fm, url_filter
from .shared import table


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentence_pieces.encode_documents(spark, table(spark, sf_dir, "documents"))


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    planted = spark.sql(
        r"SELECT CAST(-1 AS BIGINT) AS conv_id, turn, role, '</s>[INST] ok [/INST]' AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)"
    )
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(planted)
    return chat_format.read_back(chat_format.chat_windows(turns))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity_fm.score_documents(spark, docs, toxicity_fm.fit_on(docs, table(spark, sf_dir, "labels")))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_net.score_documents(spark, docs, quality_net.fit_on(docs, table(spark, sf_dir, "labels")))


def op8_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fertility_rules.judge_documents(spark, table(spark, sf_dir, "documents"))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = url_filter.judge_urls(table(spark, sf_dir, "pages"))
    return judged.withColumn("n_globs", F.size("matched_globs").cast("long")).drop("matched_globs")


def op10_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert_shards.hilbert_shards(table(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (op1_sentencepiece, op4_chat_format, op6_toxicity, op7_quality, op8_fertility, op9_url_filter, op10_hilbert_shards)
} | queries_text.QUERIES


def _glob_regex(glob: str) -> str:
    parts = re.findall(r"\*\*|\*|\?|\\.|.", glob, flags=re.S)
    own = {"**": ".*", "*": "[^/]*", "?": "[^/]"}
    return "".join(own.get(p) or re.escape(p[-1]) for p in parts)


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _decoded_sql(value: str) -> str:
    """Codes of unreserved characters resolved; the percent sign is none of them, so their order does not matter."""
    for c in url_filter.UNRESERVED:
        value = f"regexp_replace({value}, '%{ord(c):02X}', '{c}', 'gi')"
    return value


def _url_sql() -> str:
    rules = sorted(url_filter.SITE_RULES, key=lambda r: -len(r[1] + r[2]))
    fits = [f"('.' || host) LIKE '%.{h}' AND starts_with(path, '{p}')" for _, h, p in rules]
    hits = " + ".join(f"CAST(regexp_full_match(whole, '{_glob_regex(g)}', 's') AS BIGINT)" for g in url_filter.BLOCK_GLOBS)
    rule = " ".join(f"WHEN {c} THEN '{h}{p}'" for c, (_, h, p) in zip(fits, rules, strict=True))
    verdict = " ".join(f"WHEN {c} THEN '{v}'" for c, (v, _, _) in zip(fits, rules, strict=True))
    ports = " ".join(f"WHEN scheme = '{s}' AND ends_with(h, ':{p}') THEN substr(h, 1, length(h) - {len(p) + 1})" for s, p in url_filter.PORTS)
    return f"""
    WITH bare AS (
      SELECT page_id, translate(substr(url, 1, greatest(strpos(url, '://') - 1, 0)), '{_UPPER}', '{_LOWER}') AS scheme, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
    ), parts AS (
      SELECT page_id, scheme, translate(regexp_extract(rest, '^[^/?#]*'), '{_UPPER}', '{_LOWER}') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path,
             regexp_extract(rest, '^[^?#]*((?s:.*))$', 1) AS query
      FROM bare
    ), decoded AS (
      SELECT *, regexp_extract(host, '([^@]*)$', 1) AS h, string_split({_decoded_sql("path")}, '/') AS segments,
             {_decoded_sql("regexp_extract(query, '^[^#]*')")} AS asked FROM parts
    ), dotless AS (
      SELECT *, CASE {ports} ELSE h END AS bare_host,
        list_reduce(list_transform(segments, lambda x: [x]), lambda a, b: CASE WHEN b[1] = '.' THEN a
          WHEN b[1] = '..' THEN a[:greatest(len(a) - 1, 1)] ELSE list_concat(a, b) END) AS kept
      FROM decoded
    ), joined AS (
      SELECT *, CASE WHEN host || path || query = '' THEN '' ELSE '.' || bare_host || array_to_string(kept, '/')
        || CASE WHEN segments[-1] IN ('.', '..') THEN '/' ELSE '' END || asked END AS whole FROM dotless
    ),
    counted AS (SELECT *, {hits} AS n_globs FROM joined)
    SELECT page_id, host, path, CASE {rule} END AS rule,
           CASE {verdict} WHEN n_globs > 0 THEN 'block' ELSE 'allow' END AS verdict, CAST(n_globs AS BIGINT) AS n_globs
    FROM counted"""


#: Budget, history, and tokens of the marks as in the operator's defaults.
CHAT_SQL = r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), sized AS (
  SELECT *, row_number() OVER o - 1 AS idx, CAST(ceil(length(text) / 4.0) AS BIGINT) + 8 AS tokens FROM turns
  WINDOW o AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)
), summed AS (
  SELECT *, CAST(sum(tokens) OVER (PARTITION BY conv_id ORDER BY idx) - tokens AS BIGINT) AS before FROM sized
), halved AS (
  SELECT *, greatest((768 - coalesce(max(tokens) FILTER (idx = 0 AND role = 'system') OVER (PARTITION BY conv_id), 0)) // 2, 1) AS half FROM summed
), marked AS (
  SELECT *, CASE WHEN idx > 0 AND (before // half <> lag(before // half) OVER c OR lag(tokens) OVER c > half OR tokens > half) THEN 1 ELSE 0 END AS starts
  FROM halved WINDOW c AS (PARTITION BY conv_id ORDER BY idx)
), spanned AS (
  SELECT *, sum(starts) OVER (PARTITION BY conv_id ORDER BY idx) AS span FROM marked
), placed AS (
  SELECT *, max(span) OVER (PARTITION BY conv_id) AS last_span, max(before + tokens) OVER (PARTITION BY conv_id, span) AS span_end FROM spanned
), used AS (
  SELECT *, 1 + CASE WHEN idx = 0 AND role = 'system' THEN last_span
                     WHEN span < last_span AND span_end - before <= 256 THEN 1 ELSE 0 END AS uses,
    length(regexp_replace(replace(role, '\', '\\'), '(<)(/?s>)|(\[)(/?INST\])', '\1\3\\\2\4', 'g'))
      + length(regexp_replace(replace(text, '\', '\\'), '(<)(/?s>)|(\[)(/?INST\])', '\1\3\\\2\4', 'g')) + 20 AS chars
  FROM placed
)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY idx)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY idx) FILTER (role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(chars * uses) AS BIGINT) AS formatted_chars, CAST(max(span) + 1 AS BIGINT) AS n_windows
FROM used GROUP BY conv_id"""

ORACLE_SQL = {"op4_chat_format": CHAT_SQL, "op9_url_filter": _url_sql()} | queries_text.ORACLE_SQL
