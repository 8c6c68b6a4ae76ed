"""Queries of the operators that look for shared text, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import line_runs, ngram_join, phrase_index
from .shared import table


def op2_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_components(spark, table(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_runs.dedup_lines(spark, table(spark, sf_dir, "documents")).select("doc_id", "text", "n_lines", "n_removed")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return phrase_index.decontaminate(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {f.__name__: f for f in (op2_ngram_jaccard, op3_line_dedup, op5_decontamination)}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

PHRASE_SQL = rf"""
WITH iw AS (
  SELECT item_id, regexp_extract_all(translate(text, '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark
), windows AS (
  SELECT DISTINCT item_id, least(len(ws), 10) AS width, array_to_string(list_slice(ws, s, s + 9), ' ') AS phrase
  FROM iw, unnest(range(1, greatest(len(ws) - 9, 1) + 1)) AS t(s) WHERE len(ws) > 0
), dw AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents
), spots AS (
  SELECT doc_id, s, width, array_to_string(list_slice(ws, s, s + width - 1), ' ') AS phrase
  FROM dw, (SELECT DISTINCT width FROM windows), unnest(range(1, len(ws) + 1)) AS t(s) WHERE s + width - 1 <= len(ws)
), found AS (
  SELECT doc_id, s, spots.width, item_id FROM spots JOIN windows ON spots.phrase = windows.phrase AND spots.width = windows.width
), hits AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM found, unnest(range(s, s + width)) AS t(p) GROUP BY doc_id
), items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS joined
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM found) GROUP BY doc_id
)
SELECT dw.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(joined, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN hits USING (doc_id) LEFT JOIN items USING (doc_id)"""

JACCARD_SQL = rf"""
WITH RECURSIVE ws AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sh AS (
  SELECT DISTINCT doc_id, hash(array_to_string(list_slice(w, s, s + 4), ' ')) AS g
  FROM ws, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS t(s) WHERE len(w) > 0
), sizes AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
common AS (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS i FROM sh x JOIN sh y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2
), links AS MATERIALIZED (
  SELECT a, b FROM common JOIN sizes p ON p.doc_id = a JOIN sizes q ON q.doc_id = b WHERE 100 * i >= {ngram_join.SHARE} * (p.n + q.n - i)
), sym AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(node, root) AS (
  SELECT DISTINCT a, a FROM sym UNION SELECT s.b, r.root FROM reach r JOIN sym s ON s.a = r.node WHERE s.b > r.root
), roots AS (SELECT node, min(root) AS root FROM reach GROUP BY node)
SELECT ws.doc_id, coalesce(n, 0) AS n_shingles, least(coalesce(root, ws.doc_id), ws.doc_id) AS component_id
FROM ws LEFT JOIN sizes USING (doc_id) LEFT JOIN roots ON node = ws.doc_id"""

LINE_SQL = rf"""
WITH raw AS (
  SELECT doc_id, pos, line, len(list_filter(regexp_split_to_array(line, '[\x20\x09-\x0D]+'), lambda x: x <> '')) AS n
  FROM (SELECT doc_id, unnest(range(len(string_split(text, chr(10))))) AS pos, unnest(string_split(text, chr(10))) AS line FROM documents)
), rows AS (
  SELECT doc_id, pos, line, n, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS seq FROM raw WHERE n > 0
), summed AS (
  SELECT *, sum(n) OVER (PARTITION BY doc_id ORDER BY seq) AS upto FROM rows
), spans AS (
  SELECT a.doc_id, a.seq AS lo, min(b.seq) AS hi FROM summed a JOIN summed b ON a.doc_id = b.doc_id AND b.seq BETWEEN a.seq AND a.seq + 9
    AND b.upto - a.upto + a.n >= {line_runs.MIN_WORDS} GROUP BY 1, 2
  UNION
  SELECT b.doc_id, max(a.seq) AS lo, b.seq AS hi FROM summed a JOIN summed b ON a.doc_id = b.doc_id AND a.seq BETWEEN b.seq - 9 AND b.seq
    AND b.upto - a.upto + a.n >= {line_runs.MIN_WORDS} GROUP BY 1, 3
), named AS (
  SELECT s.doc_id, lo, hi, string_agg(line, chr(10) ORDER BY seq) AS run
  FROM spans s JOIN rows r ON r.doc_id = s.doc_id AND seq BETWEEN lo AND hi GROUP BY 1, 2, 3
), ordered AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY doc_id, lo) AS nth FROM named),
gone AS (
  SELECT DISTINCT r.doc_id, r.pos FROM ordered o JOIN rows r ON r.doc_id = o.doc_id AND r.seq BETWEEN lo AND hi WHERE nth > 1
), kept AS (
  SELECT raw.doc_id, string_agg(line, chr(10) ORDER BY raw.pos) FILTER (gone.pos IS NULL) AS text,
         count(*) FILTER (n > 0) AS n_lines, count(gone.pos) AS n_removed
  FROM raw LEFT JOIN gone ON gone.doc_id = raw.doc_id AND gone.pos = raw.pos GROUP BY 1
)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text,
       coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed
FROM documents d LEFT JOIN kept k USING (doc_id)"""

ORACLE_SQL = {"op2_ngram_jaccard": JACCARD_SQL, "op3_line_dedup": LINE_SQL, "op5_decontamination": PHRASE_SQL}
