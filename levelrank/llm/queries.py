"""The registered queries of the text operators, and their SQL where SQL can say it.

Each query applies its operator to the whole table and returns a row per row of it (op3: a row per document and
leaked item). Null texts count as empty, repeated rows and ids are reported row by row, ties are broken as the
operator's module says, empty tables give empty results, and columns that an operator does not name are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from levelrank.llm import bpe, leaks, licenses, linededup, personal, quality, secrets, simhash, tokenfile, urlrules
from levelrank.llm.common import table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.report(table(spark, sf_dir, "documents"))


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_pii_weak_supervision(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal.report(table(spark, sf_dir, "documents"))


def op5_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlrules.judge(table(spark, sf_dir, "pages"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.verdicts(table(spark, sf_dir, "documents"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.token_table(table(spark, sf_dir, "documents"))


def op8_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(table(spark, sf_dir, "documents"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.report(table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.line_report(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_license_scan, op2_simhash_near_dedup, op3_benchmark_decontamination, op4_pii_weak_supervision, op5_url_filters, op6_quality_rules, op7_token_files, op8_bpe_round_trip, op9_secret_scan, op10_line_dedup)}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_URLS = f"""
WITH rest AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages),
parts AS (
  SELECT page_id, translate(regexp_extract(r, '^[^/?#]*'), '{_UPPER}', '{_LOWER}') AS host,
    regexp_extract(regexp_replace(r, '^[^/?#]*', ''), '^[^?#]*') AS path FROM rest),
fits AS (
  SELECT *, CASE
    WHEN ('.' || host) LIKE '%.example.com' AND starts_with(path, '/en/7') THEN 'example.com/en/7'
    WHEN ('.' || host) LIKE '%.example.net' AND starts_with(path, '/de/8') THEN 'example.net/de/8'
    WHEN ('.' || host) LIKE '%.com' AND starts_with(path, '/en/') THEN 'com/en/'
    WHEN ('.' || host) LIKE '%.net' AND starts_with(path, '/de/') THEN 'net/de/'
    WHEN ('.' || host) LIKE '%.org' AND starts_with(path, '/es/') THEN 'org/es/' END AS rule,
  CASE
    WHEN regexp_matches(path, '/(login|signin)([/.]|$)') THEN 'sign-in pages'
    WHEN regexp_matches(host, '^(.*[.-])?casino[.-]') THEN 'casino hosts'
    WHEN regexp_matches(host, '^(.*[.-])?(xxx|porn|adult)[.-]') THEN 'adult hosts'
    WHEN regexp_matches(host, '^(.*[.-])?spam[.-]') THEN 'spam hosts'
    WHEN regexp_matches(host, '-farm[.]') THEN 'link farms' END AS own_rule
  FROM parts)
SELECT page_id, host, path, rule, CASE
  WHEN rule IN ('example.com/en/7', 'net/de/') THEN 'allow'
  WHEN rule IS NOT NULL OR own_rule IS NOT NULL THEN 'block' ELSE 'allow' END AS verdict, own_rule
FROM fits
"""

_LINES = f"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents),
keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '{_UPPER}', '{_LOWER}') AS key FROM lines),
frequent AS (
  SELECT key FROM (SELECT DISTINCT doc_id, key FROM keyed) t WHERE key <> '' GROUP BY key HAVING count(*) >= {linededup.MIN_DOCS})
SELECT doc_id, count(*) AS n_lines, count(f.key) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE f.key IS NULL), '')) AS kept_sha256
FROM keyed k LEFT JOIN frequent f ON k.key = f.key GROUP BY doc_id
"""

ORACLES = {"op5_url_filters": _URLS, "op10_line_dedup": _LINES}
