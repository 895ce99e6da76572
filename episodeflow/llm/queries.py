"""The subpackage's registered queries, and SQL for those that SQL can express."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import shared_dir
from . import decontaminate, language, onebit, packing, pii, quality, repair, simhash, token_cache, url_rules
from .common import table


def op1_onebit_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return onebit.search(rows, rows.where(F.col("vec_id") % 20 == 0))


def op2_pair_grammar_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repair.digest(table(spark, sf_dir, "documents"))


def op3_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(table(spark, sf_dir, "documents"))


def op4_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The folder of a corpus has a cache of its own: counting it again encodes what is new there, or nothing."""
    corpus = hashlib.sha256(sf_dir.rstrip("/").encode()).hexdigest()[:16]
    return token_cache.token_counts(table(spark, sf_dir, "documents"), cache=f"{shared_dir(spark)}/token-cache-{corpus}")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score(docs, quality.fit(docs, table(spark, sf_dir, "labels")))


def op8_spaced_seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judge(table(spark, sf_dir, "pages"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def queries() -> dict:
    own = (op1_onebit_neighbours, op2_pair_grammar_ids, op3_personal_data, op4_simhash_components, op5_token_counts, op6_language, op7_quality, op8_spaced_seeds, op9_url_rules, op10_packing)
    return {f.__name__: f for f in own}


ONEBIT_SQL = """
WITH e AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) = 64
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0
), s AS (
  SELECT q.vec_id AS query_id, e.vec_id, list_reduce(list_transform(list_zip(q.v, e.v), lambda p: p[1] * p[2]), lambda a, b: a + b) AS score
  FROM e AS q JOIN e ON e.vec_id <> q.vec_id WHERE q.vec_id % 20 = 0
)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM s) WHERE r <= 20
"""

URL_SQL = r"""
WITH RECURSIVE u AS (
  SELECT page_id, url, html, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), p AS (
  SELECT page_id, url, html, coalesce(translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
    coalesce(regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1), '') AS path, coalesce(regexp_extract(rest, '^[^#?]*(\?[^#]*)', 1), '') AS query FROM u
), t AS (
  SELECT host || path || query AS a, url, unnest(regexp_extract_all(html, '(?i)<(?:link|meta)\b[^>]*>')) AS tag FROM p WHERE host <> ''
), h AS (
  SELECT a, url, replace(CASE WHEN regexp_extract(tag, '(?i)href\s*=\s*["'']?([^"''\s>]+)', 1) <> '' THEN regexp_extract(tag, '(?i)href\s*=\s*["'']?([^"''\s>]+)', 1)
    ELSE regexp_extract(tag, '(?i)url\s*=\s*["'']?([^"''\s>;]+)', 1) END, '&amp;', '&') AS href
  FROM t WHERE regexp_matches(tag, '(?i)rel\s*=\s*["'']?canonical\b|http-equiv\s*=\s*["'']?refresh\b')
), g AS (
  SELECT a, CASE WHEN contains(href, '://') THEN substr(href, instr(href, '://') + 3) WHEN starts_with(href, '//') THEN substr(href, 3)
    WHEN starts_with(href, '/') THEN regexp_extract(url, '^.*?://([^/?#]*)', 1) || href END AS rest FROM h
), e AS (
  SELECT DISTINCT a, b FROM (SELECT a, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')
    || coalesce(regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1), '') || coalesce(regexp_extract(rest, '^[^#?]*(\?[^#]*)', 1), '') AS b FROM g WHERE rest IS NOT NULL) WHERE a <> b
), reach AS (
  SELECT a, b FROM e UNION SELECT b, a FROM e UNION SELECT a, a FROM e UNION SELECT b, b FROM e
  UNION SELECT reach.a, x.b FROM reach JOIN (SELECT a, b FROM e UNION ALL SELECT b, a FROM e) AS x ON reach.b = x.a
), rules(said, host, path) AS (
  VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')
), n AS (
  SELECT a, b, regexp_extract(b, '^([^/?#]*)', 1) AS host, coalesce(regexp_extract(b, '^[^/?#]*(/[^?#]*)', 1), '') AS path FROM reach
), best AS (
  SELECT n.a, n.b, arg_max(r.said, (length(r.host || r.path), r.said = 'allow')) AS said
  FROM n JOIN rules AS r ON (n.host = r.host OR ends_with(n.host, '.' || r.host)) AND starts_with(n.path, r.path) GROUP BY n.a, n.b
), aliases AS (
  SELECT a, CASE WHEN bool_or(said = 'allow') THEN 'allow' ELSE 'block' END AS said FROM best GROUP BY a
), own AS (
  SELECT p.page_id, p.host, p.path, p.query, arg_max(r.host || r.path, (length(r.host || r.path), r.said = 'allow')) AS rule, arg_max(r.said, (length(r.host || r.path), r.said = 'allow')) AS said
  FROM p LEFT JOIN rules AS r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path) GROUP BY ALL
)
SELECT own.page_id, own.host, own.path, own.rule, coalesce(own.said, aliases.said, 'allow') AS verdict
FROM own LEFT JOIN aliases ON own.host <> '' AND aliases.a = own.host || own.path || own.query
"""


def oracle_sql() -> dict:
    """SQL for the queries that it can express on whole tables; the others are tested against brute force."""
    return {"op1_onebit_neighbours": ONEBIT_SQL, "op9_url_rules": URL_SQL}
