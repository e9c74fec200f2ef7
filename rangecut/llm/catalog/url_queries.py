"""op6: a verdict for every page's URL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rangecut.llm import urls
from rangecut.llm.shared import table


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url")
    return urls.judge(pages, urls.LIST_RULES + urls.WORD_RULES).drop("n_tried")


QUERIES = {"op6_url_filter": op6_url_filter}

_LIST = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))
_FITS = " UNION ALL ".join(
    f"SELECT page_id, k, '{h}{p}' AS rule, '{v}' AS verdict, {len(h + p)} AS weight FROM parts WHERE (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')"
    for h, p, v in _LIST
)
_WORDS = " OR ".join(f"regexp_matches(lower(host || path), '(^|[^a-z0-9]){'[^a-z0-9]'.join(r.tokens)}([^a-z0-9]|$)')" for r in urls.WORD_RULES)
ORACLE_SQL = {
    "op6_url_filter": rf"""
WITH parts AS (
  SELECT page_id, row_number() OVER () AS k,
         translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), '{urls.UPPER}', '{urls.LOWER}') AS host,
         coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path
  FROM pages
), fits AS ({_FITS}), best AS (
  SELECT k, max_by(rule, weight) AS rule, max_by(verdict, weight) AS verdict FROM fits GROUP BY k
)
SELECT page_id, host, path, best.rule,
       coalesce(best.verdict, CASE WHEN {_WORDS} THEN 'block' ELSE 'allow' END) AS verdict
FROM parts LEFT JOIN best USING (k)
"""
}
