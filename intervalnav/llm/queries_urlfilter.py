"""Query of the URL filter and its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import urlfilter
from .common import pages

# The rules of the query as (host, path prefix, blocked).
RULES = [
    ("com", "/", False),
    ("example.com", "/en/", True),
    ("www.example.com", "/en/", False),
    ("net", "/es/", True),
    ("net", "/fr/", True),
]


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(pages(spark, sf_dir), RULES)


_VALUES = ", ".join(f"('{h}', '{p}', {str(b).lower()})" for h, p, b in RULES)
SQL = {
    "op7_url_filter": rf"""
    WITH rules(h, p, blocked) AS (VALUES {_VALUES}),
    parts AS (
      SELECT page_id, translate(regexp_extract(coalesce(url, ''), '^.*?://([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(coalesce(url, ''), '^.*?://[^/?#]*([^?#]*)', 1, 's') AS path FROM pages),
    fits AS (
      SELECT parts.*, h || p AS r, blocked,
             row_number() OVER (PARTITION BY page_id ORDER BY length(h || p) DESC NULLS LAST) AS n
      FROM parts LEFT JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
    SELECT page_id, host, path, r AS rule, CASE WHEN blocked THEN 'block' ELSE 'allow' END AS verdict FROM fits WHERE n = 1"""
}
QUERIES = {"op7_url_filter": op7_url_filter}
