"""Query op7: verdicts on every page URL."""

from pyspark.sql import DataFrame, SparkSession

from deltamp.llm.common import table
from deltamp.llm.urls import PATTERNS, RULES, filter_urls


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"))


def _sql() -> str:
    fits = lambda h, p: f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))"
    ranked = sorted(RULES, key=lambda r: -len(r[1] + r[2]))
    rule = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{h}{p}'" for _, h, p in ranked) + " END"
    action = "CASE rule " + " ".join(f"WHEN '{h}{p}' THEN '{a}'" for a, h, p in ranked) + " END"
    blocked = " OR ".join(f"regexp_matches(lower(coalesce(url, '')), '{p}')" for p in PATTERNS)
    return rf"""
WITH tail AS (SELECT page_id, url, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS t FROM pages),
     cut AS (SELECT page_id, url, lower(regexp_extract(t, '^[^/?#]*')) AS host, regexp_extract(t, '^[^/?#]*([^?#]*)', 1) AS path FROM tail),
     ruled AS (SELECT *, {rule} AS rule FROM cut)
SELECT page_id, host, path, rule, coalesce({action}, CASE WHEN {blocked} THEN 'block' ELSE 'allow' END) AS verdict FROM ruled"""


QUERIES = {"op7_url_filter": op7_url_filter}
ORACLES = {"op7_url_filter": _sql()}
