"""Query op3: a capture log made of the pages table, its revisits resolved.

Every page gives a full response and a later not-modified revisit that names the page's entity tag.
"""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm.common import table
from deltamp.llm.revisits import BODY_HEADERS, resolve

_LATER = "page_id * 10 + 5 + ((page_id * 7919) % 997) * 10"


def captures(pages: DataFrame) -> DataFrame:
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.md5(F.coalesce("html", F.lit(""))).alias("digest"))
    tag = F.concat(F.lit('"'), "digest", F.lit('"'))
    text = lambda c: F.col(c).cast("string")
    full = p.select((F.col("page_id") * 2).alias("record_id"), "url", (F.col("page_id") * 10).alias("ts"), F.lit("response").alias("kind"), tag.alias("etag"), F.lit(None).cast("string").alias("last_modified"), F.create_map(F.lit("content-type"), F.lit("text/html"), F.lit("etag"), tag, F.lit("x-page"), text("page_id")).alias("headers"))
    again = p.select((F.col("page_id") * 2 + 1).alias("record_id"), "url", F.expr(_LATER).alias("ts"), F.lit("revisit").alias("kind"), F.concat(F.lit("W/"), tag).alias("etag"), F.lit(None).cast("string").alias("last_modified"), F.create_map(F.lit("content-length"), F.lit("0"), F.lit("x-cache"), F.concat(F.lit("hit "), text("page_id")), F.lit("x-page"), F.concat(F.lit("r"), text("page_id"))).alias("headers"))
    return full.unionByName(again)


def op3_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = resolve(captures(table(spark, sf_dir, "pages")))
    entries = F.transform(F.array_sort(F.map_entries("headers")), lambda e: F.concat(e["key"], F.lit(": "), e["value"]))
    return out.select("record_id", "canonical_url", "response_id", "status", F.array_join(entries, "; ").alias("headers"))


_CANON = r"""rtrim(regexp_replace(regexp_replace(lower(regexp_extract(rest, '^[^/?]*')), '^www\.', ''), ':(80|443)$', '') || regexp_replace(regexp_extract(rest, '^[^/?]*([^?]*)', 1), '/+$', '') || '?' ||
  array_to_string(list_sort(list_filter(string_split(regexp_extract(rest, '\?(.*)$', 1), '&'), lambda x: x <> '' AND NOT regexp_matches(x, '^(utm_|ref=)'))), '&'), '?')"""
ORACLES = {
    "op3_revisits": rf"""
WITH p AS (SELECT page_id, regexp_replace(regexp_replace(coalesce(url, ''), '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '') AS rest, md5(coalesce(html, '')) AS digest FROM pages),
     c AS (SELECT page_id, digest, {_CANON} AS u FROM p),
     f AS (SELECT u, page_id, page_id * 10 AS ts, digest FROM c),
     r AS (SELECT u, page_id, {_LATER} AS ts, digest FROM c),
     j AS (SELECT r.page_id, r.u, r.digest AS want, max_by(f.page_id, f.ts) AS fid, max_by(f.digest, f.ts) AS got FROM r LEFT JOIN f ON f.u = r.u AND f.ts < r.ts GROUP BY ALL)
SELECT page_id * 2 + 1 AS record_id, u AS canonical_url, fid * 2 AS response_id,
       CASE WHEN fid IS NULL THEN 'no_prior' WHEN want = got THEN 'resolved' ELSE 'validator_mismatch' END AS status,
       CASE WHEN want = got THEN 'content-type: text/html; etag: "' || got || '"; x-cache: hit ' || page_id || '; x-page: r' || page_id END AS headers
FROM j"""
}
QUERIES = {"op3_revisits": op3_revisits}
assert "content-length" in BODY_HEADERS
