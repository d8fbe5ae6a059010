"""Not-modified revisits of web archives: an as-of join to the latest earlier full response.

Records are keyed by canonical URL. A hot URL may hold a third of all rows, so its records are cut
into time buckets of about BUCKET_ROWS rows at an even rate: each bucket passes its last response on to
the later ones (one row a URL and bucket), and one window per (URL, bucket) finishes the join. Only
record ids, validators and headers move; bodies stay where they are.

A revisit is resolved if its validators agree with the response's: entity tags by weak comparison where
both have one, else last-modified dates where both have one. Its permitted headers replace the
response's; those that describe the stored body never change.

Defined results: no earlier response gives status no_prior; validators that differ, validator_mismatch;
nothing to compare, no_validator; a null URL is the empty URL; a response at the revisit's own time is
not earlier; among responses of one time the greatest id wins; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BUCKET_ROWS = 20_000
# Header fields of a 304 answer that must not replace those stored with the body.
BODY_HEADERS = ("connection", "content-encoding", "content-length", "content-range", "content-type", "keep-alive", "te", "trailer", "transfer-encoding", "upgrade")


def canonical(url: Column) -> Column:
    """Scheme, leading www., default port, fragment, tracking parameters and final slash gone; host in lower case; parameters sorted."""
    u = F.regexp_replace(F.coalesce(url.cast("string"), F.lit("")), r"#[\s\S]*$", "")
    rest = F.regexp_replace(u, r"^[A-Za-z][A-Za-z0-9+.-]*://", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(rest, r"^[^/?]*", 0)), r"^www\.", ""), r":(80|443)$", "")
    path = F.regexp_replace(F.regexp_extract(rest, r"^[^/?]*([^?]*)", 1), r"/+$", "")
    query = F.regexp_extract(rest, r"\?([\s\S]*)$", 1)
    kept = F.array_join(F.array_sort(F.filter(F.split(query, "&"), lambda x: (x != "") & ~x.rlike("^(utm_|ref=)"))), "&")
    return F.concat(host, path, F.when(kept == "", "").otherwise(F.concat(F.lit("?"), kept)))


def resolve(records: DataFrame) -> DataFrame:
    """records: record_id, url, ts (long), kind (response or revisit), etag, last_modified, headers (map).

    Per revisit: record_id, canonical_url, response_id, status, headers.
    """
    span = records.agg(F.count("*").alias("n"), F.min("ts").alias("a"), F.max("ts").alias("z")).first()
    width = max(1, -(-((span["z"] or 0) - (span["a"] or 0) + 1) // max(1, -(-span["n"] // BUCKET_ROWS))))
    is_response = F.col("kind") == "response"
    full = F.when(is_response, F.struct("record_id", "etag", "last_modified", "headers"))
    rows = records.select(
        canonical(F.col("url")).alias("url"), F.floor((F.col("ts") - F.lit(span["a"] or 0)) / width).alias("bucket"),
        F.col("ts"), is_response.cast("int").alias("is_response"), "record_id", "etag", "last_modified", "headers", full.alias("held"),
    )
    latest = rows.groupBy("url", "bucket").agg(F.max_by("held", F.when(F.col("is_response") == 1, F.struct("ts", "record_id"))).alias("held"))
    earlier = Window.partitionBy("url").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = latest.select("url", "bucket", F.last("held", ignorenulls=True).over(earlier).alias("held")).where("held is not null")
    blank = {f.name: F.lit(None).cast(f.dataType) for f in rows.schema.fields}
    first = carried.select(*[F.col(c) if c in ("url", "bucket", "held") else F.lit(1 if c == "is_response" else None).cast(rows.schema[c].dataType).alias(c) for c in blank])
    # A carried row has a null time, which sorts before every record of its bucket.
    within = Window.partitionBy("url", "bucket").orderBy(F.col("ts").asc_nulls_first(), "is_response", "record_id").rowsBetween(Window.unboundedPreceding, -1)
    joined = rows.unionByName(first).withColumn("prior", F.last("held", ignorenulls=True).over(within)).where("is_response = 0")
    tag = lambda c: F.regexp_replace(c, "^W/", "")
    prior = F.col("prior")
    tags, dates = F.col("etag").isNotNull() & prior["etag"].isNotNull(), F.col("last_modified").isNotNull() & prior["last_modified"].isNotNull()
    agrees = F.when(tags, tag(F.col("etag")) == tag(prior["etag"])).when(dates, F.col("last_modified") == prior["last_modified"])
    status = F.when(prior.isNull(), "no_prior").when(agrees, "resolved").when(~agrees, "validator_mismatch").otherwise("no_validator")
    none = F.create_map().cast("map<string,string>")
    news = F.map_filter(F.coalesce("headers", none), lambda k, v: ~F.lower(k).isin(*BODY_HEADERS))
    olds = F.map_filter(F.coalesce(prior["headers"], none), lambda k, v: ~F.array_contains(F.transform(F.map_keys(news), lambda x: F.lower(x)), F.lower(k)))
    return joined.select("record_id", F.col("url").alias("canonical_url"), prior["record_id"].alias("response_id"), status.alias("status"), F.when(status == "resolved", F.map_concat(olds, news)).alias("headers"))
