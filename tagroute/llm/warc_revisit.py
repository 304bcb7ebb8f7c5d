"""Not-modified revisits of a web archive, resolved by an as-of join in DataFrame functions.

A revisit record says that a page had not changed.  It is joined by canonical
URL to the latest earlier full response, its validators are checked against that
response's, and the headers that a 304 may renew are merged into it.

The join sorts all records by (URL, time) into ranges, so that a URL with very
many captures takes many ranges.  Within a range the latest response is carried
by a window; into a range it comes from the last response of earlier ranges,
which is one row for each URL and range.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .ranges import dealt_by_order

#: Fixed list: header fields that a 304 response may renew.
PERMITTED_HEADERS = ("cache-control", "content-location", "date", "etag", "expires", "vary")
#: Query parameters that don't make another page.
TRACKING = "^(utm_[^=]*|ref|fbclid|gclid|sessionid)(=|$)"


def canonical_url(url: Column) -> Column:
    """Host in lower case without www and default port, path without a closing slash or index page, other query parameters in order; no scheme, no fragment."""
    rest = F.regexp_replace(F.regexp_replace(url, "#.*$", ""), "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(rest, "^([^/?]*)", 1)), ":(80|443)$", ""), "^www[0-9]*[.]", "")
    path = F.regexp_replace(F.regexp_extract(rest, "^[^/?]*([^?]*)", 1), "/(index[.]html?)?$", "")
    query = F.array_join(F.array_sort(F.filter(F.split(F.regexp_extract(rest, "[?](.*)$", 1), "&"), lambda p: (p != "") & ~p.rlike(TRACKING))), "&")
    return F.concat(host, path, F.when(query != "", F.concat(F.lit("?"), query)).otherwise(""))


def resolve(records: DataFrame) -> DataFrame:
    """Every revisit with its base response, what became of it, and the merged headers.

    records: rec_id long, rec_type (response or revisit; anything else is left out), url, ts long,
    etag, last_modified, digest, headers map<string, string>.
    Returned: rec_id, canonical, ts, status, base_id, digest, headers.
    status is resolved; mismatch - the first validator that the revisit has (etag, last_modified,
    digest) differs from the base's; unchecked - it has none; or orphan - there is no earlier response.
    Responses at the same time count as earlier if their rec_id is less.  Null urls are orphans; a
    null time sorts first; null headers are none.  Repeated revisits are resolved alike, of repeated
    responses any one counts.  An empty table gives an empty result.  Other columns are not read.
    """
    told = records.filter(F.col("rec_type").isin("response", "revisit")).select(
        "rec_id", "rec_type", canonical_url(F.col("url")).alias("canonical"), "ts", "etag", "last_modified", "digest", F.coalesce("headers", F.create_map().cast("map<string,string>")).alias("headers")
    )
    rows = dealt_by_order(told, F.col("canonical"), F.col("ts"), F.col("rec_id"), name="captures")
    full = F.when(F.col("rec_type") == "response", F.struct("rec_id", "etag", "last_modified", "digest", "headers"))
    here = W.partitionBy("pid", "canonical").orderBy("ts", "rec_id").rowsBetween(W.unboundedPreceding, -1)
    within = rows.withColumn("near", F.last(full, ignorenulls=True).over(here))
    # the last response of each URL in each range, then of all ranges before
    lasts = rows.groupBy("canonical", "pid").agg(F.max_by(full, F.when(F.col("rec_type") == "response", F.struct("ts", "rec_id"))).alias("last"))
    before = lasts.withColumn("far", F.last("last", ignorenulls=True).over(W.partitionBy("canonical").orderBy("pid").rowsBetween(W.unboundedPreceding, -1))).filter(F.col("far").isNotNull()).select("canonical", "pid", "far")
    joined = within.filter("rec_type = 'revisit'").join(before, ["canonical", "pid"], "left").withColumn("base", F.when(F.col("canonical").isNotNull(), F.coalesce("near", "far")))
    same = F.coalesce(F.col("etag") == F.col("base.etag"), F.when(F.col("etag").isNotNull(), False), F.col("last_modified") == F.col("base.last_modified"), F.when(F.col("last_modified").isNotNull(), False), F.col("digest") == F.col("base.digest"), F.when(F.col("digest").isNotNull(), False))
    status = F.when(F.col("base").isNull(), "orphan").when(same.isNull(), "unchecked").when(same, "resolved").otherwise("mismatch")
    renewed = F.map_filter("headers", lambda k, v: F.lower(k).isin(*PERMITTED_HEADERS))
    kept = F.map_filter("base.headers", lambda k, v: ~F.array_contains(F.transform(F.map_keys(renewed), F.lower), F.lower(k)))
    merged = F.when(F.col("status") == "resolved", F.map_concat(kept, renewed))
    return joined.withColumn("status", status).select("rec_id", "canonical", "ts", "status", F.col("base.rec_id").alias("base_id"), F.when(F.col("status") == "resolved", F.col("base.digest")).alias("digest"), merged.alias("headers"))


def records_of_pages(pages: DataFrame) -> DataFrame:
    """A crawl over the given pages: each one's response, revisits of it under other forms of its URL (some with another
    validator, some too early), and a capture of its host's robots file, which some hosts have very many of."""
    p = F.col("page_id")
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    tag = F.md5("html")
    head = lambda *kv: F.create_map(*(F.lit(x) if isinstance(x, str) else x for x in kv))
    text = lambda c: c.cast("string")
    base = pages.filter(F.col("url").isNotNull())
    none = F.lit(None).cast("string")
    response = base.select((p * 4).alias("rec_id"), F.lit("response").alias("rec_type"), "url", (p * 100).alias("ts"), tag.alias("etag"), text(p).alias("last_modified"), F.sha2("html", 256).alias("digest"), head("Content-Type", "text/html", "Date", text(p * 100), "ETag", tag, "Server", "origin").alias("headers"))
    again = base.select(
        (p * 4 + 1).alias("rec_id"), F.lit("revisit").alias("rec_type"), F.concat(F.regexp_replace("url", "#.*$", ""), F.lit("#again")).alias("url"), (p * 100 + 1000 * (1 + p % 5)).alias("ts"),
        F.when(p % 7 == 0, "other").when(p % 3 == 0, none).otherwise(tag).alias("etag"), F.when(p % 6 == 0, none).otherwise(text(p)).alias("last_modified"), F.when(p % 12 == 0, none).otherwise(F.sha2("html", 256)).alias("digest"),
        head("date", text(p * 100 + 1000), "Cache-Control", "max-age=60", "Content-Length", "0", "Set-Cookie", "a=b").alias("headers"),
    )
    early = base.filter(p % 11 == 0).select((p * 4 + 2).alias("rec_id"), F.lit("revisit").alias("rec_type"), F.upper(F.regexp_extract("url", "^([a-z]+://[^/]+)", 1)).alias("x"), "url", (p * 100 - 50).alias("ts"), tag.alias("etag"), none.alias("last_modified"), none.alias("digest"), head("Date", text(p)).alias("headers"))
    early = early.select("rec_id", "rec_type", F.concat("x", F.regexp_extract("url", "^[a-z]+://[^/]+(.*)$", 1)).alias("url"), "ts", "etag", "last_modified", "digest", "headers")
    version = F.concat(host, F.lit("-"), text(F.floor(p / 200)))
    robots = base.select((p * 4 + 3).alias("rec_id"), F.when(p % 50 == 0, "response").otherwise("revisit").alias("rec_type"), F.concat(F.lit("http://"), host, F.lit(":80/robots.txt")).alias("url"), (p * 100 + 7).alias("ts"), version.alias("etag"), none.alias("last_modified"), F.md5(version).alias("digest"), head("Date", text(p * 100), "Vary", "accept").alias("headers"))
    return response.unionByName(again).unionByName(early).unionByName(robots)
