"""Not-modified revisit resolution for web captures.

A revisit (HTTP 304) carries no body.  It stands for the latest earlier full response of the same canonical URL, if its
validators agree with that response: an entity tag that differs, or a modification time that differs where no tags can be
compared, is a mismatch.  The resolved record has the response's payload and headers, updated by those headers that a 304
may send.

The as-of join sorts captures by (url, time) over range partitions, so a URL with very many captures spreads over
partitions: inside a partition the latest response is a running maximum, and for URLs that cross partition borders the last
response of earlier partitions is carried over in a table with one row for each such URL and partition.  Captures of one
URL at one time stay together.

Defined cases: a null URL, time or id resolves to nothing (`no_url`); no earlier response gives `orphan`; responses at the
same time as the revisit are not earlier; ties among responses go to the larger id; repeated revisits each get their row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ratiobin.llm.common import saved, table

# Headers that a 304 response may send to update a stored response.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "last-modified", "vary")


def canonical_url(url: Column) -> Column:
    """One spelling of a URL: https, lower-case host without www., no fragment, tracking parameters, index page or end slash."""
    out = F.regexp_replace(url, "#.*$", "")
    out = F.regexp_replace(out, r"([?&])(utm_[a-z]+|ref|fbclid|gclid)=[^&]*", "$1")
    out = F.regexp_replace(out, r"[?&]+$", "")
    out = F.regexp_replace(out, r"\?&+", "?")
    out = F.regexp_replace(out, r"&&+", "&")
    host = F.lower(F.regexp_extract(out, r"^[A-Za-z]+://([^/?]*)", 1))
    host = F.regexp_replace(F.regexp_replace(host, r":(80|443)$", ""), r"^www\.", "")
    rest = F.regexp_replace(F.regexp_extract(out, r"^[A-Za-z]+://[^/?]*(.*)$", 1), r"(/index\.html?|/)(\?|$)", "$2")
    return F.when(host != "", F.concat(F.lit("https://"), host, rest))


def latest_earlier(captures: DataFrame, payload: list[str]) -> DataFrame:
    """(url, ts, capture_id, is_full, ...) plus `match`: struct of ts, capture_id and payload of the latest earlier full row."""
    rows = saved(captures.repartitionByRange("url", "ts").sortWithinPartitions("url", "ts").withColumn("_part", F.spark_partition_id()), "captures")
    full = F.when(F.col("is_full"), F.struct("ts", "capture_id", *payload))
    here = Window.partitionBy("_part", "url").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    near = rows.withColumn("_near", F.max(full).over(here))
    torn = rows.groupBy("url").agg(F.min("_part").alias("a"), F.max("_part").alias("b")).where("a < b").select("url")
    ends = rows.join(torn, "url", "left_semi").groupBy("url", "_part").agg(F.max(full).alias("_last"))
    parts_before = Window.partitionBy("url").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    far = ends.select("url", "_part", F.max("_last").over(parts_before).alias("_far"))
    return near.join(far, ["url", "_part"], "left").withColumn("match", F.coalesce("_near", "_far")).drop("_part", "_near", "_far")


def as_map(entries: Column) -> Column:
    return F.coalesce(F.map_from_entries(entries), F.create_map().cast("map<string,string>"))


def merged_headers(stored: Column, sent: Column) -> Column:
    """Stored headers updated by the permitted ones of the 304."""
    allowed = F.map_filter(sent, lambda k, v: k.isin(*PERMITTED) & v.isNotNull())
    return F.map_concat(F.map_filter(stored, lambda k, v: ~F.array_contains(F.map_keys(allowed), k)), allowed)


def resolve(captures: DataFrame) -> DataFrame:
    """Captures (capture_id, url, ts, status, etag, last_modified, headers, digest) to one row for each revisit (status 304)."""
    slim = captures.select(
        "capture_id", canonical_url(F.col("url")).alias("url"), "ts", "etag", "last_modified", F.map_entries("headers").alias("headers"), "digest", (F.col("status") == 200).alias("is_full"), "status"
    )
    usable = slim.where("url IS NOT NULL AND ts IS NOT NULL AND capture_id IS NOT NULL AND status IN (200, 304)")
    joined = latest_earlier(usable, ["etag", "last_modified", "headers", "digest"]).where("status = 304")
    tags = F.col("etag").isNotNull() & F.col("match.etag").isNotNull()
    times = F.col("last_modified").isNotNull() & F.col("match.last_modified").isNotNull()
    weak = lambda c: F.regexp_replace(c, "^W/", "")
    state = (
        F.when(F.col("match").isNull(), "orphan")
        .when(tags & (weak(F.col("etag")) != weak(F.col("match.etag"))), "mismatch")
        .when(~tags & times & (F.col("last_modified") != F.col("match.last_modified")), "mismatch")
        .otherwise("resolved")
    )
    found = joined.withColumn("state", state)
    good = F.col("state") == "resolved"
    out = found.select(
        "capture_id", "url", "state", F.col("match.capture_id").alias("response_id"), F.when(good, F.col("match.digest")).alias("digest"),
        F.when(good, merged_headers(as_map(F.col("match.headers")), as_map(F.col("headers")))).alias("headers"),
    )
    lost = slim.where("status = 304 AND (url IS NULL OR ts IS NULL OR capture_id IS NULL)").select(
        "capture_id", "url", F.lit("no_url").alias("state"), F.lit(None).cast(out.schema["response_id"].dataType).alias("response_id"),
        F.lit(None).cast("string").alias("digest"), F.lit(None).cast("map<string,string>").alias("headers"),
    )
    return out.unionByName(lost)


def header_text(headers: Column) -> Column:
    return F.array_join(F.array_sort(F.transform(F.map_entries(headers), lambda e: F.concat(e["key"], F.lit("="), e["value"]))), ";")


def page_captures(pages: DataFrame) -> DataFrame:
    """Captures made of the pages table: each page is a full response at ten times its id and a revisit five later.

    Every third revisit names a stale entity tag; every fifth has no tag but a modification time.  Revisit ids are negative.
    """
    tag = F.concat(F.lit('"'), F.substring(F.md5("html"), 1, 16), F.lit('"'))
    base = pages.select("page_id", "url", tag.alias("tag"), F.md5("html").alias("digest"), F.length("html").cast("string").alias("size"))
    changed = (F.col("page_id") % 97).cast("string")
    response = base.select(
        F.col("page_id").alias("capture_id"), "url", (F.col("page_id") * 10).alias("ts"), F.lit(200).alias("status"), F.col("tag").alias("etag"), changed.alias("last_modified"),
        F.create_map(F.lit("content-type"), F.lit("text/html"), F.lit("content-length"), "size", F.lit("etag"), "tag", F.lit("date"), F.col("page_id").cast("string"), F.lit("cache-control"), F.lit("max-age=60")).alias("headers"),
        "digest",
    )
    stale, untagged = F.col("page_id") % 3 == 0, F.col("page_id") % 5 == 0
    sent = F.when(untagged, F.lit(None)).when(stale, F.lit('"stale"')).otherwise(F.col("tag"))
    revisit = base.select(
        (-F.col("page_id") - 1).alias("capture_id"), F.concat(F.regexp_replace("url", "^http:", "https:"), F.lit("#again")).alias("url"), (F.col("page_id") * 10 + 5).alias("ts"), F.lit(304).alias("status"),
        sent.alias("etag"), F.when(F.col("page_id") % 2 == 0, changed).otherwise(F.lit("never")).alias("last_modified"),
        F.create_map(F.lit("content-type"), F.lit("text/plain"), F.lit("content-length"), F.lit("0"), F.lit("date"), (F.col("page_id") + 1).cast("string"), F.lit("cache-control"), F.lit("max-age=120")).alias("headers"),
        F.lit(None).cast("string").alias("digest"),
    )
    return response.unionByName(revisit)


def op4_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = resolve(page_captures(table(spark, sf_dir, "pages")))
    return found.select((-F.col("capture_id") - 1).alias("page_id"), "url", "state", "response_id", "digest", header_text(F.col("headers")).alias("headers"))


_CANON = r"""
CASE WHEN regexp_extract(u4, '^[A-Za-z]+://([^/?]*)', 1) <> '' THEN concat('https://',
  regexp_replace(regexp_replace(lower(regexp_extract(u4, '^[A-Za-z]+://([^/?]*)', 1)), ':(80|443)$', ''), '^www\.', ''),
  regexp_replace(regexp_extract(u4, '^[A-Za-z]+://[^/?]*(.*)$', 1), '(/index\.html?|/)(\?|$)', '\2', 'g')) END
"""

SQL = rf"""
WITH caps AS (
  SELECT page_id AS id, url AS u, page_id * 10 AS ts, '"' || substr(md5(html), 1, 16) || '"' AS etag, CAST(page_id % 97 AS VARCHAR) AS lm,
         md5(html) AS digest, CAST(length(html) AS VARCHAR) AS size, true AS is_full FROM pages
  UNION ALL
  SELECT page_id, regexp_replace(url, '^http:', 'https:') || '#again', page_id * 10 + 5,
         CASE WHEN page_id % 5 = 0 THEN NULL WHEN page_id % 3 = 0 THEN '"stale"' ELSE '"' || substr(md5(html), 1, 16) || '"' END,
         CASE WHEN page_id % 2 = 0 THEN CAST(page_id % 97 AS VARCHAR) ELSE 'never' END, NULL, NULL, false FROM pages),
cut AS (SELECT *, regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(u, '#.*$', ''),
    '([?&])(utm_[a-z]+|ref|fbclid|gclid)=[^&]*', '\1', 'g'), '[?&]+$', ''), '\?&+', '?', 'g'), '&&+', '&', 'g') AS u4 FROM caps),
can AS (SELECT *, {_CANON} AS url FROM cut),
rev AS (SELECT * FROM can WHERE NOT is_full), resp AS (SELECT * FROM can WHERE is_full),
j AS (SELECT rev.id AS page_id, rev.url AS url, rev.etag AS e1, rev.lm AS l1, resp.id AS response_id, resp.etag AS e2, resp.lm AS l2, resp.digest AS d2, resp.size AS size
      FROM rev ASOF LEFT JOIN resp ON rev.url = resp.url AND rev.ts > resp.ts),
s AS (SELECT *, CASE WHEN response_id IS NULL THEN 'orphan' WHEN e1 IS NOT NULL AND e1 <> e2 THEN 'mismatch'
      WHEN e1 IS NULL AND l1 <> l2 THEN 'mismatch' ELSE 'resolved' END AS state FROM j)
SELECT page_id, url, state, response_id, CASE WHEN state = 'resolved' THEN d2 END AS digest,
       CASE WHEN state = 'resolved' THEN 'cache-control=max-age=120;content-length=' || size || ';content-type=text/html;date=' || CAST(page_id + 1 AS VARCHAR) || ';etag=' || e2 END AS headers
FROM s
"""
