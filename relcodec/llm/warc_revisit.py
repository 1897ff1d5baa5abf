"""Not-modified revisits of a web archive, resolved to the full responses they confirm.

A capture is (record_id, url, ts, status, headers, digest, size). A revisit (304) is resolved by an as-of join: the
latest earlier full response (200) of the same canonical URL. Its validators are checked: entity tags compare weakly
(a leading W/ is ignored); without a tag on either side Last-Modified must agree. A confirmed revisit gets the
response's headers, with those that a not-modified answer may update taken from the revisit.

The as-of join sorts no whole URL in one task: captures are cut into time buckets of a fixed width, the last response
of a bucket is found by partial aggregation, buckets hand it on in a narrow window (one row per URL and bucket), and
captures are ordered within (URL, bucket) only. Payloads never move; `attach_payload` fetches them by record id.

Defined cases: null URLs match nothing; captures with equal time count a response as not earlier; of several
responses at one time the largest record_id counts as the latest; null headers are empty, and so are null values; header
names that differ in case only are one header with its values joined; repeated rows repeat; an empty table gives an
empty result; further columns, whatever their names, are ignored; URLs and headers of any length are read whole. In
WARC files a record without a date has no time, and one with an unreadable length ends where the next record starts.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.llm import common

#: Headers that a 304 answer may update, in lower case.
UPDATABLE = ("cache-control", "content-location", "date", "etag", "expires", "vary")
#: Query parameters that name a visit and not a page.
TRACKING = "^(utm_[a-z]+|ref|fbclid|gclid|sessionid)="
BUCKET_SECONDS = 3600


def canonical_url(url: Column) -> Column:
    """Scheme, user, default port, leading www., fragment, tracking parameters and a last slash go; the host is lower case
    and parameters are sorted."""
    bare = F.regexp_replace(F.regexp_replace(F.trim(url), "#.*$", ""), "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    path = F.regexp_replace(bare, "[?].*$", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(path, "^[^/]*", 0)), "^(.*@)?(www[.])?", ""), ":(80|443)$", "")
    rest = F.regexp_replace(F.regexp_replace(path, "^[^/]*", ""), "/+$", "")
    query = F.when(bare.contains("?"), F.regexp_replace(bare, "^[^?]*[?]", "")).otherwise("")
    kept = F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~p.rlike(TRACKING)))
    return F.concat(host, rest, F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.array_join(kept, "&"))).otherwise(""))


def lower_keys(headers: Column) -> Column:
    """Headers by lower-case name; lines whose names differ in case only are one, joined as HTTP joins repeated lines
    (equal values once)."""
    def merged(entries: Column) -> Column:
        names = F.array_distinct(F.transform(entries, lambda e: F.lower(e["key"])))
        own = lambda k: F.array_join(F.array_distinct(F.transform(F.filter(entries, lambda e: F.lower(e["key"]) == k), lambda e: F.coalesce(e["value"], F.lit("")))), ", ")
        return F.map_from_entries(F.transform(names, lambda k: F.struct(k, own(k))))

    return common.let(F.map_entries(F.coalesce(headers, F.create_map().cast("map<string,string>"))), merged)


def resolve(captures: DataFrame, bucket_seconds: int = BUCKET_SECONDS) -> DataFrame:
    """One row per revisit: revisit_id, url_key, ts, response_id, response_ts, outcome, headers, digest, size.

    outcome: resolved, validator_mismatch or no_response; headers, digest and size are null unless resolved.
    """
    base = captures.filter("status in (200, 304)").select(
        "record_id", canonical_url(F.col("url")).alias("url_key"), "ts", (F.col("status") == 200).alias("full"), lower_keys(F.col("headers")).alias("headers"), "digest", "size",
    ).withColumn("bucket", F.floor(F.col("ts") / bucket_seconds))
    response = F.when(F.col("full"), F.struct("ts", "record_id", "headers", "digest", "size"))
    # A map can't be ordered, so the latest is found by (ts, record_id) and carries the rest along.
    latest = base.filter("full and url_key is not null").groupBy("url_key", "bucket").agg(
        F.max_by(F.struct("ts", "record_id", "headers", "digest", "size"), F.struct("ts", "record_id")).alias("own"))
    need = base.filter("not full and url_key is not null").select("url_key", "bucket").distinct().withColumn("own", F.lit(None).cast(latest.schema["own"].dataType))
    by_bucket = latest.unionByName(need).groupBy("url_key", "bucket").agg(F.first("own", ignorenulls=True).alias("own"))
    carried = by_bucket.select("url_key", "bucket", F.last("own", ignorenulls=True).over(W.partitionBy("url_key").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)).alias("before"))
    within = W.partitionBy("url_key", "bucket").orderBy("ts", F.col("full").cast("int"), "record_id").rowsBetween(W.unboundedPreceding, -1)
    # At one time revisits sort before responses, so a response counts only if it is earlier.
    nearest = base.filter("url_key is not null").withColumn("inside", F.last(response, ignorenulls=True).over(within)).filter("not full")
    found = nearest.join(carried, ["url_key", "bucket"], "left").withColumn("hit", F.coalesce("inside", "before")).drop("inside", "before")
    # Revisits without a URL match nothing, so they meet no window and no join.
    nowhere = base.filter("not full and url_key is null").withColumn("hit", F.lit(None).cast(found.schema["hit"].dataType))
    found = found.unionByName(nowhere)

    tag = lambda c: F.regexp_replace(F.element_at(c, "etag"), "^W/", "")
    mine, theirs = F.col("headers"), F.col("hit.headers")
    both_tags = tag(mine).isNotNull() & tag(theirs).isNotNull()
    agree = F.when(both_tags, tag(mine) == tag(theirs)).otherwise(F.coalesce(F.element_at(mine, "last-modified") == F.element_at(theirs, "last-modified"), F.lit(False)))
    ok = F.col("hit").isNotNull() & agree
    update = F.map_filter(mine, lambda k, _: k.isin(*UPDATABLE))
    merged = F.map_concat(F.map_filter(theirs, lambda k, _: ~F.map_contains_key(update, k)), update)
    return found.select(
        F.col("record_id").alias("revisit_id"), "url_key", "ts", F.col("hit.record_id").alias("response_id"), F.col("hit.ts").alias("response_ts"),
        F.when(F.col("hit").isNull(), "no_response").when(ok, "resolved").otherwise("validator_mismatch").alias("outcome"),
        F.when(ok, merged).alias("headers"), F.when(ok, F.col("hit.digest")).alias("digest"), F.when(ok, F.col("hit.size")).alias("size"))


def attach_payload(resolved: DataFrame, payloads: DataFrame) -> DataFrame:
    """Adds the confirmed response's payload (record_id, payload) to resolved revisits; others get null."""
    return resolved.join(payloads.select(F.col("record_id").alias("response_id"), "payload"), "response_id", "left").withColumn(
        "payload", F.when(F.col("outcome") == "resolved", F.col("payload")))


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Captures of uncompressed or gzipped WARC files: record_id (hash of the WARC-Record-ID), url, ts, status, headers, digest, size, payload."""
    schema = "record_id long, url string, ts long, status int, headers map<string,string>, digest string, size long, payload binary"

    def parsed(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for content in frame["content"]:
                rows = list(parse_warc(content))
                if rows:
                    yield pd.DataFrame(rows).astype({"ts": "Int64"})

    return spark.read.format("binaryFile").load(path).select("content").mapInPandas(parsed, schema)


def joined(lines: list[str]) -> dict[str, str]:
    """Header lines as a dictionary; lines of one name are joined with commas."""
    out: dict[str, str] = {}
    for line in lines:
        name, colon, value = line.partition(":")
        if colon:
            out[name.strip()] = f"{out[name.strip()]}, {value.strip()}" if name.strip() in out else value.strip()
    return out


def parse_warc(content: bytes) -> Iterator[dict]:
    """Response and revisit records of a WARC file's bytes, in order; records of other types are passed over."""
    import gzip
    import hashlib
    from datetime import datetime

    import xxhash

    data = gzip.decompress(content) if content[:2] == b"\x1f\x8b" else content
    at = 0
    while at < len(data):
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        head = {k.lower(): v for k, v in joined(data[at:end].decode("utf-8", "replace").split("\r\n")[1:]).items()}
        length = head.get("content-length", "").strip()
        following = data.find(b"\r\nWARC/", end + 4)
        size = int(length) if length.isascii() and length.isdigit() else (following if following >= 0 else len(data)) - end - 4
        block = data[end + 4: end + 4 + size]
        at = end + 4 + size
        while data[at: at + 2] == b"\r\n":
            at += 2
        if head.get("warc-type") not in ("response", "revisit"):
            continue
        http, _, body = block.partition(b"\r\n\r\n")
        first, *lines = http.decode("latin-1").split("\r\n")
        code = first.split(" ")[1] if first.count(" ") else ""
        status = int(code) if code.isascii() and code.isdigit() else 0
        try:
            when = int(datetime.fromisoformat(head["warc-date"].replace("Z", "+00:00")).timestamp())
        except (KeyError, ValueError):
            when = None
        yield {"record_id": xxhash.xxh64_intdigest(head.get("warc-record-id", "")) >> 1, "url": head.get("warc-target-uri"), "ts": when, "status": status,
               "headers": joined(lines), "digest": head.get("warc-payload-digest") or hashlib.sha1(body).hexdigest(), "size": len(body), "payload": body}


def format_warc(record_id: str, kind: str, url: str, ts: int, status: str, headers: dict[str, str], body: bytes = b"") -> bytes:
    """One WARC record with its HTTP answer."""
    from datetime import UTC, datetime

    http = "".join([f"HTTP/1.1 {status}\r\n", *(f"{k}: {v}\r\n" for k, v in headers.items()), "\r\n"]).encode("latin-1") + body
    date = datetime.fromtimestamp(ts, UTC).strftime("%Y-%m-%dT%H:%M:%SZ")
    head = f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Record-ID: {record_id}\r\nWARC-Target-URI: {url}\r\nWARC-Date: {date}\r\nContent-Type: application/http\r\nContent-Length: {len(http)}\r\n\r\n"
    return head.encode() + http + b"\r\n\r\n"


def captures_of_pages(pages: DataFrame, lag: int = 1000) -> DataFrame:
    """A crawl log over `pages`: each page is fetched at second page_id and asked again `lag` seconds later, every tenth
    page (by id) `lag` seconds before it was fetched. Tags are digests of the page; every second revisit sends a weak one."""
    tag = F.concat(F.lit('"'), F.md5(F.coalesce("html", F.lit(""))), F.lit('"'))
    fetched = pages.select(
        (F.col("page_id") * 2).alias("record_id"), "url", F.col("page_id").alias("ts"), F.lit(200).alias("status"),
        F.create_map(F.lit("ETag"), tag, F.lit("Content-Type"), F.lit("text/html"), F.lit("Cache-Control"), F.lit("max-age=60"), F.lit("Date"), F.col("page_id").cast("string")).alias("headers"),
        F.md5(F.coalesce("html", F.lit(""))).alias("digest"), F.length(F.coalesce("html", F.lit(""))).cast("long").alias("size"))
    late = F.when(F.col("page_id") % 10 == 0, -lag).otherwise(lag)
    sent = F.when(F.col("page_id") % 2 == 1, F.concat(F.lit("W/"), tag)).otherwise(tag)
    asked = pages.select(
        (F.col("page_id") * 2 + 1).alias("record_id"), "url", (F.col("page_id") + late).alias("ts"), F.lit(304).alias("status"),
        F.create_map(F.lit("ETag"), sent, F.lit("Cache-Control"), F.lit("max-age=90"), F.lit("Content-Type"), F.lit("text/plain"), F.lit("Date"), (F.col("page_id") + late).cast("string")).alias("headers"),
        F.lit(None).cast("string").alias("digest"), F.lit(None).cast("long").alias("size"))
    return fetched.unionByName(asked)


def op8_revisit_resolution(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = resolve(captures_of_pages(common.table(spark, sf_dir, "pages")))
    header = lambda k: F.element_at("headers", k)
    return done.select(
        F.expr("revisit_id div 2").alias("page_id"), F.expr("response_id div 2").alias("response_page_id"), "url_key", "ts", "response_ts", "outcome",
        header("content-type").alias("content_type"), header("cache-control").alias("cache_control"), header("date").alias("sent"), header("etag").alias("etag"), "digest", "size")


ORACLE = """
WITH u AS (
  SELECT page_id, html, regexp_replace(regexp_replace(trim(url), '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '') AS bare FROM pages
), k AS (
  SELECT page_id, md5(coalesce(html, '')) AS digest, length(coalesce(html, ''))::BIGINT AS size, bare, regexp_replace(bare, '[?].*$', '') AS path,
         list_sort(list_filter(string_split(CASE WHEN contains(bare, '?') THEN regexp_replace(bare, '^[^?]*[?]', '') ELSE '' END, '&'),
                   lambda p: p <> '' AND NOT regexp_matches(p, '%s'))) AS params
  FROM u
), c AS (
  SELECT page_id, digest, size, concat(
    regexp_replace(regexp_replace(lower(regexp_extract(path, '^[^/]*')), '^(.*@)?(www[.])?', ''), ':(80|443)$', ''),
    regexp_replace(regexp_replace(path, '^[^/]*', ''), '/+$', ''),
    CASE WHEN len(params) > 0 THEN '?' || array_to_string(params, '&') ELSE '' END) AS url_key,
    page_id + CASE WHEN page_id %% 10 = 0 THEN -1000 ELSE 1000 END AS asked
  FROM k
), j AS (
  SELECT r.page_id, r.url_key, r.asked AS ts, r.digest AS mine, f.page_id AS response_page_id, f.digest, f.size
  FROM c r LEFT JOIN c f ON f.url_key = r.url_key AND f.page_id < r.asked
  QUALIFY row_number() OVER (PARTITION BY r.page_id ORDER BY f.page_id DESC NULLS LAST) = 1
)
SELECT page_id, response_page_id, url_key, ts, response_page_id AS response_ts,
       CASE WHEN response_page_id IS NULL THEN 'no_response' WHEN mine = digest THEN 'resolved' ELSE 'validator_mismatch' END AS outcome,
       CASE WHEN mine = digest THEN 'text/html' END AS content_type,
       CASE WHEN mine = digest THEN 'max-age=90' END AS cache_control,
       CASE WHEN mine = digest THEN ts::VARCHAR END AS sent,
       CASE WHEN mine = digest THEN CASE WHEN page_id %% 2 = 1 THEN 'W/' ELSE '' END || '"' || mine || '"' END AS etag,
       CASE WHEN mine = digest THEN digest END AS digest,
       CASE WHEN mine = digest THEN size END AS size
FROM j
""" % TRACKING
