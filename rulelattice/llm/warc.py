"""Web archive records: resolving not-modified revisits by an as-of join.

A revisit stands for a capture that the server answered with "not modified". It is joined by
canonical URL to the latest full response captured strictly earlier; the validators of both are
compared, and where they agree the record gets the response's payload and its headers, overridden by
those that a not-modified answer may carry.

The as-of join never brings a URL's whole history together: records are dealt by URL and time
bucket, each bucket looks back within itself, and what it must inherit comes from a short table with
the last response of every (URL, bucket). A hot URL is thus spread over its buckets.

Edge cases: records with a null or blank URL or a null time are never matched (``no_response``); at equal times the
larger record id is the later response, and a response at the revisit's own time is not earlier; null
validators are absent ones, and a revisit without any validator in common is ``unchecked``; null
header maps count as empty, and of header names that differ in case only the last in byte order
counts; repeated rows are resolved each; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rulelattice.llm.common import SPACE, let

#: Headers that a not-modified answer may update.
PERMITTED = ["cache-control", "content-location", "date", "etag", "expires", "vary"]
#: Fixed value: query parameters that do not change the page.
TRACKING = r"^(utm_[a-z]+|ref|fbclid|gclid|sessionid)(=|$)"

RECORD = "record_id long, kind string, url string, ts long, etag string, last_modified string, headers map<string,string>, payload_digest string"


def canonical_url(url: Column) -> Column:
    """Host without case, ``www.`` and default port, path without last slashes, sorted query without tracking.

    A URL without ``scheme://`` and a host keeps its own text, trimmed and without the fragment, after a colon,
    so that it matches its like only; a blank one is null, which never matches.
    """
    trimmed = F.regexp_replace(url, f"^[{SPACE}]+|[{SPACE}]+$", "")

    def key(u: Column) -> Column:
        host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(u, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1)), r"^www\.", ""), ":(80|443)$", "")
        path = F.regexp_replace(F.regexp_extract(u, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)", 1), "/+$", "")
        asked = F.array_sort(F.filter(F.split(F.regexp_extract(u, r"^[^?#]*\?([^#]*)", 1), "&"), lambda p: (p != "") & ~F.rlike(p, F.lit(TRACKING))))
        whole = F.concat(host, path, F.when(F.size(asked) > 0, F.concat(F.lit("?"), F.array_join(asked, "&"))).otherwise(F.lit("")))
        other = F.concat(F.lit(":"), F.regexp_extract(u, "^[^#]*", 0))
        return F.when(host != "", whole).when(u != "", other)

    return let(trimmed, key)


def weakened(etag: Column) -> Column:
    return F.regexp_replace(etag, "^W/", "")


def asof_latest(events: DataFrame, key: str, ts: str, order_id: str, value: str, width: int) -> DataFrame:
    """Adds ``_found``: the last non-null ``value`` of the key at a strictly earlier time.

    ``width`` is the time span of a bucket; a key's records of one bucket are sorted in one task.
    """
    rows = events.withColumn("_bucket", F.floor(F.col(ts) / width).cast("long"))
    held = rows.where(F.col(value).isNotNull() & F.col(key).isNotNull() & F.col(ts).isNotNull())
    last = held.groupBy(key, "_bucket").agg(F.max_by(F.col(value), F.struct(F.col(ts), F.col(order_id))).alias("_last"))
    buckets = rows.where(F.col(key).isNotNull() & F.col(ts).isNotNull()).groupBy(key, "_bucket").agg(F.lit(1).alias("_one")).drop("_one")
    known = buckets.join(last, [key, "_bucket"], "left")
    before = Window.partitionBy(key).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = known.select(key, "_bucket", F.last("_last", ignorenulls=True).over(before).alias("_carried"))
    within = Window.partitionBy(key, "_bucket").orderBy(ts, F.col(value).isNotNull(), order_id).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    # The window runs over each (key, time) step: records of one time see only earlier ones.
    local = rows.where(F.col(key).isNotNull() & F.col(ts).isNotNull()).withColumn("_local", F.when(F.col(value).isNull(), F.last(value, ignorenulls=True).over(within)))
    joined = local.join(carried, [key, "_bucket"], "left").withColumn("_found", F.coalesce("_local", "_carried")).drop("_local", "_carried", "_bucket")
    unmatched = rows.where(F.col(key).isNull() | F.col(ts).isNull()).drop("_bucket").withColumn("_found", F.lit(None).cast(events.schema[value].dataType))
    return joined.unionByName(unmatched)


def lowered_names(headers: Column) -> Column:
    """Headers under lower-case names; of names that differ in case only, the last in byte order stays."""
    entries = F.map_entries(headers)

    def one_of_each(es: Column) -> Column:
        stay = F.filter(es, lambda e: ~F.exists(es, lambda x: (F.lower(x["key"]) == F.lower(e["key"])) & (x["key"] > e["key"])))
        return F.map_from_entries(F.transform(stay, lambda e: F.struct(F.lower(e["key"]).alias("key"), e["value"].alias("value"))))

    return let(entries, one_of_each)


def resolve_revisits(records: DataFrame, width: int = 86_400) -> DataFrame:
    """One row per revisit: ``status``, the response used, its payload digest and the merged headers."""
    shaped = records.select(
        "record_id", F.lower("kind").alias("kind"), canonical_url(F.col("url")).alias("url_key"), "ts", weakened(F.col("etag")).alias("etag"), "last_modified",
        F.coalesce(lowered_names(F.col("headers")), F.create_map().cast("map<string,string>")).alias("headers"), "payload_digest",
    )
    full = F.when(F.col("kind") == "response", F.struct(F.col("record_id").alias("id"), "etag", "last_modified", "headers", "payload_digest"))
    found = asof_latest(shaped.withColumn("_full", full), "url_key", "ts", "record_id", "_full", width).where("kind = 'revisit'")
    r = F.col("_found")
    same = lambda c: r[c] == F.col(c)  # noqa: E731  null where one has none
    agreed = F.coalesce(same("etag"), same("last_modified"), same("payload_digest"))
    status = F.when(r.isNull(), "no_response").when(agreed.isNull(), "unchecked").when(agreed, "resolved").otherwise("changed")
    update = F.map_filter("headers", lambda k, v: k.isin(PERMITTED))
    merged = F.map_concat(F.map_filter(r["headers"], lambda k, v: ~F.array_contains(F.map_keys(update), k)), update)
    usable = F.col("status").isin("resolved", "unchecked")
    return found.withColumn("status", status).select(
        "record_id", "url_key", "status", r["id"].alias("response_id"), F.when(usable, r["payload_digest"]).alias("payload_digest"), F.when(usable, merged).alias("headers")
    )


def records_of_pages(pages: DataFrame, step: int = 60, later: int = 1000) -> DataFrame:
    """Archive records that a crawl of ``pages`` leaves: a full response for every page, and ``later``
    steps after it a revisit that carries the page's validator."""
    digest = F.md5(F.coalesce("html", F.lit("")))
    etag = F.concat(F.lit('"'), digest, F.lit('"'))

    def record(kind: str, at: Column, ident: Column, tag: Column, headers: Column, body: Column) -> Column:
        return F.struct(ident.alias("record_id"), F.lit(kind).alias("kind"), F.col("url"), at.alias("ts"), tag.alias("etag"), F.lit(None).cast("string").alias("last_modified"), headers.alias("headers"), body.alias("payload_digest"))

    first, again = F.col("page_id") * step, (F.col("page_id") + later) * step + F.lit(step // 2)
    response = record("response", first, F.col("page_id") * 2, etag, F.create_map(F.lit("Content-Type"), F.lit("text/html"), F.lit("ETag"), etag, F.lit("Date"), first.cast("string")), digest)
    revisit = record("revisit", again, F.col("page_id") * 2 + 1, F.concat(F.lit("W/"), etag), F.create_map(F.lit("Date"), again.cast("string"), F.lit("Content-Length"), F.lit("0")), F.lit(None).cast("string"))
    return pages.select(F.explode(F.array(response, revisit)).alias("r")).select("r.*")


def parse_archive(data: bytes) -> Iterator[dict]:
    """Records of an uncompressed archive file: header lines, an empty line, a counted body."""
    at = 0
    while at < len(data):
        start = data.find(b"WARC/", at)
        if start < 0:
            return
        end = data.find(b"\r\n\r\n", start)
        if end < 0:
            return
        fields = {}
        for line in data[start:end].decode("utf-8", "replace").split("\r\n")[1:]:
            name, _, value = line.partition(":")
            fields[name.strip().lower()] = value.strip()
        size = int(fields.get("content-length") or 0)
        yield {"fields": fields, "body": data[end + 4 : end + 4 + size]}
        at = end + 4 + size


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Records of archive files (one file a task): warc type, URL, date, fields and HTTP body."""
    import gzip

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for name, data in zip(pdf["path"], pdf["content"], strict=True):
                raw = gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
                got = list(parse_archive(bytes(raw)))
                yield pd.DataFrame(
                    {"path": [name] * len(got), "kind": [r["fields"].get("warc-type") for r in got], "url": [r["fields"].get("warc-target-uri") for r in got], "date": [r["fields"].get("warc-date") for r in got], "fields": [r["fields"] for r in got], "body": [r["body"] for r in got]}
                )

    shape = "path string, kind string, url string, date string, fields map<string,string>, body binary"
    return spark.read.format("binaryFile").load(path).select("path", "content").mapInPandas(rows, shape)
