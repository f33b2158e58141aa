"""Not-modified revisit records of web archives, resolved against the latest earlier full response of the same canonical URL.

An as-of join in DataFrame operations. Records are keyed by (canonical URL, slice of time): within a slice a window finds the last
response before each revisit, and the slices' last responses, aggregated before they are shuffled, are carried on from slice to slice. So a URL
that holds a third of all records is dealt to as many tasks as there are slices.

Earlier means smaller (captured_at, record_id). Statuses: resolved (the first validator that both sides have agrees: payload digest, then ETag
by weak comparison, then Last-Modified), mismatch (it differs), unvalidated (no validator in common), unresolved (no earlier response, or a
null URL or time). Headers are merged only if resolved: the stored ones, with those in PERMITTED taken from the revisit.

Defined results: a null header map counts as empty, header names are compared in lower case (of names that differ in case alone the first in
order counts); repeated records are resolved one by one; an empty table gives an empty result; other columns of the revisits are not returned.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load

#: Headers that a 304 answer may update.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "last-modified", "vary")
#: Query parameters that do not select content.
TRACKING = "^(utm_[a-z]+|fbclid|gclid|sessionid)(=|$)"
SLICES = 64


def canonical_url(url: Column) -> Column:
    """Scheme, user, leading www, default port, fragment, tracking parameters and trailing slashes go; host in lower case; parameters sorted."""
    bare = F.regexp_replace(F.regexp_replace(F.trim(url), "#.*$", ""), "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    path = F.regexp_extract(bare, r"^([^?]*)", 1)
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(path, r"^(?:[^/@]*@)?([^/]*)", 1)), "^www[0-9]*[.]", ""), ":(80|443)$", "")
    rest = F.regexp_replace(F.regexp_extract(path, r"^[^/]*(/.*)$", 1), "/+$", "")
    query = F.regexp_extract(bare, r"[?](.*)$", 1)
    kept = F.array_join(F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~F.lower(p).rlike(TRACKING))), "&")
    return F.concat(host, rest, F.when(kept != "", F.concat(F.lit("?"), kept)).otherwise(""))


def lower_names(headers: Column) -> Column:
    """The map with names in lower case; the first in order counts."""
    entries = F.array_sort(F.transform(F.map_entries(headers), lambda e: F.struct(F.lower(e["key"]).alias("key"), e["value"].alias("value"))))
    firsts = F.filter(entries, lambda e, i: (i == 0) | (F.get(entries, i - 1)["key"] != e["key"]))
    return F.coalesce(F.map_from_entries(firsts), F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<string>")))


def resolve(records: DataFrame, slices: int = SLICES) -> DataFrame:
    """records: record_id, record_type (response or revisit), url, captured_at (numeric), headers map<string,string>, payload_digest.

    Returns a row for each revisit: record_id, canonical_url, captured_at, status, refers_to, payload_digest, headers.
    """
    keyed = records.select(
        "record_id",
        (F.col("record_type") == "response").alias("full"),
        canonical_url(F.col("url")).alias("k"),
        F.col("captured_at").alias("t"),
        lower_names(F.col("headers")).alias("h"),
        F.col("payload_digest").alias("d"),
    ).where(F.col("full") | (records["record_type"] == "revisit"))
    usable = keyed.where("k IS NOT NULL AND t IS NOT NULL")
    cuts = usable.select(F.percentile_approx("t", [i / slices for i in range(1, slices)], 1000)).first()[0] or []
    marks = F.array(*[F.lit(c) for c in sorted(set(cuts))]) if cuts else F.array().cast("array<bigint>")
    usable = usable.withColumn("s", F.size(F.filter(marks, lambda c: c <= F.col("t"))))
    response = F.when(F.col("full"), F.struct("record_id", "h", "d"))
    order = Window.partitionBy("k", "s").orderBy("t", "record_id", F.desc("full"))
    inside = usable.withColumn("near", F.last(response, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1))).where("NOT full")
    ends = usable.groupBy("k", "s").agg(F.max_by(response, F.when(F.col("full"), F.struct("t", "record_id"))).alias("end"))
    carried = ends.withColumn("carry", F.last("end", ignorenulls=True).over(Window.partitionBy("k").orderBy("s").rowsBetween(Window.unboundedPreceding, -1))).select("k", "s", "carry").where("carry IS NOT NULL")
    found = inside.join(carried, ["k", "s"], "left").withColumn("r", F.coalesce("near", "carry")).drop("near", "carry", "s", "full")
    lost = keyed.where("NOT full AND (k IS NULL OR t IS NULL)").drop("full")
    found = found.unionByName(lost, allowMissingColumns=True)
    weak = lambda c: F.regexp_replace(c, "^W/", "")
    checks = [(F.col("d"), F.col("r.d")), (weak(F.col("h")["etag"]), weak(F.col("r.h")["etag"])), (F.col("h")["last-modified"], F.col("r.h")["last-modified"])]
    agrees = F.coalesce(*[F.when(a.isNotNull() & b.isNotNull(), a == b) for a, b in checks])
    status = F.when(F.col("r").isNull(), "unresolved").when(agrees.isNull(), "unvalidated").when(agrees, "resolved").otherwise("mismatch")
    found = found.withColumn("status", status)
    own = F.map_filter("h", lambda k, v: k.isin(*PERMITTED))
    stored = F.map_filter("r.h", lambda k, v: ~F.map_contains_key(own, k))
    return found.select(
        "record_id",
        F.col("k").alias("canonical_url"),
        F.col("t").alias("captured_at"),
        "status",
        F.col("r.record_id").alias("refers_to"),
        F.when(F.col("status") == "resolved", F.col("r.d")).alias("payload_digest"),
        F.when(F.col("status") == "resolved", F.map_concat(stored, own)).alias("headers"),
    )


def page_records(pages: DataFrame) -> DataFrame:
    """A crawl made of the pages: each is a full response at time page_id, and is asked for again with an answer of not modified.

    The second request comes 1000 ticks later, or 1 tick before the page for every 7th (then an older capture of its URL counts); every 5th has
    a validator of some other version.
    """
    etag = F.concat(F.lit('"'), F.substring(F.md5("html"), 1, 16), F.lit('"'))
    full = pages.select(
        (F.col("page_id") * 2).alias("record_id"),
        F.lit("response").alias("record_type"),
        "url",
        F.col("page_id").alias("captured_at"),
        F.create_map(F.lit("ETag"), etag, F.lit("Content-Type"), F.lit("text/html"), F.lit("Cache-Control"), F.lit("max-age=60"), F.lit("Date"), F.col("page_id").cast("string")).alias("headers"),
        F.sha1("html").alias("payload_digest"),
    )
    again = F.when(F.col("page_id") % 7 == 0, F.col("page_id") - 1).otherwise(F.col("page_id") + 1000)
    part = pages.select(
        (F.col("page_id") * 2 + 1).alias("record_id"),
        F.lit("revisit").alias("record_type"),
        F.concat("url", F.lit("#again")).alias("url"),
        again.alias("captured_at"),
        F.create_map(
            F.lit("etag"), F.when(F.col("page_id") % 5 == 0, F.lit('"other"')).otherwise(F.concat(F.lit("W/"), etag)), F.lit("content-type"), F.lit("text/plain"), F.lit("cache-control"), F.lit("max-age=120"), F.lit("date"), again.cast("string")
        ).alias("headers"),
        F.lit(None).cast("string").alias("payload_digest"),
    )
    return full.unionByName(part)


def op4_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = resolve(page_records(load(spark, sf_dir, "pages").select("page_id", "url", "html")))
    listed = F.array_join(F.transform(F.array_sort(F.map_entries("headers")), lambda e: F.concat(e["key"], F.lit(": "), e["value"])), "\n")
    return done.withColumn("headers", listed)


OP4_SQL = r"""
WITH p AS (SELECT page_id, html, regexp_replace(regexp_replace(trim(url), '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '') AS bare FROM pages),
c AS (SELECT page_id, html, regexp_replace(regexp_replace(lower(regexp_extract(bare, '^(?:[^/?@]*@)?([^/?]*)', 1)), '^www[0-9]*[.]', ''), ':(80|443)$', '') AS host,
             regexp_replace(regexp_extract(bare, '^[^/?]*(/[^?]*)', 1), '/+$', '') AS rest,
             array_to_string(list_sort(list_filter(string_split(regexp_extract(bare, '[?](.*)$', 1), '&'), lambda x: x <> '' AND NOT regexp_matches(lower(x), '^(utm_[a-z]+|fbclid|gclid|sessionid)(=|$)'))), '&') AS q FROM p),
k AS (SELECT page_id, host || rest || CASE WHEN q <> '' THEN '?' || q ELSE '' END AS k, sha1(html) AS d, '"' || substr(md5(html), 1, 16) || '"' AS etag FROM c),
v AS (SELECT page_id * 2 + 1 AS record_id, k, CASE WHEN page_id % 7 = 0 THEN page_id - 1 ELSE page_id + 1000 END AS t, CASE WHEN page_id % 5 = 0 THEN '"other"' ELSE etag END AS etag FROM k),
j AS (SELECT v.record_id, max(r.page_id) AS page FROM v JOIN k r ON r.k = v.k AND (r.page_id < v.t OR (r.page_id = v.t AND r.page_id * 2 < v.record_id)) GROUP BY 1),
f AS (SELECT v.*, r.page_id AS page, r.d, r.etag AS old, CASE WHEN r.page_id IS NULL THEN 'unresolved' WHEN r.etag = v.etag THEN 'resolved' ELSE 'mismatch' END AS status
      FROM v LEFT JOIN j ON j.record_id = v.record_id LEFT JOIN k r ON r.page_id = j.page)
SELECT record_id, k AS canonical_url, t AS captured_at, status, page * 2 AS refers_to, CASE WHEN status = 'resolved' THEN d END AS payload_digest,
       CASE WHEN status = 'resolved' THEN 'cache-control: max-age=120' || chr(10) || 'content-type: text/html' || chr(10) || 'date: ' || t || chr(10) || 'etag: ' || CASE WHEN record_id % 10 = 1 THEN old ELSE 'W/' || etag END END AS headers
FROM f
"""
