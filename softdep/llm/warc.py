"""Not-modified revisits of web captures, resolved to the full response they stand for.

A revisit (status 304, no body) is joined as of its time to the latest earlier full response of the same canonical URL.
The join sorts no URL's whole history in one task: captures are dealt by URL and time bucket; inside a bucket a window
carries the last response forward, and a second window over one row per URL and bucket carries the last response of
earlier buckets. So a URL with a third of all captures is spread over its buckets. Bodies take no part: only capture ids
and validators move, and the body is fetched by the resolved id.

Validators: if both sides have an ETag, these must agree by weak comparison (RFC 9110), and nothing else counts; else if
both have a Last-Modified, these must agree; else the revisit is taken to fit ("unvalidated"). A 304 may update only the
header fields in PERMITTED; all others come from the stored response.

Edge cases. A response at the same instant is not earlier; among equal instants the greatest id is latest. A null URL or
time is never resolved (no_prior). Null headers are empty maps; names are compared in lower case, and of names that differ
in case only the last in order counts. Repeated rows are resolved alike. Very long URLs and headers are kept whole. Only the
five columns named below are read, so others cannot clash. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Fields that a 304 response may carry to update the stored response.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "vary")


def canonical(url: Column) -> Column:
    """Scheme and www. dropped, host in lower case, default port, fragment and trailing slash removed; null without ://."""
    rest = F.regexp_replace(F.substring(url, F.instr(url, "://") + 3, F.length(url)), "#.*$", "")
    host = F.lower(F.regexp_extract(rest, "^([^/?]*)", 1))
    host = F.regexp_replace(F.regexp_replace(host, "^www\\.", ""), ":(80|443)$", "")
    tail = F.regexp_replace(F.regexp_extract(rest, "^[^/?]*(.*)$", 1), "/+(?=\\?|$)", "")
    return F.when(F.instr(url, "://") > 0, F.concat(host, tail))


def lowered(headers: Column) -> Column:
    """headers with names in lower case; null is empty."""
    entries = F.array_sort(F.map_entries(F.coalesce(headers, F.create_map().cast("map<string,string>"))))
    names = F.array_distinct(F.transform(entries, lambda e: F.lower(e["key"])))
    return F.map_from_arrays(names, F.transform(names, lambda n: F.element_at(F.filter(entries, lambda e: F.lower(e["key"]) == n), -1)["value"]))


def same_etag(a: Column, b: Column) -> Column:
    weak = lambda x: F.regexp_replace(F.trim(x), "^W/", "")
    return weak(a) == weak(b)


def resolved(captures: DataFrame, bucket_seconds: int = 86400) -> DataFrame:
    """Each revisit of captures(id, url, ts, status, headers) with outcome, response_id, response_ts and merged headers.

    outcome: etag, last_modified or unvalidated where it is resolved; mismatch or no_prior, with null response columns,
    where it is not. Full responses are the rows of status 200.
    """
    c = captures.select("id", canonical(F.col("url")).alias("url_key"), F.col("ts").cast("timestamp").alias("ts"), "status", lowered(F.col("headers")).alias("h"))
    slot = F.floor(F.unix_micros(F.col("ts")) / (bucket_seconds * 1_000_000)).alias("slot")
    is_full, is_304 = F.col("status") == 200, F.col("status") == 304
    full = F.struct("ts", "id", F.col("h")["etag"].alias("etag"), F.col("h")["last-modified"].alias("modified"))
    moved = c.where((is_full | is_304) & F.col("url_key").isNotNull() & F.col("ts").isNotNull())
    slim = moved.select("id", "url_key", "ts", slot, is_304.alias("again"), F.when(is_full, full).alias("full"), F.when(is_304, F.struct(F.col("h")["etag"].alias("etag"), F.col("h")["last-modified"].alias("modified"))).alias("own"))
    lasts = slim.where("full is not null").groupBy("url_key", "slot").agg(F.max("full").alias("slot_last"))
    slots = slim.select("url_key", "slot").distinct().join(lasts, ["url_key", "slot"], "left")
    before = Window.partitionBy("url_key").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    carried = slots.withColumn("carried", F.last("slot_last", ignorenulls=True).over(before)).select("url_key", "slot", "carried")
    # Strictly earlier instants: the frame in range ends one microsecond before the row.
    inside = Window.partitionBy("url_key", "slot").orderBy("micros").rangeBetween(Window.unboundedPreceding, -1)
    near = slim.withColumn("micros", F.unix_micros("ts")).withColumn("near", F.max("full").over(inside)).where("again").join(carried, ["url_key", "slot"], "left")
    prior = F.coalesce("near", "carried")
    found = near.select("id", "own", prior.alias("prior"))
    by_tag = F.col("own.etag").isNotNull() & F.col("prior.etag").isNotNull()
    by_date = F.col("own.modified").isNotNull() & F.col("prior.modified").isNotNull()
    outcome = (
        F.when(F.col("prior").isNull(), "no_prior")
        .when(by_tag, F.when(same_etag(F.col("own.etag"), F.col("prior.etag")), "etag").otherwise("mismatch"))
        .when(by_date, F.when(F.col("own.modified") == F.col("prior.modified"), "last_modified").otherwise("mismatch"))
        .otherwise("unvalidated")
    )
    fits = ~F.col("outcome").isin("no_prior", "mismatch")
    judged = found.select("id", outcome.alias("outcome"), "prior").select("id", "outcome", F.when(fits, F.col("prior.id")).alias("response_id"), F.when(fits, F.col("prior.ts")).alias("response_ts")).distinct()
    stored = c.where(is_full).select(F.col("id").alias("response_id"), F.col("h").alias("stored")).dropDuplicates(["response_id"])
    revisits = c.where(is_304).select("id", "url_key", "ts", "h")
    out = revisits.join(judged, "id", "left").withColumn("outcome", F.coalesce("outcome", F.lit("no_prior")))
    # Unresolved rows join on ids of their own that no response has, so that nulls do not meet in one task.
    none = F.struct(F.lit(False).alias("is"), F.col("id").alias("v"))
    some = F.struct(F.lit(True).alias("is"), F.col("response_id").alias("v"))
    out = out.withColumn("__k", F.when(F.col("response_id").isNull(), none).otherwise(some)).join(stored.select(some.alias("__k"), "stored"), "__k", "left").drop("__k")
    update = F.map_filter("h", lambda k, _: k.isin(*PERMITTED))
    merged = F.map_concat(F.map_filter("stored", lambda k, _: ~F.map_contains_key(update, k)), update)
    return out.select("id", "url_key", "ts", "outcome", "response_id", "response_ts", F.when(F.col("response_id").isNotNull(), merged).alias("headers"))


def with_bodies(revisits: DataFrame, captures: DataFrame) -> DataFrame:
    """revisits with the body of the response each was resolved to."""
    return revisits.join(captures.where("status = 200").select(F.col("id").alias("response_id"), "body").dropDuplicates(["response_id"]), "response_id", "left")
