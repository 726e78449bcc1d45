"""Not-modified revisits of web archives, resolved to the response that they stand for.

A revisit record says that a page had not changed since an earlier capture. It is
resolved by an as-of join: the latest full response of the same canonical URL that
is strictly earlier. The join holds if validators agree (entity tags by weak
comparison, else the modification dates, else payload digests). The resolved record
has the response's headers, overlaid with those that a not-modified answer may
change; length, coding and type always stay the response's.

A hot URL is split by time: inside each of ``slices`` spans the last response is carried
forward by a window, and one row per URL and span (at most ``slices`` for a URL) carries
it on to later spans. Spans hold about as many records each (their bounds are quantiles
of all times), so a window holds about 1 / ``slices`` of all records at most, unless more
were captured at one and the same time.

Defined results: rows without URL or time are ``no_original``, since they have no
earlier response; of responses at the same time the one with the largest id counts
as the latest; repeated revisit rows are resolved each; missing headers are empty;
an empty table gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Headers that a not-modified answer may change. Fixed values.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "set-cookie", "vary")


def canonical_url(url: Column) -> Column:
    """Host in lower case without www, default port and scheme; no fragment, tracking parameters or last slash; parameters sorted."""
    bare = F.regexp_replace(F.regexp_replace(url, "#.*$", ""), "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(bare, "^[^/?]*", 0)), ":(80|443)$", ""), r"^www[0-9]*\.", "")
    path = F.regexp_replace(F.regexp_extract(bare, r"^[^/?]*([^?]*)", 1), "/+$", "")
    given = F.split(F.regexp_extract(bare, r"\?(.*)$", 1), "&")
    kept = F.array_sort(F.filter(given, lambda p: (p != "") & ~p.rlike("^(utm_[a-z]+|ref)=")))
    query = F.array_join(kept, "&")
    return F.concat(host, path, F.when(query != "", F.concat(F.lit("?"), query)).otherwise(""))


def _weak(tag: Column) -> Column:
    return F.regexp_replace(tag, "^W/", "")


def resolve_revisits(records: DataFrame, slices: int = 64, permitted: tuple[str, ...] = PERMITTED) -> DataFrame:
    """records: record_id, url, ts (long), kind (response or revisit), etag, last_modified, digest, headers (map).

    One row per revisit: record_id, canonical_url, ts, original_id, original_ts, status, headers.
    """
    # bounds by rank, not by time, so that a burst of captures falls into many slices
    shares = [i / slices for i in range(1, slices)]
    bounds = records.agg(F.percentile_approx("ts", shares, 100 * slices)).first()[0] if shares else []
    bounds = sorted(set(bounds or []))
    here_slice = F.size(F.filter(F.lit(bounds), lambda x: x < F.col("ts"))) if bounds else F.lit(0)
    full = F.col("kind") == "response"
    original = F.struct(F.col("ts").alias("ts"), F.col("record_id").alias("id"), "etag", "last_modified", "digest", "headers")
    known = records.select("record_id", "ts", "kind", "etag", "last_modified", "digest", "headers", canonical_url(F.col("url")).alias("u"))
    rows = known.select(
        "record_id", "u", "ts", "etag", "last_modified", "digest", "headers", full.alias("full"),
        here_slice.alias("slice"), F.when(full & F.col("u").isNotNull() & F.col("ts").isNotNull(), original).alias("o"),
    )
    # revisits come before responses of the same time, which are not earlier
    here = Window.partitionBy("u", "slice").orderBy("ts", "full", "record_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    near = rows.withColumn("near", F.last("o", ignorenulls=True).over(here)).filter(~F.col("full"))
    ends = rows.filter("u is not null and ts is not null").groupBy("u", "slice").agg(F.max_by("o", F.when(F.col("full"), F.struct("ts", "record_id"))).alias("o"))
    before = Window.partitionBy("u").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select("u", "slice", F.last("o", ignorenulls=True).over(before).alias("far"))
    found = near.join(carried, ["u", "slice"], "left").withColumn("best", F.coalesce("near", "far"))
    best = F.col("best")
    agrees = F.when(
        F.col("etag").isNotNull() & best["etag"].isNotNull(), _weak(F.col("etag")) == _weak(best["etag"])
    ).when(F.col("last_modified").isNotNull() & best["last_modified"].isNotNull(), F.col("last_modified") == best["last_modified"]).when(
        F.col("digest").isNotNull() & best["digest"].isNotNull(), F.col("digest") == best["digest"]
    )
    status = F.when(best.isNull(), "no_original").when(agrees.isNull(), "unverified").when(agrees, "resolved").otherwise("mismatch")
    none = F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<string>"))
    news = F.map_filter(F.coalesce("headers", none), lambda k, v: F.lower(k).isin(*permitted))
    kept = F.map_filter(F.coalesce(best["headers"], none), lambda k, v: ~F.array_contains(F.transform(F.map_keys(news), F.lower), F.lower(k)))
    merged = F.when(status == "resolved", F.map_concat(kept, news))
    return found.select("record_id", F.col("u").alias("canonical_url"), "ts", best["id"].alias("original_id"), best["ts"].alias("original_ts"), status.alias("status"), merged.alias("headers"))


def records_of_pages(pages: DataFrame, later: int = 1000) -> DataFrame:
    """Captures for a table of pages: a response for each page, and a revisit ``later`` on.

    Of every eleventh page the revisit comes just before the response, as if the first
    capture were lost. Entity tags and digests are of the page's content.
    """
    digest = F.md5(F.coalesce("html", F.lit("")).cast("binary"))
    base = pages.select("page_id", "url", digest.alias("digest"), F.length(F.coalesce("html", F.lit(""))).cast("string").alias("n"))
    first = base.select(
        (F.col("page_id") * 2).alias("record_id"), "url", (F.col("page_id") * 2).alias("ts"), F.lit("response").alias("kind"), "digest",
        F.create_map(F.lit("content-type"), F.lit("text/html"), F.lit("content-length"), F.col("n"), F.lit("etag"), F.col("digest"), F.lit("cache-control"), F.lit("max-age=60"), F.lit("date"), (F.col("page_id") * 2).cast("string")).alias("headers"),
    )
    when = F.when(F.col("page_id") % 11 == 0, F.col("page_id") * 2 - 1).otherwise(F.col("page_id") * 2 + later * 2 + 1)
    again = base.select(
        (F.col("page_id") * 2 + 1).alias("record_id"), "url", when.alias("ts"), F.lit("revisit").alias("kind"), "digest",
        F.create_map(F.lit("content-length"), F.lit("0"), F.lit("cache-control"), F.lit("max-age=300"), F.lit("date"), when.cast("string")).alias("headers"),
    )
    both = first.unionByName(again)
    return both.select("record_id", "url", "ts", "kind", F.col("digest").alias("etag"), F.lit(None).cast("string").alias("last_modified"), "digest", "headers")
