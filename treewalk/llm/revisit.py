"""WARC: resolution of server-not-modified revisit records.

A revisit with status 304 stands for the latest earlier full response of the same canonical URL.
``resolve`` finds it by an as-of join, checks the validators the revisit carries (entity tag by
weak comparison, else the modification date) and merges the headers that a 304 may update into
the stored ones.  Only record ids, validators and headers move; bodies stay where they are.

The as-of join has two levels, so that no URL gathers in one task: within slices of ``WIDTH`` time
units the last response before each revisit is found by a window; where a slice has none, the
last response of the nearest earlier slice is taken from a summary with one row per URL and slice.

Defined cases: a revisit without URL or time, or without an earlier response, has verdict
``no_response``; one without validators ``no_validator`` (it resolves, with nothing to check);
unequal validators ``mismatch``, without a resolved id; responses at the same time are not earlier;
of several at one time the greatest id counts; repeated records are resolved each; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

WIDTH = 4096
#: Fixed list: header fields that a 304 must not change in the stored response.
KEPT = ("content-encoding", "content-length", "content-range", "content-type", "connection", "keep-alive", "te", "trailer", "transfer-encoding", "upgrade")


def canonical(url: Column) -> Column:
    """URL without scheme, fragment, default port, ``www.``, tracking parameters and final slashes,
    with its host in lower case."""
    bare = F.regexp_replace(F.regexp_replace(F.trim(url), "#.*$", ""), "^[a-zA-Z]+://", "")
    host = F.regexp_extract(bare, "^[^/?]*", 0)
    rest = F.regexp_replace(F.substring(bare, F.length(host) + 1, F.length(bare)), "[?&](utm_[a-z]+|ref)=[^&]*", "")
    amp = F.instr(rest, "&")
    rest = F.when((F.instr(rest, "?") == 0) & (amp > 0), F.concat(F.substring(rest, F.lit(1), amp - 1), F.lit("?"), F.substring(rest, amp + 1, F.length(rest)))).otherwise(rest)
    host = F.regexp_replace(F.regexp_replace(F.lower(host), ":(80|443)$", ""), "^www[.]", "")
    return F.concat(host, F.regexp_replace(rest, "/+$", ""))


def _bare_tag(tag: Column) -> Column:
    return F.regexp_replace(tag, "^W/", "")


def resolve(records: DataFrame, width: int = WIDTH) -> DataFrame:
    """``records (record_id, record_type, url, ts, status, etag, last_modified, headers)`` to one row
    for each not-modified revisit: ``(record_id, canonical_url, resolved_id, verdict, headers)``."""
    r = records.select("record_id", "record_type", canonical(F.col("url")).alias("url"), "ts", "status", "etag", "last_modified", "headers").withColumn("slice", F.floor(F.col("ts") / width))
    revisit = (F.col("record_type") == "revisit") & (F.col("status") == 304)
    full = (F.col("record_type") == "response") & (F.col("status") == 200) & F.col("url").isNotNull() & F.col("ts").isNotNull()
    found = F.struct(F.col("record_id").alias("id"), "etag", "last_modified", "headers")
    both = r.where(revisit | full).withColumn("is_revisit", revisit).withColumn("stored", F.when(full, found))
    placed = both.where(F.col("url").isNotNull() & F.col("ts").isNotNull())
    # at one time revisits come first, so that only earlier responses are seen
    before = Window.partitionBy("url", "slice").orderBy("ts", F.desc("is_revisit"), "record_id").rowsBetween(Window.unboundedPreceding, -1)
    near = placed.withColumn("near", F.last("stored", ignorenulls=True).over(before)).where("is_revisit").select("record_id", "url", "slice", "etag", "last_modified", "headers", "near")
    ends = placed.where(~F.col("is_revisit")).groupBy("url", "slice").agg(F.max_by("stored", F.struct("ts", "record_id")).alias("stored"))
    slices = ends.unionByName(placed.where("is_revisit").select("url", "slice").distinct(), allowMissingColumns=True).groupBy("url", "slice").agg(F.first("stored", ignorenulls=True).alias("stored"))
    earlier = Window.partitionBy("url").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    carried = slices.withColumn("carried", F.last("stored", ignorenulls=True).over(earlier)).where("carried is not null").select("url", "slice", "carried")
    seen = near.join(carried, ["url", "slice"], "left").withColumn("s", F.coalesce("near", "carried"))
    lost = both.where(F.col("is_revisit") & (F.col("url").isNull() | F.col("ts").isNull())).select("record_id", "url", "etag", "last_modified", "headers", F.col("stored").alias("s"))
    every = seen.select("record_id", "url", "etag", "last_modified", "headers", "s").unionByName(lost)
    s = F.col("s")
    agrees = F.when(F.col("etag").isNotNull(), F.coalesce(_bare_tag(F.col("etag")) == _bare_tag(s["etag"]), F.lit(False))).otherwise(F.coalesce(F.col("last_modified") == s["last_modified"], F.lit(False)))
    verdict = F.when(s.isNull(), "no_response").when(F.col("etag").isNull() & F.col("last_modified").isNull(), "no_validator").when(agrees, "match").otherwise("mismatch")
    mine = F.coalesce(F.col("headers"), F.create_map().cast("map<string,string>"))
    fresh = F.map_filter(mine, lambda k, v: ~k.isin(*KEPT))
    stored = F.coalesce(s["headers"], F.create_map().cast("map<string,string>"))
    merged = F.map_concat(F.map_filter(stored, lambda k, v: ~F.map_contains_key(fresh, k)), fresh)
    ok = F.col("verdict").isin("match", "no_validator")
    return every.withColumn("verdict", verdict).select("record_id", F.col("url").alias("canonical_url"), F.when(ok, s["id"]).alias("resolved_id"), "verdict", F.when(ok, merged).alias("headers"))


def header_lines(headers: Column) -> Column:
    """Header map as sorted ``name: value`` lines."""
    return F.array_join(F.transform(F.array_sort(F.map_keys(headers)), lambda k: F.concat(k, F.lit(": "), F.element_at(headers, k))), "\n")


def crawl(pages: DataFrame) -> DataFrame:
    """WARC records of two visits to every page: a full response, and later a 304 whose URL is
    written another way and whose validators are, by turns, its own, weak, a date only, stale or none."""
    h = lambda *kv: F.create_map(*[F.lit(x) if isinstance(x, str) else x for x in kv])
    p = pages.select(F.col("page_id").cast("long").alias("k"), "url", F.concat(F.lit('"'), F.substring(F.md5("html"), 1, 16), F.lit('"')).alias("tag"), F.length("html").alias("n"))
    day = F.concat(F.lit("day "), F.col("k") % 7)
    first = p.select((F.col("k") * 2).alias("record_id"), F.lit("response").alias("record_type"), "url", (F.col("k") * 10).alias("ts"), F.lit(200).alias("status"), F.col("tag").alias("etag"), day.alias("last_modified"), h("content-type", "text/html", "content-length", F.col("n").cast("string"), "etag", F.col("tag"), "last-modified", day, "server", "one").alias("headers"))
    turn = F.col("k") % 5
    tag = F.when(turn == 0, F.lit('"stale"')).when(turn == 2, F.concat(F.lit("W/"), F.col("tag"))).when(turn == 3, F.col("tag"))
    date = F.when(turn != 4, day)
    other = F.when(F.col("k") % 3 == 0, F.concat(F.col("url"), F.lit("#part"))).when(F.col("k") % 3 == 1, F.regexp_replace("url", "^https?://", "HTTP://")).otherwise(F.col("url"))
    later = p.select((F.col("k") * 2 + 1).alias("record_id"), F.lit("revisit").alias("record_type"), other.alias("url"), (F.col("k") * 10 + 170 + (F.col("k") % 50) * 1000).alias("ts"), F.lit(304).alias("status"), tag.alias("etag"), date.alias("last_modified"), h("content-length", "0", "date", F.concat(F.lit("visit "), F.col("k") % 11), "server", "two").alias("headers"))
    return first.unionByName(later)


def run(pages: DataFrame) -> DataFrame:
    done = resolve(crawl(pages))
    return done.select("record_id", "canonical_url", F.coalesce("resolved_id", F.lit(-1)).alias("resolved_id"), "verdict", header_lines(F.col("headers")).alias("headers"))


ORACLE = r"""
WITH p AS (SELECT page_id AS k, url, '"' || substr(md5(html), 1, 16) || '"' AS tag, length(html) AS n, 'day ' || (page_id % 7) AS day FROM pages),
rec AS (
  SELECT k * 2 AS record_id, 'response' AS kind, url, k * 10 AS ts, tag AS etag, day AS lm,
         NULL AS visit, n, k FROM p
  UNION ALL
  SELECT k * 2 + 1, 'revisit', CASE k % 3 WHEN 0 THEN url || '#part' WHEN 1 THEN regexp_replace(url, '^https?://', 'HTTP://') ELSE url END,
         k * 10 + 170 + (k % 50) * 1000, CASE k % 5 WHEN 0 THEN '"stale"' WHEN 2 THEN 'W/' || tag WHEN 3 THEN tag END,
         CASE WHEN k % 5 <> 4 THEN day END, 'visit ' || (k % 11), n, k FROM p),
bare AS (SELECT *, regexp_replace(regexp_replace(trim(url), '#.*$', ''), '^[a-zA-Z]+://', '') AS b FROM rec),
cut AS (SELECT *, regexp_extract(b, '^[^/?]*') AS host, regexp_replace(substr(b, length(regexp_extract(b, '^[^/?]*')) + 1), '[?&](utm_[a-z]+|ref)=[^&]*', '', 'g') AS rest FROM bare),
can AS (SELECT *, regexp_replace(regexp_replace(lower(host), ':(80|443)$', ''), '^www[.]', '') ||
        regexp_replace(CASE WHEN instr(rest, '?') = 0 AND instr(rest, '&') > 0 THEN substr(rest, 1, instr(rest, '&') - 1) || '?' || substr(rest, instr(rest, '&') + 1) ELSE rest END, '/+$', '') AS c FROM cut),
pick AS (
  SELECT v.record_id, v.c, v.etag, v.lm, v.visit, s.record_id AS sid, s.etag AS setag, s.lm AS slm, s.n AS sn,
         row_number() OVER (PARTITION BY v.record_id ORDER BY s.ts DESC NULLS LAST, s.record_id DESC) AS rn
  FROM can v LEFT JOIN can s ON s.kind = 'response' AND s.c = v.c AND s.ts < v.ts WHERE v.kind = 'revisit'),
judged AS (
  SELECT *, CASE WHEN sid IS NULL THEN 'no_response' WHEN etag IS NULL AND lm IS NULL THEN 'no_validator'
    WHEN CASE WHEN etag IS NOT NULL THEN regexp_replace(etag, '^W/', '') = setag ELSE lm = slm END THEN 'match' ELSE 'mismatch' END AS verdict
  FROM pick WHERE rn = 1)
SELECT record_id, c AS canonical_url, CASE WHEN verdict IN ('match', 'no_validator') THEN sid ELSE -1 END AS resolved_id, verdict,
  CASE WHEN verdict IN ('match', 'no_validator') THEN 'content-length: ' || sn || chr(10) || 'content-type: text/html' || chr(10) || 'date: ' || visit || chr(10) ||
    'etag: ' || setag || chr(10) || 'last-modified: ' || slm || chr(10) || 'server: two' END AS headers
FROM judged
"""
