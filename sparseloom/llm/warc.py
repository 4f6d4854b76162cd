"""Web archive records: not-modified revisits resolved against the captures they stand for.

A revisit record of a "304 Not Modified" answer holds no content. Its content is that of the
latest earlier full response for the same canonical URL, provided that the validators agree. The
as-of join works on slices of time: rows are ordered only within (URL, slice), and what the last
response of each slice was is carried to later slices through a table with one row per
(URL, slice). A URL with a third of all captures is thus spread over all slices; nothing is
broadcast. Slices are cut at quantiles of the capture times.

Validators: an entity tag on both sides must be equal under weak comparison; without one, the
Last-Modified dates must be equal; without these, the payload digests; a revisit without any of them is
resolved as "unvalidated". Of a revisit's headers only those that a 304 answer may update replace
the stored ones; all others, such as the content's length and type, stay as they were stored.

Defined results: a response at the same instant as the revisit is not earlier; of responses at one
instant the one with the largest record id counts, then the one with the largest validators, then one by a hash of the payload;
revisits with a null or empty URL, a null time or without an earlier response are "missing". Every revisit row gives a row
of its own, repeated rows and rows with a null or shared record id too, and responses without a record id count like others;
an empty table gives no rows; other columns are ignored. Pages without an id stand for no records.
"""

from __future__ import annotations

import gzip
import io
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import map_batches

SLICES = 1024
#: Headers that a 304 answer may update (lower case).
UPDATABLE = ("cache-control", "content-location", "date", "etag", "expires", "last-modified", "vary", "age", "warning")
#: Query parameters that name a visit and not a page.
_TRACKING = r"^(utm_[a-z]+|fbclid|gclid|ref|sessionid|phpsessid)(=|$)"

COLUMNS = {
    "record_id": "long", "kind": "string", "url": "string", "ts": "long", "status": "int", "etag": "string",
    "last_modified": "string", "digest": "string", "headers": "map<string,string>", "payload": "string",
}


def canonical_url(url: Column) -> Column:
    """Host in lower case without www or m; no scheme, fragment, default port or tracking parameter; sorted parameters."""
    plain = F.regexp_replace(F.trim(url), "#.*$", "")
    plain = F.regexp_replace(plain, "^[a-zA-Z][a-zA-Z0-9+.-]*://", "")
    host = F.regexp_replace(F.lower(F.regexp_extract(plain, "^[^/?]*", 0)), r"^(www[0-9]*|m)\.|:(80|443)$", "")
    path = F.regexp_replace(F.regexp_extract(plain, r"^[^/?]*([^?]*)", 1), "/+$", "")
    query = F.regexp_extract(plain, r"\?(.*)$", 1)
    kept = F.array_sort(F.filter(F.split(query, "&"), lambda p: ~F.lower(p).rlike(_TRACKING) & (p != "")))
    return F.concat(host, path, F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.array_join(kept, "&"))).otherwise(""))


def _weak(tag: Column) -> Column:
    return F.regexp_replace(tag, "^W/", "")


def agreement(visit: Column, base: Column) -> Column:
    """resolved, unvalidated or mismatch: the first validator that both have decides."""
    tag, date, digest = (
        (visit[c].isNotNull() & base[c].isNotNull()) for c in ("etag", "last_modified", "digest")
    )
    verdict = lambda same: F.when(same, "resolved").otherwise("mismatch")
    return (
        F.when(tag, verdict(_weak(visit["etag"]) == _weak(base["etag"])))
        .when(date, verdict(visit["last_modified"] == base["last_modified"]))
        .when(digest, verdict(visit["digest"] == base["digest"]))
        .otherwise("unvalidated")
    )


def merged_headers(stored: Column, update: Column) -> Column:
    """Stored headers with those of the update that a 304 may change."""
    lower = lambda m: F.transform_keys(F.coalesce(m, F.create_map().cast("map<string,string>")), lambda k, _: F.lower(k))
    stored, update = lower(stored), F.map_filter(lower(update), lambda k, _: k.isin(*UPDATABLE))
    kept = F.map_filter(stored, lambda k, _: ~F.coalesce(F.array_contains(F.map_keys(update), k), F.lit(False)))
    return F.map_concat(kept, update)


def resolve_revisits(records: DataFrame, slices: int = SLICES) -> DataFrame:
    """For every revisit: record_id, key, ts, base_id, base_ts, outcome, headers, payload (of the base, if it stands)."""
    known = records.select(
        *[F.col(c).cast(t) for c, t in COLUMNS.items()], canonical_url(F.col("url")).alias("key")
    )
    usable = "coalesce(key, '') <> '' AND ts IS NOT NULL"
    full = known.where(f"kind = 'response' AND status = 200 AND {usable}")
    visits = known.where("kind = 'revisit'")
    placed = visits.where(usable)
    outside = visits.where(f"NOT ({usable})")

    # thin rows for the as-of join: no payload, headers of revisits only; a base sorts by its time, then its id
    base_type = "struct<ts:long,id:long,etag:string,last_modified:string,digest:string>"
    validators = ["etag", "last_modified", "digest"]
    nothing = lambda t: F.lit(None).cast(t)
    thin_full = full.select(
        "key", "ts", F.lit(1).alias("is_full"), F.struct("ts", F.col("record_id").alias("id"), *validators).alias("base"),
        nothing("struct<record_id:long,etag:string,last_modified:string,digest:string,headers:map<string,string>>").alias("visit"),
    )
    thin_visit = placed.select("key", "ts", F.lit(0).alias("is_full"), nothing(base_type).alias("base"), F.struct("record_id", *validators, "headers").alias("visit"))
    rows = thin_full.unionByName(thin_visit)
    shares = [k / slices for k in range(1, slices)]
    cuts = sorted(set(rows.agg(F.percentile_approx("ts", shares, 2 * slices)).first()[0] or [])) if shares else []
    rows = rows.withColumn("slice", _slice_of(F.col("ts"), cuts))

    within = Window.partitionBy("key", "slice").orderBy("ts", "is_full", "base").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    lasts = rows.where("is_full = 1").groupBy("key", "slice").agg(F.max("base").alias("last"))
    # carry the last response of each slice to the slices that hold revisits
    wanted = rows.where("is_full = 0").select("key", "slice").distinct().withColumn("last", nothing(base_type))
    marks = lasts.withColumn("ask", F.lit(0)).unionByName(wanted.withColumn("ask", F.lit(1)))
    # within one slice number the question comes before the slice's own answer
    earlier = Window.partitionBy("key").orderBy("slice", F.desc("ask")).rowsBetween(Window.unboundedPreceding, -1)
    carried = marks.withColumn("carried", F.last("last", ignorenulls=True).over(earlier)).where("ask = 1").select("key", "slice", "carried")
    answered = (
        rows.withColumn("near", F.last("base", ignorenulls=True).over(within)).where("is_full = 0")
        .join(carried, ["key", "slice"], "left")
        .withColumn("base", F.coalesce("near", "carried"))
        .withColumn("outcome", F.when(F.col("base").isNull(), "missing").otherwise(agreement(F.col("visit"), F.col("base"))))
        .select("visit.record_id", "key", "ts", F.col("visit.headers").alias("update"), "base", "outcome")
    )
    stands = F.col("outcome").isin("resolved", "unvalidated")
    # one name for a response's key, time, id and validators: its content is grouped, moved and met by it once
    ref = lambda base: F.md5(F.to_json(F.struct("key", base.alias("base"))))
    stored = full.select(
        ref(F.struct("ts", F.col("record_id").alias("id"), *validators)).alias("ref"), F.struct(F.col("headers").alias("stored"), "payload").alias("content"),
        F.xxhash64(F.coalesce("payload", F.lit(""))).alias("order"),
    )
    stored = stored.groupBy("ref").agg(F.max_by("content", "order").alias("content")).select("ref", "content.stored", "content.payload")
    with_base = answered.where(stands).withColumn("ref", ref(F.col("base"))).join(stored, "ref").drop("ref")
    without = answered.where(~stands).withColumns({"stored": nothing("map<string,string>"), "payload": nothing("string")})
    no_place = outside.select(
        "record_id", "key", "ts", F.col("headers").alias("update"), nothing(base_type).alias("base"), F.lit("missing").alias("outcome"),
        nothing("map<string,string>").alias("stored"), nothing("string").alias("payload"),
    )
    whole = with_base.unionByName(without).unionByName(no_place)
    headers = F.when(F.col("outcome").isin("resolved", "unvalidated"), merged_headers(F.col("stored"), F.col("update")))
    return whole.select("record_id", "key", "ts", F.col("base.id").alias("base_id"), F.col("base.ts").alias("base_ts"), "outcome", headers.alias("headers"), "payload")


def _slice_of(ts: Column, cuts: list[int], width: int = 32) -> Column:
    """How many of the sorted cuts are at or before `ts`: first among every `width`-th, then among those in between."""
    if not cuts:
        return F.lit(0)
    upto = lambda xs: F.size(F.filter(xs, lambda c: c <= ts))
    blocks = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    longs = lambda xs: F.array(*map(F.lit, xs)).cast("array<long>")
    whole = upto(longs([b[-1] for b in blocks]))
    return whole * width + upto(F.coalesce(F.get(F.array(*map(longs, blocks)), whole), longs([])))


# ------------------------------------------------------------------ record files


def to_warc(records: list[dict]) -> bytes:
    """Record files: one gzip member per record."""
    out = io.BytesIO()
    for r in records:
        body = "" if r["kind"] == "revisit" else r.get("payload") or ""
        lines = [f"HTTP/1.1 {r['status']} x", *(f"{k}: {v}" for k, v in (r.get("headers") or {}).items()), "", ""]
        block = ("\r\n".join(lines) + body).encode()
        head = {
            "WARC-Type": r["kind"], "WARC-Record-ID": f"<urn:record:{r['record_id']}>", "WARC-Target-URI": r["url"], "WARC-Date": str(r["ts"]),
            "Content-Type": "application/http;msgtype=response", "Content-Length": str(len(block)),
        }
        if r.get("digest"):
            head["WARC-Payload-Digest"] = r["digest"]
        if r["kind"] == "revisit":
            head["WARC-Profile"] = "http://netpreserve.org/warc/1.1/revisit/server-not-modified"
        text = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()) + "\r\n"
        out.write(gzip.compress(text.encode() + block + b"\r\n\r\n", mtime=0))
    return out.getvalue()


def _headers(text: str) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in text.split("\r\n") if ":" in x)}


def from_warc(data: bytes) -> Iterator[dict]:
    """Records of a file, plain or gzip, one after the other."""
    with gzip.open(io.BytesIO(data)) if data[:2] == b"\x1f\x8b" else io.BytesIO(data) as f:
        while line := f.readline():
            if not line.startswith(b"WARC/"):
                continue
            lines = []
            while (line := f.readline()) not in (b"\r\n", b""):
                lines.append(line.decode("utf-8", "replace").rstrip("\r\n"))
            head = _headers("\r\n".join(lines))
            block = f.read(int(head.get("content-length", 0))).decode("utf-8", "replace")
            first, _, body = block.partition("\r\n\r\n")
            status, _, rest = first.partition("\r\n")
            http = _headers(rest)
            yield {
                "record_id": int(head["warc-record-id"].strip("<>").rsplit(":", 1)[-1]), "kind": head.get("warc-type"), "url": head.get("warc-target-uri"),
                "ts": int(head.get("warc-date", 0)), "status": int((status.split(" ") + ["0"])[1]) if status.startswith("HTTP") else None, "etag": http.get("etag"),
                "last_modified": http.get("last-modified"), "digest": head.get("warc-payload-digest"), "headers": http, "payload": body,
            }


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of all files below a path, in the columns that `resolve_revisits` takes."""
    schema = ", ".join(f"{c} {t}" for c, t in COLUMNS.items())
    arrow = pa.schema([
        ("record_id", pa.int64()), ("kind", pa.string()), ("url", pa.string()), ("ts", pa.int64()), ("status", pa.int32()), ("etag", pa.string()),
        ("last_modified", pa.string()), ("digest", pa.string()), ("headers", pa.map_(pa.string(), pa.string())), ("payload", pa.string()),
    ])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0).to_pylist():
                rows = [r | {"headers": list(r["headers"].items())} for r in from_warc(data)]
                yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    files = spark.read.format("binaryFile").load(path).select("content")
    return map_batches(files, work, schema)


# ------------------------------------------------------------------ the crawl that the pages table stands for


def crawl_of(pages: DataFrame) -> DataFrame:
    """Two records per page: its capture, in order of page_id, and a later not-modified revisit of its URL.

    The revisit carries the tag of the page's own capture. Where another page with the same canonical URL was
    captured in between with other content, the validators do not agree.
    """
    page = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")).where("page_id IS NOT NULL")
    tag = F.concat(F.lit('"'), F.md5("html"), F.lit('"'))
    full = page.select(
        (F.col("page_id") * 2).alias("record_id"), F.lit("response").alias("kind"), "url", (F.col("page_id") * 10).alias("ts"), F.lit(200).alias("status"),
        tag.alias("etag"), F.lit(None).cast("string").alias("last_modified"), F.md5("html").alias("digest"),
        F.create_map(F.lit("ETag"), tag, F.lit("Date"), (F.col("page_id") * 10).cast("string"), F.lit("Content-Type"), F.lit("text/html"), F.lit("Content-Length"), F.length("html").cast("string")).alias("headers"),
        F.col("html").alias("payload"),
    )
    later = (F.col("page_id") + 5000) * 10 + 5
    visit = page.select(
        (F.col("page_id") * 2 + 1).alias("record_id"), F.lit("revisit").alias("kind"), "url", later.alias("ts"), F.lit(304).alias("status"),
        F.concat(F.lit("W/"), tag).alias("etag"), F.lit(None).cast("string").alias("last_modified"), F.md5("html").alias("digest"),
        F.create_map(F.lit("etag"), F.concat(F.lit("W/"), tag), F.lit("Date"), later.cast("string"), F.lit("Cache-Control"), F.lit("max-age=60"), F.lit("Content-Length"), F.lit("0"), F.lit("Set-Cookie"), F.lit("s=1")).alias("headers"),
        F.lit(None).cast("string").alias("payload"),
    )
    return full.unionByName(visit)


def revisit_report(pages: DataFrame) -> DataFrame:
    """Every revisit of the pages' crawl, with digests of the headers and content it stands for."""
    found = resolve_revisits(crawl_of(pages))
    lines = F.array_join(F.transform(F.array_sort(F.map_entries("headers")), lambda e: F.concat(e["key"], F.lit("="), e["value"])), ";")
    return found.select(
        F.floor((F.col("record_id") - 1) / 2).cast("long").alias("page_id"), "key", "ts", F.floor(F.col("base_id") / 2).cast("long").alias("base_page_id"), "base_ts",
        "outcome", lines.alias("headers"), F.md5("payload").alias("payload_md5"), F.length("payload").cast("long").alias("payload_chars"),
    )


REVISIT_SQL = r"""
WITH page AS (
  SELECT page_id, url, coalesce(html, '') AS html, '"' || md5(coalesce(html, '')) || '"' AS tag,
         regexp_replace(regexp_replace(trim(url), '#.*$', ''), '^[a-zA-Z][a-zA-Z0-9+.-]*://', '') AS plain
  FROM pages WHERE page_id IS NOT NULL
), parts AS (
  SELECT *, regexp_replace(lower(regexp_extract(plain, '^[^/?]*')), '^(www[0-9]*|m)\.|:(80|443)$', '', 'g') AS host,
         regexp_replace(regexp_extract(plain, '^[^/?]*([^?]*)', 1), '/+$', '') AS path,
         list_sort(list_filter(string_split(regexp_extract(plain, '\?(.*)$', 1), '&'),
           lambda p: NOT regexp_matches(lower(p), '^(utm_[a-z]+|fbclid|gclid|ref|sessionid|phpsessid)(=|$)') AND p <> '')) AS kept
  FROM page
), keyed AS (
  SELECT *, host || path || CASE WHEN len(kept) > 0 THEN '?' || array_to_string(kept, '&') ELSE '' END AS key FROM parts
), visit AS (
  SELECT page_id, key, (page_id + 5000) * 10 + 5 AS ts, tag FROM keyed
), found AS (
  SELECT v.page_id, v.key, v.ts, v.tag AS visit_tag, b.page_id AS base_page_id, b.ts AS base_ts, b.tag AS base_tag, b.html AS html
  FROM visit v ASOF LEFT JOIN (SELECT page_id, key, page_id * 10 AS ts, tag, html FROM keyed WHERE key <> '') b
    ON v.key = b.key AND v.ts > b.ts
)
SELECT page_id, key, ts, base_page_id, base_ts,
       CASE WHEN base_page_id IS NULL THEN 'missing' WHEN visit_tag = base_tag THEN 'resolved' ELSE 'mismatch' END AS outcome,
       CASE WHEN visit_tag = base_tag THEN 'cache-control=max-age=60;content-length=' || length(html) || ';content-type=text/html;date='
         || ts || ';etag=W/' || visit_tag END AS headers,
       CASE WHEN visit_tag = base_tag THEN md5(html) END AS payload_md5,
       CASE WHEN visit_tag = base_tag THEN length(html) END AS payload_chars
FROM found
"""
