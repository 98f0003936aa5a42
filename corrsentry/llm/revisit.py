"""WARC: reading records, and resolving not-modified revisits to the responses they stand for.

A revisit (a 304 answer, or a record that says its payload is unchanged) has no body.  It is joined as of its time to
the latest strictly earlier full response with the same canonical URL.  The validators are then checked: entity tags
by weak comparison, else Last-Modified, else the payload digest.  If they agree, the stored response's headers are
updated with those that a not-modified answer may change; if not, the revisit stays unresolved.

The as-of join works on time buckets: the last response of each URL and bucket is aggregated, carried over later
buckets of the URL (one small row each), and only rows of one URL and one bucket are sorted together, so a URL with a
third of all captures is spread over its buckets.  Bodies are not part of the join.

Edge cases: a null URL or time never matches; equal times do not count as earlier; of several responses at the latest
time the one with the greatest id is taken; null headers count as none; repeated revisits each get a row; an empty
table gives an empty result.
"""

from __future__ import annotations

import datetime as dt
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

#: Headers that describe the stored body or one connection; a not-modified answer does not change them.
NOT_PERMITTED = ["connection", "content-encoding", "content-length", "content-md5", "content-range", "content-type", "keep-alive", "proxy-authenticate", "proxy-authorization", "te", "trailer", "transfer-encoding", "upgrade"]
#: Query parameters that do not choose a page.
TRACKING = "(utm_[a-z]+|ref|fbclid|gclid)"
RECORD = "record_id string, kind string, url string, ts timestamp, status int, headers map<string,string>, digest string, body binary"


def canonical_url(url: Column) -> Column:
    """Host in lower case without www. and default port, path without a closing slash, query without tracking
    parameters; scheme, user and fragment are dropped."""
    bare = F.regexp_replace(F.regexp_replace(url, r"(?s)#.*$", ""), r"(?i)^[a-z][a-z0-9+.-]*://", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(bare, r"^([^/?]*)", 1)), r"^[^@]*@", ""), r"^www\.|:(80|443)$", "")
    path = F.regexp_replace(F.regexp_extract(bare, r"^[^/?]*([^?]*)", 1), r"/+$", "")
    query = F.regexp_extract(bare, r"^[^?]*\?(.*)$", 1)
    kept = F.regexp_replace(F.regexp_replace(query, f"(^|&){TRACKING}=[^&]*", ""), "^&", "")
    return F.concat(host, path, F.when(kept == "", "").otherwise(F.concat(F.lit("?"), kept)))


def _weak(tag: Column) -> Column:
    return F.regexp_replace(tag, "^W/", "")


def resolve_revisits(captures: DataFrame, buckets: int | None = None) -> DataFrame:
    """captures (id, url, ts timestamp, is_revisit boolean, headers map with lower-case names, digest) -> a row for each
    revisit: id, url, ts, response_id, verdict (etag, last-modified, digest, mismatch, unverified or missing) and
    headers (merged, or null unless resolved).  buckets: of time; None: more with more rows, so that those of one URL in
    one bucket stay few."""
    rows = captures.select("id", "url", canonical_url(F.col("url")).alias("page"), "ts", "is_revisit", "headers", "digest")
    *ends, n = captures.agg(F.min("ts"), F.max("ts"), F.count(F.lit(1))).first()
    lo, hi = (x.timestamp() if x else 0.0 for x in ends)
    width = max(1.0, (hi - lo + 1) / (buckets or min(1 << 20, 64 + n // 50_000)))
    rows = rows.withColumn("bucket", F.floor((F.col("ts").cast("double") - lo) / width))
    full = F.when(~F.col("is_revisit") & F.col("ts").isNotNull(), F.struct(F.col("id"), F.col("headers"), F.col("digest")))
    rows = rows.withColumn("full", full)
    last = rows.where("page is not null and ts is not null").groupBy("page", "bucket").agg(F.max_by("full", F.when(F.col("full").isNotNull(), F.struct("ts", "id"))).alias("last"))
    earlier = Window.partitionBy("page").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = last.select("page", "bucket", F.last("last", ignorenulls=True).over(earlier).alias("carried"))
    inside = Window.partitionBy("page", "bucket").orderBy("ts", F.col("full").isNotNull(), "id").rowsBetween(Window.unboundedPreceding, -1)
    near = rows.where("page is not null and ts is not null").withColumn("near", F.last("full", ignorenulls=True).over(inside)).where("is_revisit").drop("full")
    found = near.join(carried, ["page", "bucket"], "left").withColumn("full", F.coalesce("near", "carried")).drop("near", "carried")
    never = rows.where("is_revisit and (page is null or ts is null)").withColumn("full", F.lit(None).cast(rows.schema["full"].dataType))
    found = found.unionByName(never.select(*found.columns))
    none = F.create_map().cast("map<string,string>")
    own, old = F.coalesce("headers", none), F.coalesce("full.headers", none)
    tag = (own["etag"], old["etag"])
    date = (own["last-modified"], old["last-modified"])
    digest = (F.col("digest"), F.col("full.digest"))
    both = lambda p: p[0].isNotNull() & p[1].isNotNull()
    verdict = (
        F.when(F.col("full").isNull(), "missing")
        .when(both(tag), F.when(_weak(tag[0]) == _weak(tag[1]), "etag").otherwise("mismatch"))
        .when(both(date), F.when(date[0] == date[1], "last-modified").otherwise("mismatch"))
        .when(both(digest), F.when(digest[0] == digest[1], "digest").otherwise("mismatch"))
        .otherwise("unverified")
    )
    fresh = F.map_filter(own, lambda k, v: ~k.isin(NOT_PERMITTED) & v.isNotNull())
    merged = F.map_concat(F.map_filter(old, lambda k, _: ~F.map_contains_key(fresh, k)), fresh)
    return found.select("id", "url", "ts", F.col("full.id").alias("response_id"), verdict.alias("verdict"), F.when(verdict.isin("etag", "last-modified", "digest"), merged).alias("headers"))


def header_text(headers: Column) -> Column:
    """name=value lines in the names' order."""
    return F.array_join(F.array_sort(F.transform(F.map_entries(headers), lambda e: F.concat(e["key"], F.lit("="), e["value"]))), "\n")


def _members(raw: bytes) -> Iterator[bytes]:
    """Plain bytes of a WARC file: itself, or its gzip members one after the other; a damaged member ends the file."""
    if raw[:2] != b"\x1f\x8b":
        yield raw
        return
    view, at = memoryview(raw), 0
    while view[at : at + 2] == b"\x1f\x8b":
        d, plain = zlib.decompressobj(31), []
        try:
            while not d.eof and at < len(view):  # fed by pieces: what a member leaves over is never more than one piece
                piece = view[at : at + 65_536]
                plain.append(d.decompress(piece))
                at += len(piece) - len(d.unused_data)
        except zlib.error:
            return
        yield b"".join(plain)


def _fields(head: bytes) -> tuple[str, dict[str, str]]:
    lines = head.decode("utf-8", "replace").split("\r\n")
    out: dict[str, str] = {}
    for line in lines[1:]:
        name, sep, value = line.partition(":")
        if sep:
            out[name.strip().lower()] = value.strip()
    return lines[0], out


def parse_warc(raw: bytes) -> Iterator[dict]:
    """Response and revisit records of one file; other kinds and records cut off are passed over."""
    for data in _members(raw):
        at = 0
        while (at := data.find(b"WARC/", at)) >= 0:
            end = data.find(b"\r\n\r\n", at)
            if end < 0:
                break
            _, warc = _fields(data[at:end])
            length = warc.get("content-length", "")
            if not length.isdigit() or end + 4 + int(length) > len(data):
                break
            block, at = data[end + 4 : end + 4 + int(length)], end + 4 + int(length)
            if warc.get("warc-type") not in ("response", "revisit"):
                continue
            head, _, body = block.partition(b"\r\n\r\n")
            first, headers = _fields(head)
            status = first.split()[1] if len(first.split()) > 1 else ""
            try:
                ts = dt.datetime.fromisoformat(warc.get("warc-date", "").replace("Z", "+00:00"))
            except ValueError:
                ts = None
            yield {"record_id": warc.get("warc-record-id"), "kind": warc["warc-type"], "url": warc.get("warc-target-uri", "").strip("<>") or None, "ts": ts, "status": int(status) if status.isdigit() else None, "headers": headers, "digest": warc.get("warc-payload-digest"), "body": body if warc["warc-type"] == "response" else None}


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of the WARC files under path, plain or gzipped; a task holds one file at a time."""
    kinds = pa.schema([("record_id", pa.string()), ("kind", pa.string()), ("url", pa.string()), ("ts", pa.timestamp("us", "UTC")), ("status", pa.int32()), ("headers", pa.map_(pa.string(), pa.string())), ("digest", pa.string()), ("body", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for raw in b.column(0):
                rows = [r | {"headers": list(r["headers"].items())} for r in parse_warc(raw.as_py())]
                yield pa.RecordBatch.from_pylist(rows, schema=kinds)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, RECORD)


def write_warc(record_id: str, kind: str, url: str, ts: str, status: str, headers: dict[str, str], body: bytes = b"") -> bytes:
    """One plain WARC record."""
    http = f"HTTP/1.1 {status}\r\n".encode() + b"".join(f"{k}: {v}\r\n".encode() for k, v in headers.items()) + b"\r\n" + body
    head = f"WARC/1.0\r\nWARC-Type: {kind}\r\nWARC-Record-ID: {record_id}\r\nWARC-Target-URI: {url}\r\nWARC-Date: {ts}\r\nContent-Type: application/http\r\nContent-Length: {len(http)}\r\n\r\n"
    return head.encode() + http + b"\r\n\r\n"


#: The crawl of the query: page i is fetched i seconds after the start, and asked for again a day later.
START, AGAIN_S = 1_704_067_200, 86_400


def page_captures(pages: DataFrame) -> DataFrame:
    """Each page as a full response and, a day later, as a not-modified answer with the entity tag of its body."""
    tag = F.concat(F.lit('"'), F.md5(F.col("html")), F.lit('"'))
    base = pages.select("page_id", "url", tag.alias("tag"), F.length(F.col("html").cast("binary")).cast("string").alias("size"), (F.col("page_id") + START).alias("at"))
    text = lambda c: c.cast("string")
    full = F.create_map(F.lit("content-type"), F.lit("text/html"), F.lit("content-length"), F.col("size"), F.lit("etag"), F.col("tag"), F.lit("date"), text(F.col("at")))
    again = F.create_map(F.lit("content-type"), F.lit("text/plain"), F.lit("content-length"), F.lit("0"), F.lit("etag"), F.col("tag"), F.lit("date"), text(F.col("at") + AGAIN_S), F.lit("cache-control"), F.lit("max-age=60"))
    a = base.select(F.col("page_id").alias("id"), "url", F.timestamp_seconds("at").alias("ts"), F.lit(False).alias("is_revisit"), full.alias("headers"), F.lit(None).cast("string").alias("digest"))
    b = base.select(F.col("page_id").alias("id"), "url", F.timestamp_seconds(F.col("at") + AGAIN_S).alias("ts"), F.lit(True).alias("is_revisit"), again.alias("headers"), F.lit(None).cast("string").alias("digest"))
    return a.unionByName(b)


def op10_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = resolve_revisits(page_captures(table(spark, sf_dir, "pages").select("page_id", "url", "html")))
    return found.select(F.col("id").alias("page_id"), "response_id", "verdict", F.md5(header_text(F.col("headers"))).alias("headers_md5"))


SQL = rf"""
WITH cut AS (SELECT *, regexp_replace(regexp_replace(url, '#.*$', '', 's'), '^[a-z][a-z0-9+.-]*://', '', 'i') AS bare FROM pages),
parts AS (SELECT *, regexp_replace(regexp_replace(lower(regexp_extract(bare, '^([^/?]*)', 1)), '^[^@]*@', ''), '^www\.|:(80|443)$', '', 'g') AS host,
 regexp_replace(regexp_extract(bare, '^[^/?]*([^?]*)', 1), '/+$', '') AS path,
 regexp_replace(regexp_replace(regexp_extract(bare, '^[^?]*\?(.*)$', 1), '(^|&){TRACKING}=[^&]*', '', 'g'), '^&', '') AS query FROM cut),
p AS (SELECT page_id, page_id + {START} AS t0, '"' || md5(html) || '"' AS tag, strlen(html) AS size, host || path || CASE WHEN query = '' THEN '' ELSE '?' || query END AS page FROM parts),
f AS (SELECT r.page_id, r.t0, r.tag, o.page_id AS response_id, o.tag AS old_tag, o.size AS old_size, row_number() OVER (PARTITION BY r.page_id ORDER BY o.t0 DESC, o.page_id DESC) AS k
 FROM p r LEFT JOIN p o ON r.page = o.page AND o.t0 < r.t0 + {AGAIN_S})
SELECT page_id, response_id, CASE WHEN response_id IS NULL THEN 'missing' WHEN tag = old_tag THEN 'etag' ELSE 'mismatch' END AS verdict,
 CASE WHEN tag = old_tag THEN md5('cache-control=max-age=60' || chr(10) || 'content-length=' || old_size || chr(10) || 'content-type=text/html' || chr(10) || 'date=' || (t0 + {AGAIN_S}) || chr(10) || 'etag=' || tag) END AS headers_md5
FROM f WHERE k = 1
"""
