"""WARC captures: not-modified revisits resolved to the full response they mean.

A revisit takes the latest earlier full response of the same canonical URL if
its validators agree, and the stored headers updated by those that a
not-modified answer may change.  The search is an as-of join in two levels, by
time slice and then inside slices, so a URL with very many captures is never
sorted in one task.
"""

from __future__ import annotations

import gzip
import io
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window as W, functions as F

#: Headers that a not-modified answer never changes.
FIXED_HEADERS = ["connection", "content-encoding", "content-length", "content-range", "content-type", "keep-alive", "proxy-authenticate",
                 "proxy-authorization", "te", "trailer", "transfer-encoding", "upgrade"]
#: Query parameters that name no other resource.
TRACKING = "utm_[a-z]+|ref|fbclid|gclid"
#: Seconds in a time slice of the as-of join.
SLICE = 86_400
RECORDS = "record_id long, url string, ts long, kind string, headers map<string,string>, body binary"


def canonical_url(url: Column) -> Column:
    """One spelling for URLs of one resource: no scheme, ``www.``, default port,
    fragment, tracking parameters or final slash; host in lower case and
    parameters in order.  Null for null."""
    bare = F.regexp_replace(F.trim(url), "#.*$", "")
    rest = F.regexp_replace(bare, "^[A-Za-z][A-Za-z0-9+.-]*://", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(rest, "^[^/?]*", 0)), "^www\\.", ""), ":(80|443)$", "")
    path = F.regexp_replace(F.regexp_extract(rest, "^[^/?]*([^?]*)", 1), "/+$", "")
    query = F.regexp_extract(rest, "\\?(.*)$", 1)
    kept = F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~p.rlike(f"^({TRACKING})(=|$)")))
    return F.concat(host, path, F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.array_join(kept, "&"))).otherwise(F.lit("")))


def _header(headers: Column, name: str) -> Column:
    return F.element_at(headers, F.lit(name))


def _lower_keys(headers: Column) -> Column:
    """Keys in lower case; of keys that become equal the last one holds."""
    entries = F.transform(F.map_entries(headers), lambda e: F.struct(F.lower(e["key"]).alias("key"), e["value"].alias("value")))
    last = F.filter(entries, lambda e, i: ~F.exists(F.slice(entries, i + 2, F.size(entries)), lambda x: x["key"] == e["key"]))
    return F.map_from_entries(last)


def resolve_revisits(records: DataFrame, slice_seconds: int = SLICE) -> DataFrame:
    """``record_id, canonical, ts, refers_to, refers_ts, status, headers`` for
    each record of kind ``revisit``.

    ``refers_to`` is the latest full response (kind ``response``) of the same
    canonical URL with a smaller ts; of several with one ts, that with the
    largest record id.  ``status`` is ``resolved``, ``mismatch`` (validators
    disagree) or ``missing`` (no earlier response, or a null URL or ts); only
    resolved rows have merged headers.  ETags are compared weakly; where the
    revisit has none, Last-Modified must be equal; a revisit without either
    takes the response as it is.  Repeated records give repeated rows.
    """
    rows = records.select(F.col("record_id").cast("long").alias("record_id"), canonical_url(F.col("url")).alias("canonical"), F.col("ts").cast("long").alias("ts"),
                          "kind", _lower_keys(F.coalesce("headers", F.create_map().cast("map<string,string>"))).alias("headers")).where("kind in ('response', 'revisit')")
    known = rows.where("canonical is not null and ts is not null").withColumn("slice", F.floor(F.col("ts") / slice_seconds).cast("long"))
    full = F.when(F.col("kind") == "response", F.struct("ts", "record_id", "headers"))
    # inside a slice: rows with one ts see earlier ones only
    inside = W.partitionBy("canonical", "slice").orderBy("ts", F.when(F.col("kind") == "revisit", 0).otherwise(1), "record_id").rowsBetween(W.unboundedPreceding, -1)
    near = known.withColumn("near", F.last(full, ignorenulls=True).over(inside)).where("kind = 'revisit'")
    # over slices: the last response of each slice, carried on
    last = known.where("kind = 'response'").groupBy("canonical", "slice").agg(F.max_by(F.struct("ts", "record_id", "headers"), F.struct("ts", "record_id")).alias("last"))
    slices = last.select("canonical", "slice", "last").unionByName(near.where("near is null").select("canonical", "slice", F.lit(None).cast(last.schema["last"].dataType).alias("last")))
    slices = slices.groupBy("canonical", "slice").agg(F.max_by("last", F.col("last.ts")).alias("last"))
    carry = W.partitionBy("canonical").orderBy("slice").rowsBetween(W.unboundedPreceding, -1)
    carried = slices.withColumn("far", F.last("last", ignorenulls=True).over(carry)).select("canonical", "slice", "far")
    joined = near.join(carried, ["canonical", "slice"], "left").withColumn("hit", F.coalesce("near", "far")).drop("near", "far", "slice")
    lost = rows.where("kind = 'revisit' and (canonical is null or ts is null)").withColumn("hit", F.lit(None).cast(joined.schema["hit"].dataType))
    found = joined.select("record_id", "canonical", "ts", "headers", "hit").unionByName(lost.select("record_id", "canonical", "ts", "headers", "hit"))
    weak = lambda c: F.regexp_replace(c, "^W/", "")
    etag, modified = _header(F.col("headers"), "etag"), _header(F.col("headers"), "last-modified")
    stored = F.col("hit.headers")
    agrees = (F.when(etag.isNotNull(), F.coalesce(weak(etag) == weak(_header(stored, "etag")), F.lit(False)))
              .when(modified.isNotNull(), F.coalesce(modified == _header(stored, "last-modified"), F.lit(False))).otherwise(F.lit(True)))
    status = F.when(F.col("hit").isNull(), "missing").when(agrees, "resolved").otherwise("mismatch")
    fresh = F.map_filter("headers", lambda k, v: ~k.isin(FIXED_HEADERS))
    merged = F.map_concat(F.map_filter(stored, lambda k, v: ~F.map_contains_key(fresh, k)), fresh)
    return found.withColumn("status", status).select(
        "record_id", "canonical", "ts", F.when(F.col("status") != "missing", F.col("hit.record_id")).alias("refers_to"), F.col("hit.ts").alias("refers_ts"), "status",
        F.when(F.col("status") == "resolved", merged).alias("headers"))


# --- files -------------------------------------------------------------------


def record_bytes(record_id: int, url: str, ts: int, kind: str, headers: dict, body: bytes | None) -> bytes:
    """One WARC/1.1 record; its block is an HTTP answer."""
    status = "304 Not Modified" if kind == "revisit" else "200 OK"
    http = f"HTTP/1.1 {status}\r\n" + "".join(f"{k}: {v}\r\n" for k, v in (headers or {}).items()) + "\r\n"
    block = http.encode() + (body or b"")
    when = pd.Timestamp(ts, unit="s").strftime("%Y-%m-%dT%H:%M:%SZ")
    profile = "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/server-not-modified\r\n" if kind == "revisit" else ""
    head = (f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Record-ID: <urn:x-record:{record_id}>\r\nWARC-Target-URI: {url}\r\nWARC-Date: {when}\r\n{profile}"
            f"Content-Type: application/http; msgtype=response\r\nContent-Length: {len(block)}\r\n\r\n")
    return head.encode() + block + b"\r\n\r\n"


def _inflated(raw: bytes) -> bytes:
    """The bytes of all gzip members, as far as they are whole; plain bytes as they are."""
    out, rest = [], raw
    while rest[:2] == b"\x1f\x8b":
        member = zlib.decompressobj(31)
        try:
            out.append(member.decompress(rest))
        except zlib.error:
            break
        if not member.eof:
            break
        rest = member.unused_data
    return b"".join(out) if raw[:2] == b"\x1f\x8b" else raw


def _text(head: bytes) -> str:
    try:
        return head.decode()
    except UnicodeDecodeError:
        return head.decode("latin-1")


def _seconds(date: str | None) -> int | None:
    when = pd.to_datetime(date, errors="coerce", utc=True) if date else pd.NaT
    return None if when is pd.NaT else int(when.timestamp())


def _kind(kind: str | None, status: list[str], profile: str) -> str | None:
    full = len(status) < 2 or status[1] == "200"
    if kind == "response" and not full or kind == "revisit" and profile and not profile.endswith("server-not-modified"):
        return "other"
    return kind


def parse_warc(raw: bytes) -> Iterator[dict]:
    """Records of a WARC file, gzip members or plain; reading stops at the
    first record that is cut short or has no valid length.  A record without a
    valid date has a null ``ts``.  Answers other than 200 are of kind
    ``other``, and so are revisits that do not say "not modified": neither is a
    full response or a claim about validators."""
    data = io.BytesIO(_inflated(raw))
    while line := data.readline():
        if not line.startswith(b"WARC/"):
            continue
        fields = {}
        while (line := data.readline().strip()):
            k, _, v = line.decode("utf-8", "replace").partition(":")
            fields[k.strip().lower()] = v.strip()
        size = fields.get("content-length", "0")
        block = data.read(int(size)) if size.isascii() and size.isdigit() else None
        if block is None or len(block) < int(size):
            return
        head, _, body = block.partition(b"\r\n\r\n")
        first, *lines = _text(head).split("\r\n")
        pairs = (x.partition(":") for x in lines)
        number = fields.get("warc-record-id", "").strip("<>").rpartition(":")[2]
        yield {"record_id": int(number) if number.isdigit() else None, "url": fields.get("warc-target-uri"), "ts": _seconds(fields.get("warc-date")),
               "kind": _kind(fields.get("warc-type"), first.split(" "), fields.get("warc-profile", "")), "headers": {k.strip().lower(): v.strip() for k, _, v in pairs if k}, "body": body}


def read_warc(spark, path: str) -> DataFrame:
    """Records of all WARC files below ``path``, a file to a task."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for raw in frame["content"]:
                rows = pd.DataFrame(list(parse_warc(bytes(raw))), columns=["record_id", "url", "ts", "kind", "headers", "body"])
                yield rows.astype({"record_id": "Int64", "ts": "Int64"})
    return spark.read.format("binaryFile").load(path).select("content").mapInPandas(run, RECORDS)


def write_warc(records: DataFrame, path: str) -> None:
    """Gzip-membered WARC, one binary row for each record, as Parquet parts
    (column ``warc``) that concatenate to files."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = (record_bytes(int(r.record_id), r.url, int(r.ts), r.kind, dict(r.headers or {}), r.body) for r in f.itertuples())
            yield pd.DataFrame({"record_id": f["record_id"], "warc": [gzip.compress(x, mtime=0) for x in rows]})
    records.mapInPandas(run, "record_id long, warc binary").write.mode("overwrite").parquet(path)


# --- the page table as captures ---------------------------------------------


def page_captures(pages: DataFrame) -> DataFrame:
    """Two captures of each page: the full response, and a later revisit.

    Ids give times, ten minutes apart.  Every seventh revisit has a validator of
    another version; every fifth has Last-Modified only; page_id -1-x style ids
    are not made up: records are 2 * page_id and 2 * page_id + 1.
    """
    tag = F.concat(F.lit('"'), F.substring(F.md5(F.coalesce(pages["html"], F.lit(""))), 1, 16), F.lit('"'))
    base = pages.select(pages["page_id"].cast("long").alias("page_id"), pages["url"].cast("string").alias("url"), tag.alias("tag"),
                        F.octet_length(F.coalesce(pages["html"], F.lit(""))).cast("string").alias("size"))
    ts = F.col("page_id") * 600
    full = base.select((F.col("page_id") * 2).alias("record_id"), "url", ts.alias("ts"), F.lit("response").alias("kind"), F.create_map(
        F.lit("ETag"), F.col("tag"), F.lit("Last-Modified"), F.col("page_id").cast("string"), F.lit("Content-Type"), F.lit("text/html"),
        F.lit("Content-Length"), F.col("size"), F.lit("Cache-Control"), F.lit("max-age=60")).alias("headers"))
    seventh, fifth = F.col("page_id") % 7 == 0, F.col("page_id") % 5 == 0
    again = base.select((F.col("page_id") * 2 + 1).alias("record_id"), "url", (ts + 90_000).alias("ts"), F.lit("revisit").alias("kind"), F.map_filter(F.create_map(
        F.lit("ETag"), F.when(seventh, F.lit('"other"')).when(~fifth, F.concat(F.lit("W/"), F.col("tag"))),
        F.lit("Last-Modified"), F.col("page_id").cast("string"), F.lit("Content-Length"), F.lit("0"), F.lit("Cache-Control"), F.lit("max-age=600")),
        lambda k, v: v.isNotNull()).alias("headers"))
    return full.unionByName(again)


def op7_warc_revisits(spark, sf_dir: str) -> DataFrame:
    found = resolve_revisits(page_captures(spark.read.parquet(f"{sf_dir}/pages.parquet")))
    h = lambda name: _header(F.col("headers"), name)
    return found.select(((F.col("record_id") - 1) / 2).cast("long").alias("page_id"), "record_id", "canonical", "ts", "refers_to", "refers_ts", "status",
                        h("etag").alias("etag"), h("last-modified").alias("last_modified"), h("content-type").alias("content_type"),
                        h("content-length").alias("content_length"), h("cache-control").alias("cache_control"))


OP7_SQL = f"""
with p as (select page_id, html, url, regexp_replace(regexp_replace(trim(url), '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '') as rest from pages),
q as (select page_id, '"' || substr(md5(coalesce(html, '')), 1, 16) || '"' as tag, strlen(coalesce(html, ''))::varchar as size,
  regexp_replace(regexp_replace(lower(regexp_extract(rest, '^[^/?]*', 0)), '^www\\.', ''), ':(80|443)$', '') as host,
  regexp_replace(regexp_extract(rest, '^[^/?]*([^?]*)', 1), '/+$', '') as path,
  list_sort(list_filter(string_split(regexp_extract(rest, '\\?(.*)$', 1), '&'), lambda x: x <> '' and not regexp_matches(x, '^({TRACKING})(=|$)'))) as kept from p),
c as (select page_id, tag, size, host || path || case when len(kept) > 0 then '?' || array_to_string(kept, '&') else '' end as canonical from q),
again as (select page_id, canonical, page_id * 600 + 90000 as ts,
  case when page_id % 7 = 0 then '"other"' when page_id % 5 <> 0 then tag end as tag from c),
hit as (select a.page_id, a.canonical, a.ts, a.tag, max(b.page_id) as r from again a left join c b on a.canonical = b.canonical and b.page_id * 600 < a.ts group by all),
j as (select h.*, b.tag as stored, b.size, case when h.r is null then 'missing' when h.tag is null then case when h.page_id = h.r then 'resolved' else 'mismatch' end
  when h.tag = b.tag then 'resolved' else 'mismatch' end as status from hit h left join c b on b.page_id = h.r)
select page_id, page_id * 2 + 1 as record_id, canonical, ts, r * 2 as refers_to, r * 600 as refers_ts, status,
  case when status = 'resolved' then case when tag is null then stored else 'W/' || tag end end as etag,
  case when status = 'resolved' then page_id::varchar end as last_modified,
  case when status = 'resolved' then 'text/html' end as content_type, case when status = 'resolved' then size end as content_length,
  case when status = 'resolved' then 'max-age=600' end as cache_control from j"""
