"""Web archives: reading and writing records, and resolving not-modified revisits to earlier full responses."""

from __future__ import annotations

import gzip
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from distinct_bounds.llm.common import col, map_arrow, materialize, table

#: Header fields that a not-modified answer may replace in the stored response.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "vary")
#: Query parameters that only track, by their beginnings.
TRACKING = r"(?:utm_[^=&]*|gclid|fbclid|ref)"
STATUS = ("response", "resolved", "no_earlier_response", "validator_mismatch", "other")
BLOCK = 3600 * 1_000_000
RECORDS = "record_id string, kind string, url string, ts long, headers map<string,string>, digest string, payload binary"


def canonical(url: Column) -> Column:
    """A key for captures of one page: no scheme, user, default port, www, fragment, tracking parameter or final slash;
    host in lower case. Null for null."""
    rest = F.regexp_replace(F.regexp_replace(F.trim(url), r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//", ""), r"#.*$", "")
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(rest, r"^[^/?]*", 0)), r"^.*@", ""), r":(?:80|443)$", "")
    host = F.regexp_replace(host, r"^www\.", "")
    path = F.regexp_replace(rest, r"^[^/?]*", "")
    path = F.regexp_replace(path, rf"([?&]){TRACKING}=[^&]*", "$1")
    path = F.regexp_replace(F.regexp_replace(path, r"&&+", "&"), r"\?&", "?")
    return F.concat(host, F.regexp_replace(F.regexp_replace(path, r"[?&]+$", ""), r"/+$", ""))


def resolve_revisits(records: DataFrame) -> DataFrame:
    """records with canonical_url, status, source_id and merged_headers.

    records holds record_id, kind ("response" or "revisit"), url, ts (microseconds), headers
    (names in lower case) and digest. A revisit refers to the latest response of its
    canonical URL with an earlier ts, of equal ones the largest record_id. It is resolved if
    each validator that both have (etag, last-modified, digest) agrees; weak etags are
    compared without their mark. Then it gets the response's headers with the permitted
    ones of its own in their place; otherwise source_id and merged_headers stay null, as for
    a null url or ts. Other kinds pass with status "other". Repeated records are resolved
    one by one. Of responses that share record_id, canonical URL and ts, the one whose headers,
    in order of their names, and digest come first as text counts. An empty table gives an
    empty one. Columns named as the new ones are replaced.

    The as-of join never brings all captures of a URL together: the latest response is
    found within an hour of captures, and before it among the hours' latest ones.
    """
    kept = [c for c in records.columns if c.lower() not in ("canonical_url", "status", "source_id", "merged_headers")]
    rows = records.select(F.struct(*[col(c) for c in kept]).alias("_r"), canonical(F.col("url")).alias("_canon"), F.col("ts").alias("_ts"), F.col("kind").alias("_kind"), F.col("record_id").alias("_id"))
    rows = rows.withColumn("_block", F.floor(F.col("_ts") / BLOCK)).withColumn("_row", F.monotonically_increasing_id())
    rows = materialize(rows, "captures")
    keys = rows.select("_row", "_canon", "_ts", "_block", "_kind", "_id").filter(F.col("_canon").isNotNull() & F.col("_ts").isNotNull())
    full = F.when(F.col("_kind") == "response", F.struct(F.col("_ts").alias("t"), F.col("_id").alias("i")))
    hours = keys.groupBy("_canon", "_block").agg(F.max(full).alias("top"))
    before = Window.partitionBy("_canon").orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    hours = materialize(hours.withColumn("_old", F.max("top").over(before)).select(F.col("_canon").alias("_c"), F.col("_block").alias("_b"), "_old"), "hours")
    earlier = Window.partitionBy("_canon", "_block").orderBy("_ts").rangeBetween(Window.unboundedPreceding, -1)
    near = keys.withColumn("_near", F.max(full).over(earlier)).filter("_kind = 'revisit'")
    found = near.join(hours, (F.col("_canon") == F.col("_c")) & (F.col("_block") == F.col("_b")), "left")
    latest = F.coalesce("_near", "_old")
    found = found.select(F.col("_row").alias("_found"), "_canon", latest["t"].alias("_when"), latest["i"].alias("_source"))

    looks = F.struct(F.to_json(F.array_sort(F.map_entries("_r.headers"))).alias("h"), F.col("_r.digest").alias("d"))
    sources = rows.filter("_kind = 'response'").groupBy(F.col("_id").alias("_sid"), F.col("_canon").alias("_sc"), F.col("_ts").alias("_st"))
    sources = sources.agg(F.min_by(F.struct(F.col("_r.headers").alias("h"), F.col("_r.digest").alias("d")), looks).alias("_s")).select("_sid", "_sc", "_st", F.col("_s.h").alias("_sh"), F.col("_s.d").alias("_sd"))
    same = (F.col("_source") == F.col("_sid")) & (F.col("_canon") == F.col("_sc")) & (F.col("_when") == F.col("_st"))
    wanted = materialize(found.filter("_source is not null"), "wanted").join(sources, same)
    told = materialize(wanted.select("_found", "_source", "_sh", "_sd"), "told")
    met = rows.join(told, F.col("_row") == F.col("_found"), "left")

    own, base = F.coalesce(F.col("_r.headers"), F.create_map().cast("map<string,string>")), F.coalesce(F.col("_sh"), F.create_map().cast("map<string,string>"))

    def agrees(a: Column, b: Column) -> Column:
        return a.isNull() | b.isNull() | (a == b)

    def etag(m: Column) -> Column:
        return F.regexp_replace(F.element_at(m, "etag"), r"^W/", "")

    good = agrees(etag(own), etag(base)) & agrees(F.element_at(own, "last-modified"), F.element_at(base, "last-modified")) & agrees(F.col("_r.digest"), F.col("_sd"))
    status = F.when(F.col("_kind") == "response", "response").when(F.coalesce(F.col("_kind"), F.lit("")) != "revisit", "other")
    status = status.when(F.col("_source").isNull(), "no_earlier_response").when(good, "resolved").otherwise("validator_mismatch")
    fresh = F.map_filter(own, lambda k, v: k.isin(*PERMITTED))
    merged = F.map_concat(F.map_filter(base, lambda k, v: ~F.array_contains(F.map_keys(fresh), k)), fresh)
    met = met.withColumn("_status", status)
    resolved = F.col("_status") == "resolved"
    return met.select(*[F.col("_r")[c].alias(c) for c in kept], F.col("_canon").alias("canonical_url"), F.col("_status").alias("status"), F.when(resolved, F.col("_source")).alias("source_id"), F.when(resolved, merged).alias("merged_headers"))


# ---- records and files -----------------------------------------------------------------


def split_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields in lower case, block) of each record of an uncompressed or gzipped archive.

    A record that is cut off ends the archive; bytes between records are passed over.
    """
    if data[:2] == b"\x1f\x8b":
        whole, rest = [], data
        while rest[:2] == b"\x1f\x8b":
            d = zlib.decompressobj(31)
            try:
                whole.append(d.decompress(rest))
            except zlib.error:
                break
            rest = d.unused_data.lstrip(b"\r\n\x00") if d.eof else b""
        data = b"".join(whole)
    at = data.find(b"WARC/")
    while at >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        head = fields(data[at:end].split(b"\r\n")[1:])
        length = head.get("content-length", "")
        if not length.isdigit() or end + 4 + int(length) > len(data):
            return
        yield head, data[end + 4 : end + 4 + int(length)]
        at = data.find(b"WARC/", end + 4 + int(length))


def fields(lines: list[bytes]) -> dict[str, str]:
    """Header fields with names in lower case; of repeated names the last, folded lines joined."""
    out, last = {}, None
    for line in lines:
        text = line.decode("utf-8", "replace")
        if text[:1] in (" ", "\t") and last:
            out[last] += " " + text.strip()
        elif ":" in text:
            last = text.split(":", 1)[0].strip().lower()
            out[last] = text.split(":", 1)[1].strip()
    return out


def micros(date: str | None) -> int | None:
    from datetime import datetime, timezone

    try:
        found = datetime.fromisoformat((date or "").replace("Z", "+00:00"))
    except ValueError:
        return None
    found = found if found.tzinfo else found.replace(tzinfo=timezone.utc)
    return round(found.timestamp() * 1_000_000)


def read(spark: SparkSession, path: str) -> DataFrame:
    """RECORDS of the archives at a path, one task a file or more; damaged ends of files are left out."""

    def work(batches):
        for batch in batches:
            for data in batch.column(0):
                rows = [record(h, b) for h, b in split_records(data.as_py() or b"")]
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=ARROW)

    return map_arrow(spark.read.format("binaryFile").load(path).select("content"), work, RECORDS)


ARROW = pa.schema([("record_id", pa.string()), ("kind", pa.string()), ("url", pa.string()), ("ts", pa.int64()), ("headers", pa.map_(pa.string(), pa.string())), ("digest", pa.string()), ("payload", pa.binary())])


def record(head: dict[str, str], block: bytes) -> dict:
    http, _, payload = block.partition(b"\r\n\r\n") if head.get("content-type", "").startswith("application/http") else (b"", b"", block)
    return {"record_id": head.get("warc-record-id"), "kind": head.get("warc-type"), "url": head.get("warc-target-uri"), "ts": micros(head.get("warc-date")), "headers": list(fields(http.split(b"\r\n")[1:]).items()), "digest": head.get("warc-payload-digest"), "payload": payload}


def written(row: dict, compressed: bool = True) -> bytes:
    """One record as bytes, a gzip member of its own if compressed."""
    from datetime import datetime, timezone

    http = b"HTTP/1.1 " + (b"304 Not Modified" if row["kind"] == "revisit" else b"200 OK") + b"\r\n"
    http += b"".join(f"{k}: {v}\r\n".encode() for k, v in (row["headers"] or [])) + b"\r\n" + (row["payload"] or b"")
    date = "" if row["ts"] is None else datetime.fromtimestamp(row["ts"] / 1_000_000, timezone.utc).isoformat().replace("+00:00", "Z")
    named = (("WARC-Record-ID", row["record_id"]), ("WARC-Type", row["kind"]), ("WARC-Target-URI", row["url"]), ("WARC-Date", date), ("WARC-Payload-Digest", row["digest"]), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(http))))
    out = b"WARC/1.1\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in named if v) + b"\r\n" + http + b"\r\n\r\n"
    return gzip.compress(out, mtime=0) if compressed else out


def encoded(records: DataFrame, compressed: bool = True) -> DataFrame:
    """(record_id, record): each record as the bytes that an archive holds; archives are their concatenation."""

    def work(batches):
        for batch in batches:
            rows = batch.to_pylist()
            yield pa.RecordBatch.from_arrays([pa.array([r["record_id"] for r in rows], pa.string()), pa.array([written(r, compressed) for r in rows], pa.binary())], ["record_id", "record"])

    return map_arrow(records.select("record_id", "kind", "url", "ts", "headers", "digest", "payload"), work, "record_id string, record binary")


# ---- the query -------------------------------------------------------------------------

START = 1_704_067_200_000_000
MINUTE = 60 * 1_000_000


def captures(pages: DataFrame) -> DataFrame:
    """A capture log of a table of pages: every page as a full response, a minute after the page before it, and a revisit.

    The revisit comes half a minute later, under another spelling of the URL and with a new
    date. By the page's number, some come before their page was captured and some after it
    had changed, so that every outcome occurs.
    """
    n, tag = F.col("page_id"), F.substring(F.md5(F.coalesce("html", F.lit("")).cast("binary")), 1, 16)
    base = pages.select("page_id", "url", (F.lit(START) + n * MINUTE).alias("at"), F.concat(F.lit('"'), tag, F.lit('"')).alias("tag"), F.sha2(F.coalesce("html", F.lit("")).cast("binary"), 256).alias("digest"))
    first = F.struct(
        F.concat(F.lit("f"), n.cast("string")).alias("record_id"), F.lit("response").alias("kind"), F.col("url"), F.col("at").alias("ts"),
        F.create_map(F.lit("content-type"), F.lit("text/html"), F.lit("etag"), F.col("tag"), F.lit("date"), F.col("at").cast("string")).alias("headers"), F.col("digest").cast("string").alias("digest"),
    )
    early, changed = n % 11 == 5, n % 7 == 3
    again = F.struct(
        F.concat(F.lit("r"), n.cast("string")).alias("record_id"), F.lit("revisit").alias("kind"), F.concat("url", F.lit("#again")).alias("url"),
        (F.col("at") + F.when(early, -MINUTE // 2).otherwise(MINUTE // 2)).alias("ts"),
        F.create_map(F.lit("etag"), F.when(changed, F.lit('"changed"')).otherwise(F.concat(F.lit("W/"), F.col("tag"))), F.lit("date"), (F.col("at") + MINUTE // 2).cast("string"), F.lit("set-cookie"), F.lit("no")).alias("headers"),
        F.lit(None).cast("string").alias("digest"),
    )
    return base.select("page_id", F.explode(F.array(first, again)).alias("c")).select("page_id", "c.*")


def op8_warc(spark, sf_dir: str) -> DataFrame:
    """page_id, record_id, kind, canonical_url, status, source_id, merged_headers for every capture of every page."""
    out = resolve_revisits(captures(table(spark, sf_dir, "pages").select("page_id", "url", "html")))
    pairs = F.transform(F.array_sort(F.map_entries("merged_headers")), lambda e: F.concat_ws("=", e["key"], e["value"]))
    return out.select("page_id", "record_id", "kind", "canonical_url", "status", "source_id", F.array_join(pairs, ";").alias("merged_headers"))


OP8_SQL = rf"""
WITH b AS (
  SELECT page_id, url, {START} + page_id * {MINUTE} AS cap, '"' || substr(md5(coalesce(html, '')), 1, 16) || '"' AS tag FROM pages
), r AS (
  SELECT page_id, 'f' || page_id AS record_id, 'response' AS kind, url, cap AS ts, tag, cap AS date FROM b
  UNION ALL
  SELECT page_id, 'r' || page_id, 'revisit', url || '#again', cap + CASE WHEN page_id % 11 = 5 THEN -{MINUTE // 2} ELSE {MINUTE // 2} END,
         CASE WHEN page_id % 7 = 3 THEN '"changed"' ELSE tag END, cap + {MINUTE // 2} FROM b
), s AS (SELECT *, regexp_replace(regexp_replace(trim(url), '^([A-Za-z][A-Za-z0-9+.-]*:)?//', ''), '#.*$', '') AS rest FROM r),
p AS (SELECT *, regexp_replace(regexp_replace(regexp_replace(lower(regexp_extract(rest, '^[^/?]*')), '^.*@', ''), ':(80|443)$', ''), '^www\.', '') AS host,
  regexp_replace(regexp_replace(regexp_replace(regexp_replace(rest, '^[^/?]*', ''), '([?&]){TRACKING}=[^&]*', '\1', 'g'), '&&+', '&', 'g'), '\?&', '?', 'g') AS path FROM s),
c AS (SELECT page_id, record_id, kind, ts, tag, date, host || regexp_replace(regexp_replace(path, '[?&]+$', ''), '/+$', '') AS canonical_url FROM p),
f AS (SELECT * FROM c WHERE kind = 'response'),
k AS (SELECT v.record_id AS rid, (SELECT max({{'t': f.ts, 'i': f.record_id}}) FROM f WHERE f.canonical_url = v.canonical_url AND f.ts < v.ts).i AS sid FROM c v WHERE v.kind = 'revisit'),
m AS (SELECT c.*, k.sid, f.tag AS stag FROM c LEFT JOIN k ON c.record_id = k.rid LEFT JOIN f ON k.sid = f.record_id)
SELECT page_id, record_id, kind, canonical_url,
  CASE WHEN kind = 'response' THEN 'response' WHEN sid IS NULL THEN 'no_earlier_response' WHEN tag = stag THEN 'resolved' ELSE 'validator_mismatch' END AS status,
  CASE WHEN kind = 'revisit' AND tag = stag THEN sid END AS source_id,
  CASE WHEN kind = 'revisit' AND tag = stag THEN 'content-type=text/html;date=' || date || ';etag=W/' || tag END AS merged_headers
FROM m
"""
