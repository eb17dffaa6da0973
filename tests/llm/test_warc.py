import gzip
import random

import pytest
from pyspark.sql import functions as F

from distinct_bounds.llm import warc

SCHEMA = "record_id string, kind string, url string, ts long, headers map<string,string>, digest string, STATUS int"


def brute(rows):
    """(status, source, headers) of each row."""
    out = []
    full = {r[0]: r for r in rows if r[1] == "response"}
    for id_, kind, url, ts, headers, digest, canon in rows:
        if kind != "revisit":
            out.append((id_, "response" if kind == "response" else "other", None, None))
            continue
        found = [(r[3], r[0]) for r in rows if r[1] == "response" and r[6] == canon and canon is not None and None not in (r[3], ts) and r[3] < ts]
        if not found:
            out.append((id_, "no_earlier_response", None, None))
            continue
        base = full[max(found)[1]]
        own, theirs = headers or {}, base[4] or {}
        same = all(a is None or b is None or a.removeprefix("W/") == b.removeprefix("W/") for a, b in [(own.get("etag"), theirs.get("etag"))])
        same = same and all(a is None or b is None or a == b for a, b in [(own.get("last-modified"), theirs.get("last-modified")), (digest, base[5])])
        if not same:
            out.append((id_, "validator_mismatch", None, None))
        else:
            out.append((id_, "resolved", base[0], theirs | {k: v for k, v in own.items() if k in warc.PERMITTED}))
    return sorted(out, key=str)


def test_revisits_equal_brute_force(spark):
    rng = random.Random(5)
    urls = [("http://a.com/x", "a.com/x"), ("https://www.A.com:443/x/#f", "a.com/x"), ("http://a.com/x?utm_source=1", "a.com/x"), ("http://b.com/y?q=1&ref=z", "b.com/y?q=1"), (None, None)]
    rows = []
    for i in range(400):
        url, canon = rng.choice(urls)
        headers = rng.choice([None, {}, {"etag": '"1"', "x": "a"}, {"etag": 'W/"1"', "date": "d", "set-cookie": "c"}, {"etag": '"2"'}, {"last-modified": "m"}])
        rows.append((f"r{i}", rng.choice(["response", "revisit", "revisit", "request"]), url, rng.choice([None, *range(0, 40 * warc.BLOCK, warc.BLOCK // 3)]), headers, rng.choice([None, "d1", "d2"]), canon))
    df = spark.createDataFrame([(*r[:6], 1) for r in rows], SCHEMA).repartition(4)
    made = warc.resolve_revisits(df)
    assert made.columns == ["record_id", "kind", "url", "ts", "headers", "digest", "canonical_url", "status", "source_id", "merged_headers"]
    got = sorted(((r["record_id"], r["status"], r["source_id"], r["merged_headers"]) for r in made.collect()), key=str)
    assert got == brute(rows)
    assert warc.resolve_revisits(df.limit(0)).count() == 0
    twice = warc.resolve_revisits(df.unionByName(df))
    assert twice.count() == 2 * len(rows)


@pytest.mark.parametrize("url,want", [("HTTP://WWW.Ex.com:80", "ex.com"), ("https://u@ex.com/a/?utm_x=1&b=2&&ref=3#z", "ex.com/a/?b=2"), ("//ex.com/a//", "ex.com/a"), ("ex.com/A?ref=1", "ex.com/A"), (None, None), ("", "")])
def test_canonical_urls(spark, url, want):
    got = spark.createDataFrame([(url,)], "u string").select(warc.canonical(F.col("u")).alias("c")).first()["c"]
    assert got == want


def test_equal_record_ids_give_one_answer(spark):
    rows = [("r", "response", "http://a.com/x", 5, {"x": v}, "d", 1) for v in ("3", "1", "2")] + [("r", "response", "http://b.com/x", 5, {"x": "0"}, "d", 1), ("r", "response", "http://a.com/x", 4, {"x": "0"}, "d", 1)]
    rows += [("q", "revisit", "http://a.com/x", 9, {"date": "t"}, "d", 1), ("p", "revisit", "http://a.com/x", 9, {"note": "y" * 300_000}, "d", 1)]
    for parts in (1, 3, 7):
        got = {r["record_id"]: r for r in warc.resolve_revisits(spark.createDataFrame(rows, SCHEMA).repartition(parts)).filter("kind = 'revisit'").collect()}
        assert got["q"]["merged_headers"] == {"x": "1", "date": "t"} and got["p"]["status"] == "resolved"


def test_archives_round_trip(spark, tmp_path):
    rows = [("<a>", "response", "http://x.com/", 1_700_000_000_000_000, {"etag": '"1"', "content-type": "text/html"}, "sha1:Q", b"<p>\r\n\r\nWARC/1.0 in a page</p>"), ("<b>", "revisit", "http://x.com/", 1_700_000_001_500_000, {"date": "now"}, None, b""), ("<c>", "response", None, None, {}, None, None)]
    df = spark.createDataFrame(rows, warc.RECORDS)
    for name, compressed in (("one.warc.gz", True), ("two.warc", False)):
        parts = {r["record_id"]: bytes(r["record"]) for r in warc.encoded(df, compressed).collect()}
        (tmp_path / name).write_bytes(b"".join(parts[i] for i in ("<a>", "<b>", "<c>")))
        got = {r["record_id"]: r for r in warc.read(spark, str(tmp_path / name)).collect()}
        assert set(got) == {"<a>", "<b>", "<c>"}
        assert (got["<a>"]["url"], got["<a>"]["ts"], got["<a>"]["headers"], bytes(got["<a>"]["payload"])) == ("http://x.com/", rows[0][3], rows[0][4], rows[0][6])
        assert got["<b>"]["kind"] == "revisit" and got["<b>"]["ts"] == rows[1][3] and got["<c>"]["ts"] is None
    cut = gzip.compress(b"WARC/1.0\r\nWARC-Type: response\r\nContent-Length: 4\r\n\r\nabcd\r\n\r\n") + b"\x1f\x8bbroken"
    (tmp_path / "cut.warc.gz").write_bytes(cut)
    assert warc.read(spark, str(tmp_path / "cut.warc.gz")).count() == 1
    (tmp_path / "none.warc").write_bytes(b"")
    assert warc.read(spark, str(tmp_path / "none.warc")).count() == 0


def test_query_has_every_outcome(spark, tmp_path):
    spark.createDataFrame([(i, f"http://h{i % 9}.com/p{i % 30}", "<p>x</p>" if i % 30 < 20 else f"<p>{i}</p>") for i in range(120)], "page_id long, url string, html string").write.parquet(str(tmp_path / "pages.parquet"))
    made = warc.op8_warc(spark, str(tmp_path))
    assert made.count() == 240
    assert {r["status"] for r in made.select("status").distinct().collect()} == {"response", "resolved", "no_earlier_response", "validator_mismatch"}
