"""WARC records: round trips, links and digests; page reading on hostile input."""

import time

import pytest

from ladderset.llm import warc


def test_round_trip_and_links():
    page = '<html lang="de"><head><title>A &amp; B</title><script>var x="</p>";</script></head><body><p>One<br>two &lt;3</p><!-- no --><a href="/x?a=1&amp;b=2">go</a></body></html>'
    response = warc.response_record(7, "http://e.org/d/ e\n", page)
    for squeeze in (False, True):
        (back,) = warc.parse_records(response.to_bytes(squeeze))
        assert back == response
    meta, text = warc.derive(response)
    assert text.block.decode() == "One\ntwo <3\ngo" and text.get("WARC-Block-Digest") == warc.digest(text.block)
    assert {r.get("WARC-Refers-To") for r in (meta, text)} == {response.get("WARC-Record-ID")}
    body = meta.block.decode()
    for part in ("title: A & B", "language: de", "outlink: http://e.org/x?a=1&b=2", "http-Content-Type: text/html; charset=utf-8", "source-WARC-Payload-Digest: " + warc.digest(page.encode())):
        assert part + "\r\n" in body
    assert meta.get("WARC-Concurrent-To") == text.get("WARC-Record-ID")
    many = response.to_bytes() + meta.to_bytes() + text.to_bytes()
    assert list(warc.parse_records(many)) == [response, meta, text]


@pytest.mark.parametrize("page", ["<" * 200_000, '<a href="' * 50_000, "<script>" * 50_000, "<!--" * 100_000, "&lt;" * 100_000, "<p '" * 50_000, "</" * 100_000])
def test_hostile_pages_are_linear(page):
    began = time.time()
    warc.read_page(page)
    assert time.time() - began < 3


def test_query(spark):
    pages = spark.createDataFrame([(1, "http://a", "<p>x", 5), (1, "http://a", "<p>x", 5), (2, None, None, 5), (None, "http://b", "", 5)], "page_id long, url string, html string, record int")
    got = warc.derivatives(warc.response_records(pages)).collect()
    assert len(got) == 8 and all(r["kind"] in ("metadata", "conversion") for r in got)
    for r in got:
        (rec,) = warc.parse_records(bytes(r["record"]))
        assert rec.get("WARC-Record-ID") == r["record_id"] and len(rec.block) == r["content_length"] and warc.digest(rec.block) == r["block_digest"]
    broken = warc.derivatives(spark.createDataFrame([(3, bytearray(b"junk")), (4, None)], "page_id long, record binary")).collect()
    assert [r["kind"] for r in broken] == ["broken"]
    assert warc.derivatives(warc.response_records(pages.limit(0))).count() == 0


def test_files(spark, tmp_path):
    whole = b"".join(warc.response_record(i, f"http://e/{i}", f"<p>{i}").to_bytes(True) for i in range(5))
    (tmp_path / "a.warc.gz").write_bytes(whole)
    got = warc.derivatives(warc.read_warc_files(spark, f"file://{tmp_path}")).where("kind = 'conversion'").collect()
    assert len(got) == 5


def test_records_are_streamed(spark, tmp_path):
    """The same derivatives as from whole files, a page that quotes a record and empty blocks among them."""
    quoting = "<pre>text\r\n\r\nWARC/1.0\r\nWARC-Type: response\r\n\r\n</pre>"
    records = [warc.response_record(i, f"http://e/{i}", quoting if i % 5 == 2 else f"<p>{i}" if i % 5 else "") for i in range(40)]
    for name, squeeze in (("a.warc", False), ("b.warc.gz", True)):
        (tmp_path / name).write_bytes(b"".join(r.to_bytes(squeeze) for r in records))
        path = f"file://{tmp_path}/{name}"
        whole, streamed = (sorted((r["record_id"], r["kind"], r["refers_to"], r["block_digest"]) for r in warc.derivatives(f(spark, path)).collect()) for f in (warc.read_warc_files, warc.read_warc_records))
        assert whole == streamed and len(whole) == 80


def test_derivatives_against_a_plain_reading(spark):
    """Every page of the table: links, digests, headers and text, found again with regular expressions and the standard library."""
    import base64
    import hashlib
    import html as entities
    import re

    sha = lambda b: "sha1:" + base64.b32encode(hashlib.sha1(b).digest()).decode()
    pages = {r["page_id"]: r for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect()}
    got = warc.derivatives(warc.response_records(spark.read.parquet("/root/testdata/sf0.001/pages.parquet"))).collect()
    assert len(got) == 2 * len(pages)
    responses = {r["page_id"]: next(warc.parse_records(bytes(r["record"]))) for r in warc.response_records(spark.read.parquet("/root/testdata/sf0.001/pages.parquet")).collect()}
    for r in got:
        page, response = pages[r["page_id"]], responses[r["page_id"]]
        record = next(warc.parse_records(bytes(r["record"])))
        assert r["refers_to"] == response.get("WARC-Record-ID") and r["target_uri"] == response.get("WARC-Target-URI")
        assert r["block_digest"] == sha(record.block) and r["source_payload_digest"] == sha(page["html"].encode())
        body = record.block.decode()
        if r["kind"] == "metadata":
            assert f"source-WARC-Record-ID: {response.get('WARC-Record-ID')}\r\n" in body and "http-Content-Type: text/html" in body
            links = re.findall(r"<a\b[^>]*?\bhref=\"([^\"]*)\"", re.sub(r"(?s)<!--.*?-->|<(script|style)\b.*?</\1>", "", page["html"]))
            assert body.count("outlink: ") == len(links)
        else:
            bare = re.sub(r"(?s)<!--.*?-->|<(script|style|title|head)\b.*?</\1>|<[^>]*>", " ", page["html"])
            mine, theirs = (set(re.findall(r"\w+", x)) for x in (body, entities.unescape(bare)))
            assert len(mine ^ theirs) <= 0.02 * len(theirs) + 2, (r["page_id"], mine ^ theirs)


def test_a_bad_response_ends_only_itself(spark, tmp_path):
    good = [warc.response_record(i, f"http://e/{i}", f"<p>{i}") for i in range(4)]
    dns = warc.make_record("response", "<urn:uuid:dns>", b"e. 60 IN A 127.0.0.1\n", "text/dns", [("WARC-Target-URI", "dns:e")])
    bare = warc.make_record("response", "<urn:uuid:lf>", b"HTTP/1.1 200 OK\nContent-Type: text/html\n\n<p>x", "application/http", [])
    info = warc.make_record("warcinfo", "<urn:uuid:info>", b"a: b\r\n", "application/warc-fields")
    whole = [info, dns, *good[:2], bare, *good[2:]]
    for name, squeeze in (("a.warc", False), ("b.warc.gz", True)):
        (tmp_path / name).write_bytes(b"".join(r.to_bytes(squeeze) for r in whole))
        got = warc.derivatives(warc.read_warc_files(spark, f"file://{tmp_path}/{name}")).collect()
        assert [r["kind"] for r in got] == ["broken", *["metadata", "conversion"] * 2, "broken", *["metadata", "conversion"] * 2]
        bad = [r for r in got if r["kind"] == "broken"]
        assert [(r["refers_to"], r["reason"]) for r in bad] == [("<urn:uuid:dns>", "no HTTP head"), ("<urn:uuid:lf>", "no HTTP head")]
        assert [next(warc.parse_records(bytes(r["record"]))) for r in bad] == [dns, bare]
    (tmp_path / "c.warc").write_bytes(b"".join(r.to_bytes() for r in whole) + b"junk")
    got = warc.derivatives(warc.read_warc_files(spark, f"file://{tmp_path}/c.warc")).collect()
    assert [r["kind"] for r in got].count("conversion") == 4 and got[-1]["kind"] == "broken" and got[-1]["reason"].startswith("no record at byte")
