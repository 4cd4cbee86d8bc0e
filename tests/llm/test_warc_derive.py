"""WARC derivatives: round trips, links between records, and text against the standard library's parser."""

import gzip
import json
import re
import time
import zlib
from html.parser import HTMLParser

import pytest

from prefbook.llm.warc_derive import Page, capture_pages, derivative_report, derivatives, derive_records, digest, named, parse_record, parse_response, plain_text, record, response_record


class Visible(HTMLParser):
    SKIP = {"script", "style", "head"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.depth, self.out = 0, []

    def handle_starttag(self, tag, attrs):
        self.depth += tag in self.SKIP

    def handle_endtag(self, tag):
        self.depth -= tag in self.SKIP and self.depth > 0

    def handle_data(self, data):
        if not self.depth:
            self.out.append(data)


def squeezed(text):
    return re.sub(r"\s+", "", text)


def test_round_trip():
    source = response_record("http://a.example/x", "<p>é & b</p>")
    headers, block = parse_record(source)
    assert named(headers, "content-length") == str(len(block)) and named(headers, "WARC-Block-Digest") == digest(block)
    status, fields, payload, _ = parse_response(block)
    assert status == "HTTP/1.1 200 OK" and payload == "<p>é & b</p>".encode() and named(headers, "WARC-Payload-Digest") == digest(payload)
    assert parse_record(gzip.compress(source)) == (headers, block)
    assert record(headers[:-2], block) == source


def test_links():
    source = response_record("http://a.example/d/x", '<title>T &amp; t</title><a href="../y?a=1&amp;b=2">l</a>body')
    headers, _ = parse_record(source)
    (meta, info), (conv, text) = derivatives(source)
    for h in (meta, conv):
        assert named(h, "WARC-Refers-To") == named(headers, "WARC-Record-ID")
        assert named(h, "WARC-Target-URI") == "http://a.example/d/x"
        assert named(h, "WARC-Source-Payload-Digest") == named(headers, "WARC-Payload-Digest")
    facts = json.loads(info)
    assert facts["title"] == "T & t" and facts["links"] == [{"tag": "a", "url": "http://a.example/y?a=1&b=2"}]
    assert facts["source"]["headers"] == [list(x) for x in headers]
    assert text == b"T & tlbody" and derivatives(source) == derivatives(source)


def test_codings():
    chunked = b"HTTP/1.1 200 OK\r\nTransfer-Encoding: chunked\r\n\r\n3\r\nabc\r\n2;x=y\r\nde\r\n0\r\n\r\n"
    assert parse_response(chunked)[2] == b"abcde"
    packed = b"HTTP/1.1 200 OK\r\nContent-Encoding: gzip\r\n\r\n" + gzip.compress(b"hello")
    assert parse_response(packed)[2] == b"hello"


def response(fields, message):
    return record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:x:1>"), *fields], message)


def test_repeated_headers_stay():
    fields = [("WARC-Concurrent-To", "<urn:x:2>"), ("WARC-Concurrent-To", "<urn:x:3>")]
    (_, info), _ = derivatives(response(fields, b"HTTP/1.1 200 OK\r\nSet-Cookie: a\r\nSet-Cookie: b\r\n\r\nx"))
    facts = json.loads(info)
    assert [list(x) for x in fields] == [x for x in facts["source"]["headers"] if x[0] == "WARC-Concurrent-To"]
    assert facts["http"]["headers"] == [["Set-Cookie", "a"], ["Set-Cookie", "b"]]


@pytest.mark.parametrize("coding, body, left", [("gzip", b"<b>plain</b>", ["gzip"]), ("br", b"\x0b\x02", ["br"]), ("x-gzip", gzip.compress(b"hi"), []), ("deflate", zlib.compress(b"hi"), []), ("deflate", b"\xff\xff", ["deflate"]), ("identity", b"hi", []), ("br, gzip", gzip.compress(b"?"), ["br"])])
def test_broken_and_unknown_codings(coding, body, left):
    (_, info), (_, text) = derivatives(response([], b"HTTP/1.1 200 OK\r\nContent-Encoding: " + coding.encode() + b"\r\n\r\n" + body))
    assert json.loads(info)["http"]["codings_left"] == left and text == (b"" if left else b"hi")


def test_bad_captures(spark):
    whole = gzip.compress(response_record("http://x", "p"))
    bad = [b"\x1f\x8b garbage", whole[:-9], whole[:20], b"WARC/1.1\r\n", b"\xff" * 50, None]
    captures = spark.createDataFrame([(i, x, "k") for i, x in enumerate([*bad, whole])], "`page id` long, warc binary, kind string")
    assert {r["page id"] for r in derive_records(captures, "page id").collect()} == {len(bad)}
    odd = response([], b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=idna\r\n\r\n\xff<p>a")
    assert derivatives(odd)[1][1].endswith(b"a")


@pytest.mark.parametrize("page", ["<a " * 330_000, "<!--" * 250_000, '<a "' * 250_000, "<script>" * 125_000, "<head>" * 160_000, "\u2003" * 1_000_000, "<a href=x " + "y" * 1_000_000 + ">", "<a x='" * 160_000 + "'", "&" * 1_000_000])
def test_hostile_pages_take_linear_time(page):
    began = time.process_time()
    Page(page, "http://x")
    assert time.process_time() - began < 5


def test_marks_without_an_end_are_text():
    assert plain_text("a <b c") == "a <b c" and plain_text("a <!-- b") == "a <!-- b" and plain_text("1 < 2<p>x") == "1 < 2\nx"
    read = Page("<head><title>t <i>u</title><link href='/l'></head><!-- <a href=no> --><A HREF=/y data-src=z>v</A><script src=s>if (a<b) '<a href=no>'</script>w", "http://h/")
    assert (read.title, read.text) == ("t u", "v w") and [x["url"] for x in read.links] == ["http://h/l", "http://h/y", "http://h/s"]


def test_not_responses():
    assert derivatives(b"") == [] and derivatives(b"no record\r\n\r\n") == []
    assert derivatives(record([("WARC-Type", "request")], b"x")) == []


def test_text_matches_parser(spark, small):
    for row in spark.read.parquet(f"{small}/pages.parquet").collect():
        parser = Visible()
        parser.feed(row.html)
        assert squeezed(plain_text(row.html)) == squeezed("".join(parser.out))


def test_table(spark, small):
    pages = spark.read.parquet(f"{small}/pages.parquet")
    made = derivative_report(pages).collect()
    assert len(made) == 2 * pages.count() and len({r.record_id for r in made}) == len(made)
    whole = derive_records(capture_pages(pages)).first()
    headers, block = parse_record(bytes(whole.warc))
    assert block == bytes(whole.block) and named(headers, "WARC-Record-ID") == whole.record_id


def test_edges(spark):
    pages = spark.createDataFrame([(1, None, None, "k"), (1, None, None, "k"), (None, "http://x", "a" * 500000, "k")], "page_id long, url string, html string, kind string")
    made = derivative_report(pages).collect()
    assert len(made) == 6 and {r.block_length for r in made if r.kind == "conversion"} == {0, 500000}
    assert derivative_report(pages.limit(0)).count() == 0
