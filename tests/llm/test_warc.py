"""Derivatives: linked records, brute-force text, forged fields, encodings, archives read back, odd tables."""

import base64
import gzip
import hashlib
import html.parser
import random
import time
import zlib

import pytest
import zstandard
from pyspark.sql import functions as F

from spark_curation.io import table
from spark_curation.llm import warc_derivatives as warc
from tests.conftest import DATA

PAGE = "<html lang=en><head><title>T</title></head><p>A &amp; B<p>C <a href='/x'>l</a>"


def test_round_trip():
    src = warc.response(1, "http://a.b/?q=1", PAGE, "2024-01-01T00:00:00Z")
    meta, text = warc.derive(src)
    data = b"".join(map(warc.serialize, (src, meta, text)))
    (f0, b0), (f1, b1), (f2, b2) = warc.parse(data)
    assert f1["warc-refers-to"] == f2["warc-refers-to"] == f0["warc-record-id"]
    assert b2.decode() == "A & B\nC l" and b"outlink: /x" in b1 and b"http-content-type: text/html" in b1 and b"title: T" in b1 and b"languages-declared: en" in b1
    for f, b in ((f0, b0), (f1, b1), (f2, b2)):
        assert f["warc-block-digest"] == "sha1:" + base64.b32encode(hashlib.sha1(b).digest()).decode() and int(f["content-length"]) == len(b)
    assert warc.derive(src) == [meta, text]
    assert list(warc.parse(b"".join(gzip.compress(warc.serialize(r)) for r in (src, meta, text)))) == [(f0, b0), (f1, b1), (f2, b2)]


def test_values_cannot_forge_fields():
    evil = "http://a/\r\nWARC-Type: evil\r\n\r\nx"
    src = warc.response(1, evil, f'<a href="/q\r\nx: y">l</a><title>a\r\nb: c</title>', "2024\r\nWARC-Type: evil")
    for record in (src, *warc.derive(src)):
        ((fields, _),) = warc.parse(warc.serialize(record))
        assert fields["warc-type"] == record[1]
    block = b"HTTP/1.1 200 OK\r\nX: 1\rY\r\nContent-Type: text/html\r\n\r\nhi"
    meta = warc.derive((*src[:10], block))[0][-1]
    assert all(b": " in x for x in meta.split(b"\r\n")[:-1]) and b"\nx: y" not in meta


@pytest.mark.parametrize("code", ["gzip", "deflate", "zstd", "chunked", "gzip, chunked", "none", "broken"])
def test_encoded_bodies(code):
    body = "<p>grün & ok</p>".encode("latin-1")
    head = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=latin-1\r\n"
    if code in ("gzip", "gzip, chunked", "broken"):
        head += "Content-Encoding: gzip\r\n"
        body = gzip.compress(body) if code != "broken" else body
    elif code in ("deflate", "zstd"):
        head += f"Content-Encoding: {code}\r\n"
        body = zlib.compress(body) if code == "deflate" else zstandard.ZstdCompressor().compress(body)
    if "chunked" in code:
        head += "Transfer-Encoding: chunked\r\n"
        body = b"5\r\n" + body[:5] + b"\r\n" + f"{len(body) - 5:x};q=1\r\n".encode() + body[5:] + b"\r\n0\r\n\r\n"
    record = (1, "response", "<id>", None, "u", "d", "c", "b", "p", 0, head.encode() + b"\r\n" + body)
    assert warc.derive(record)[1][-1].decode() == "grün & ok"


class Reference(html.parser.HTMLParser):
    """Visible text by the library's parser, for well-formed pages."""

    def __init__(self):
        super().__init__()
        self.lines, self.depth = [""], 0

    def handle_starttag(self, tag, attrs):
        if tag in warc.HIDDEN:
            self.depth += 1
            self.lines[-1] += " "
        if tag in warc.LINES:
            self.lines.append("")
        elif tag in warc.CELLS:
            self.lines[-1] += " "

    def handle_endtag(self, tag):
        self.depth -= tag in warc.HIDDEN
        self.handle_starttag(tag, []) if tag in warc.LINES | warc.CELLS else None

    def handle_data(self, data):
        if not self.depth:
            self.lines[-1] += data


def test_text_equals_a_parser(spark):
    r = random.Random(3)
    word = lambda: r.choice(["a", "b&amp;c", "d  e", "f\ng", "1 &lt; 2"])

    def some(depth):
        tag = r.choice(["p", "div", "b", "i", "li", "td", "span", "script", "svg", "h2"])
        inner = word() if depth == 0 or tag in ("script", "svg") else "".join(r.choice([word, lambda: some(depth - 1)])() for _ in range(3))
        return f'<{tag} class="x > y">{inner}</{tag}>'

    pages = ["".join(some(3) for _ in range(4)) for _ in range(300)] + [p.html for p in table(spark, DATA, "pages").select("html").collect()]
    for page in pages:
        ref = Reference()
        ref.feed(page)
        ref.close()
        assert warc.plain_text(page) == "\n".join(x for x in (" ".join(t.split()) for t in ref.lines) if x)


def test_text_after_elements_that_stay_open():
    text = warc.plain_text
    assert text("<html><head><title>t</title><body><p>one<p>two") == "one\ntwo"
    assert text("<html><head><title>t</title>loose <b>text</b><p>one") == "loose text\none"
    assert text("<p>a<svg width=1/> b<iframe/> c<object> d<p>e") == "a b c d\ne"
    assert text("<head><title>t</title>x</head><p>a<svg>x</svg> b<script>x") == "a b"


@pytest.mark.parametrize("unit", ["<title ", "<a ", "<a href=", "<head>", "<svg>", "<!--", '<a x="', "<p>x"])
def test_hostile_pages_take_time_in_proportion(unit):
    took = []
    for size in (1 << 16, 1 << 19):
        began = time.process_time()
        warc.read_page((unit * (size // len(unit) + 1))[:size])
        took.append(time.process_time() - began)
    assert took[1] < 20 * max(took[0], 0.02)


def test_archives_are_read_back(spark, tmp_path):
    rows = [(1, "http://a", PAGE), (2, "http://b", None), (3, None, "plain"), (None, "http://c", "<p>x" * 3000)]
    pages = spark.createDataFrame([(*r, "2020-02-02T00:00:00Z") for r in rows], "page_id long, url string, html string, at string")
    records = warc.responses(pages, F.col("at"))
    members = {m.record_id: m.member for m in warc.archive_members(records).collect()}
    (tmp_path / "one.warc.gz").write_bytes(b"".join(list(members.values())[:2]))
    (tmp_path / "two.warc").write_bytes(b"".join(gzip.decompress(m) for m in list(members.values())[2:]))
    (tmp_path / "none.warc").write_bytes(b"")
    back = warc.read_archives(spark, str(tmp_path))
    want = {tuple(r)[1:] for r in records.collect()}
    assert {(*tuple(r)[1:],) for r in back.collect()} == want
    assert {r.block_sha256 for r in warc.digests(warc.derivatives(back)).collect()} == {r.block_sha256 for r in warc.digests(warc.derivatives(records)).collect()}


def test_odd_tables(spark):
    rows = [(1, None, None), (1, None, None), (2, "u", ""), (None, "u", "<p>" + "word " * 50_000)]
    pages = spark.createDataFrame([(*r, "clash", 1) for r in rows], "page_id long, url string, html string, block string, date int")
    out = warc.digests(warc.derivatives(warc.responses(pages))).collect()
    assert len(out) == 8 and sorted(r.n_chars for r in out if r.record_type == "conversion") == [0, 0, 0, 249_999]
    assert warc.derivatives(warc.responses(pages.where("false"))).count() == 0
