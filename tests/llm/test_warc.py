import base64
import gzip
import hashlib
import json
import time
import zlib
from html.parser import HTMLParser
from urllib.parse import urljoin

import pytest
from pyarrow import fs

from recordlink.llm import common, warc


def test_parse_what_build_makes():
    one = warc.build("response", {"WARC-Record-ID": "<a>", "X": "é"}, b"ab\r\n\r\nc")
    two = warc.build("warcinfo", {"WARC-Record-ID": "<b>"}, b"")
    got = list(warc.parse(one + two))
    assert [(h["warc-type"], h["warc-record-id"], b) for h, b in got] == [("response", "<a>", b"ab\r\n\r\nc"), ("warcinfo", "<b>", b"")]
    assert list(warc.parse(gzip.compress(one) + gzip.compress(two))) == got


def test_text_and_links():
    page = "<html><head><title>A &amp; B</title><style>p{}</style></head><body><p>One&nbsp;two</p><script>no()</script><!-- no --><div>3 &lt; 4<br>five<a href='/x?a=1&amp;b=2'>go</a></div><img src=i.png></body>"
    assert warc.plain_text(page) == "A & B\nOne two\n3 < 4\nfivego"
    got = warc.facts(page, "http://h.example/d/")
    assert got["title"] == "A & B"
    assert [x["url"] for x in got["links"]] == ["http://h.example/x?a=1&b=2", "http://h.example/d/i.png"]
    more = """<a title="x href=no" data-href=no2 HREF = "a>b">q</a><script src=s.js>var a = "<a href='z'>"</script><img alt='<a href="n">' src='i j.png'><a>no</a></a href=e>"""
    assert [(x["path"], x["url"]) for x in warc.facts(more, "http://h.example/")["links"]] == [("a@href", "http://h.example/a>b"), ("script@src", "http://h.example/s.js"), ("img@src", "http://h.example/i j.png")]
    assert warc.plain_text("3 < 4 <b>x</b> > <p") == "3 < 4 x > <p"


class Reader(HTMLParser):
    """The standard library's parser, as a second opinion on text, title and links."""

    def __init__(self, uri):
        super().__init__(convert_charrefs=True)
        self.uri, self.text, self.links, self.title, self.hidden, self.in_title = uri, [], [], None, 0, False

    def handle_starttag(self, tag, attrs):
        want = {"a": "href", "area": "href", "link": "href", "img": "src", "script": "src", "iframe": "src"}.get(tag)
        value = next((v for k, v in attrs if k == want), None) if want else None
        if value is not None and not self.hidden:
            self.links.append((f"{tag}@{want}", urljoin(self.uri, value)))
        self.hidden += tag in ("script", "style", "noscript", "template")
        self.in_title |= tag == "title"
        self.text.append("\n" if tag in warc.BLOCKS else "")

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        self.hidden -= tag in ("script", "style", "noscript", "template")

    def handle_endtag(self, tag):
        self.hidden -= tag in ("script", "style", "noscript", "template")
        self.in_title &= tag != "title"
        self.text.append("\n" if tag in warc.BLOCKS else "")

    def handle_data(self, data):
        if self.in_title:
            self.title = (self.title or "") + data
        if not self.hidden:
            self.text.append(data)


def second(markup, uri):
    r = Reader(uri)
    r.feed(markup)
    r.close()
    lines = (" ".join(x.split()) for x in "".join(r.text).split("\n"))
    return "\n".join(x for x in lines if x), r.links, " ".join(r.title.split()) if r.title is not None else None


def test_pages_against_the_standard_parser(spark, sf_dir):
    """Every page of the table: the derived records hold what an independent parser and plain hashing give."""
    from recordlink.llm.queries import op5_warc

    rows = spark.read.parquet(f"{sf_dir}/pages.parquet").collect()
    made = {(r["page_id"], r["record_type"]): r for r in op5_warc(spark, sf_dir).collect()}
    whole = {(r["page_id"], r["record_type"]): bytes(r["record"]) for r in warc.derivatives(warc.pages_as_warc(spark.read.parquet(f"{sf_dir}/pages.parquet")), ["page_id"]).collect()}
    assert len(made) == 2 * len(rows)
    sha = lambda b: "sha1:" + base64.b32encode(hashlib.sha1(b).digest()).decode()
    for p in rows:
        text, links, title = second(p["html"] or "", p["url"] or "")
        c, m = made[p["page_id"], "conversion"], made[p["page_id"], "metadata"]
        assert c["n_chars"] == len(text) and c["block_digest"] == sha(text.encode()) and m["title"] == title and m["n_links"] == len(links)
        assert c["source_payload_digest"] == m["source_payload_digest"] == sha((p["html"] or "").encode())
        assert c["refers_to"] == m["refers_to"] and len({c["record_id"], m["record_id"], c["refers_to"]}) == 3
        for kind in ("conversion", "metadata"):
            raw = whole[p["page_id"], kind]
            head, _, body = raw.partition(b"\r\n\r\n")
            lines = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
            assert made[p["page_id"], kind]["record_sha256"] == hashlib.sha256(raw).hexdigest()
            assert lines["WARC-Type"] == kind and lines["WARC-Refers-To"] == c["refers_to"] and lines["WARC-Refers-To-Target-URI"] == lines["WARC-Target-URI"] and lines["WARC-Refers-To-Date"] == lines["WARC-Date"]
            assert len(body) == int(lines["Content-Length"]) + 4
            if kind == "metadata":
                assert [(x["path"], x["url"]) for x in json.loads(body)["html"]["links"]] == links


def sent(headers, body, **more):
    block = b"HTTP/1.1 200 OK\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers).encode() + b"\r\n" + body
    return warc.build("response", {"WARC-Target-URI": "http://h.example/"} | more, block)


def test_bodies_are_decoded():
    page = ("<p>" + "word " * 500).encode()
    pieces = b"".join(f"{len(page[i : i + 100]):x};x=y\r\n".encode() + page[i : i + 100] + b"\r\n" for i in range(0, len(page), 100)) + b"0\r\n\r\n"
    raw = zlib.compressobj(wbits=-15)
    cases = [([("Transfer-Encoding", "chunked")], pieces), ([("Content-Encoding", "gzip")], gzip.compress(page)), ([("content-encoding", "DEFLATE")], zlib.compress(page)), ([("Content-Encoding", "deflate")], raw.compress(page) + raw.flush()), ([("Content-Encoding", "gzip")], page), ([("Transfer-Encoding", "chunked")], page)]
    gz = gzip.compress(page)
    cases.append(([("Transfer-Encoding", "chunked"), ("Content-Encoding", "gzip")], f"{len(gz):x}\r\n".encode() + gz + b"\r\n0\r\n\r\n"))
    for headers, body in cases:
        ((head, block),) = warc.parse(sent(headers, body))
        made = {kind: (own, data) for kind, own, data, _ in warc.derive(head, block)}
        assert made["conversion"][1].decode() == " ".join(["word"] * 500), headers
        assert made["metadata"][0]["WARC-Source-Payload-Digest"] == warc.digest(body)


def test_sources_without_ids_have_derivatives_of_their_own():
    one, two = sent([], b"<p>a"), sent([], b"<p>b")
    ids = [own["WARC-Record-ID"] for head, block in warc.parse(one + two + one) for _, own, _, _ in warc.derive(head, block)]
    assert len(set(ids)) == 6
    assert all("WARC-Refers-To" not in own for head, block in warc.parse(one) for _, own, _, _ in warc.derive(head, block))


def test_a_fault_in_a_member_keeps_those_before():
    one = sent([], b"<p>a")
    bad = bytearray(gzip.compress(sent([], b"<p>b" * 100)))
    bad[15:25] = bytes(10)
    for data in (gzip.compress(one) + bytes(bad), gzip.compress(one) + bytes(bad[:40]), one + b"WARC/1.0\r\nContent-Length: 99\r\n\r\nx"):
        got = []
        with pytest.raises(ValueError):
            for head, _ in warc.parse(data):
                got.append(head["warc-type"])
        assert got == ["response"]
    half = len(one) // 2  # a record across two members
    assert [b for _, b in warc.parse(gzip.compress(one[:half]) + gzip.compress(one[half:]))] == [b for _, b in warc.parse(one)]


def test_scans_are_linear():
    """A megabyte of each kind of unfinished markup."""
    for part in ("<a ", "<a href", "<p", "<title", "<!--", "<script", "</script ", "<a href='", '<a x="', "<a x=\">", "<a x='\">", "<", ">", "&", "<a href = ", "<a " + "x" * 9, "<img src=\"'"):
        text = part * ((1 << 20) // len(part))
        for tail in ("", ">"):
            began = time.process_time()
            warc.facts(text + tail, "http://h.example/")
            warc.plain_text(text + tail)
            assert time.process_time() - began < 8, part


def test_pages_have_two_linked_records(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    sources = {r["page_id"]: next(warc.parse(bytes(r["warc"]))) for r in warc.pages_as_warc(pages).collect()}
    rows = warc.derivatives(warc.pages_as_warc(pages), ["page_id"]).collect()
    assert len(rows) == 2 * len(sources) and len({r["record_id"] for r in rows}) == len(rows)
    for r in rows:
        head, block = sources[r["page_id"]]
        ((own, body),) = warc.parse(bytes(r["record"]))
        assert own["warc-type"] == r["record_type"] and own["warc-record-id"] == r["record_id"]
        assert own["warc-refers-to"] == r["refers_to"] == head["warc-record-id"]
        assert own["warc-target-uri"] == head["warc-target-uri"] and own["warc-date"] == head["warc-date"]
        assert own["warc-block-digest"] == warc.digest(body) == r["block_digest"]
        assert own["warc-source-payload-digest"] == head["warc-payload-digest"] == warc.digest(warc.split_http(block)[2])
        if r["record_type"] == "metadata":
            meta = json.loads(body)
            assert meta["source"]["warc-record-id"] == head["warc-record-id"] and meta["http"]["status"] == "HTTP/1.1 200 OK"
            assert ["Content-Type", "text/html; charset=utf-8"] in meta["http"]["headers"]
        else:
            assert body.decode() == warc.plain_text(warc.split_http(block)[2].decode())


def test_odd_input(spark):
    ok = warc.response("http://h.example/", "<p>x", "k")
    rows = [(1, None), (1, None), (2, b""), (3, b"junk"), (4, ok + ok), (5, ok[:-30]), (6, warc.build("request", {}, b"GET /")), (7, warc.response("", "", "")), (8, ok + b"rest")]
    df = spark.createDataFrame([(i, d, "t") for i, d in rows], "page_id long, warc binary, title string")
    got = warc.derivatives(df, ["page_id", "title"])
    count = {}
    for r in got.collect():
        count.setdefault(r["page_id"], []).append(bool(r["error"]))
        assert r["title_in"] == "t"
    assert count == {1: [True, True], 2: [True], 3: [True], 4: [False] * 4, 5: [True], 7: [False, False], 8: [False, False, True]}
    assert warc.derivatives(df.where("false"), ["page_id"]).count() == 0
    nulls = spark.createDataFrame([(None, None, None)], "page_id long, url string, html string")
    assert warc.derivatives(warc.pages_as_warc(nulls), ["page_id"]).count() == 2


def test_files(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    made = warc.derivatives(warc.pages_as_warc(pages), ["page_id"])
    folder = common.shared_folder(spark, "warc")
    assert warc.write_files(made, folder) == made.count()
    where, path = fs.FileSystem.from_uri(folder)
    found = [h for f in where.get_file_info(fs.FileSelector(path)) for h, _ in warc.parse(where.open_input_stream(f.path, compression=None).read())]
    assert sorted(h["warc-record-id"] for h in found) == sorted(r["record_id"] for r in made.collect())
