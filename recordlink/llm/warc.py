"""WARC derivatives: each response becomes a metadata record and a plain-text conversion record.

Both refer to the response by its record id, target URI and date, keep its payload digest, and carry the response's HTTP
headers (metadata).  Their own ids are derived from the source's id and their kind (for a source without an id, from its bytes
and its place in the file), so a repeated run or a lost executor yields the same bytes.

Bodies are read as they were sent: chunked transfer coding and gzip or deflate content coding are undone, at most ``MAX_BODY``
bytes of them.  All scans of markup are linear in its length.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import json
import re
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import urljoin

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

VERSION = b"WARC/1.1"
CRLF = b"\r\n"
#: A task's memory cannot spill: an opened gzip member, or a decoded body, of more bytes is a fault.
MAX_MEMBER = MAX_BODY = 1 << 28


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join(parts))}>"


def build(kind: str, headers: dict[str, str], block: bytes) -> bytes:
    lines = [VERSION, f"WARC-Type: {kind}".encode(), *(f"{k}: {v}".encode() for k, v in headers.items()), f"Content-Length: {len(block)}".encode()]
    return CRLF.join(lines) + CRLF * 2 + block + CRLF * 2


class _Cut(ValueError):
    """The bytes end within a record."""


def _records(data: bytes, start: int = 0) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(where the record begins, where it ends, headers, block) of the records that follow each other from ``start``."""
    at = start
    while at < len(data):
        if data[at : at + 2] == CRLF:
            at += 2
            continue
        if not b"WARC/".startswith(data[at : at + 5]):
            raise ValueError(f"no record at byte {at}")
        end = data.find(CRLF * 2, at)
        if end < 0:
            raise _Cut("headers without an end")
        head: dict[str, str] = {}
        name = ""
        for line in data[at:end].split(CRLF)[1:]:
            if line[:1] in (b" ", b"\t") and name:
                head[name] += " " + line.strip().decode("utf-8", "replace")
                continue
            key, _, value = line.partition(b":")
            name = key.strip().decode("utf-8", "replace").lower()
            head[name] = value.strip().decode("utf-8", "replace")
        size = head.get("content-length", "")
        if not size.isdecimal():
            raise ValueError("a block without a length")
        stop = end + 4 + int(size)
        if stop > len(data):
            raise _Cut("a block is cut")
        yield at, stop, head, data[end + 4 : stop]
        at = stop


def members(data: bytes) -> Iterator[bytes]:
    """Each gzip member of the data, opened."""
    while data:
        opener = zlib.decompressobj(31)
        try:
            out = opener.decompress(data, MAX_MEMBER)
        except zlib.error as e:
            raise ValueError(f"gzip: {e}") from None
        if not opener.eof:
            raise ValueError("a gzip member is cut" if not opener.unconsumed_tail else "a gzip member is larger than MAX_MEMBER")
        yield out
        data = opener.unused_data.lstrip(b"\0")


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers by lower-cased name, block) of each record, gzip members being opened one by one.

    Raises ValueError at a fault, after the records before it.  The place of a record in the opened bytes is under the name "".
    """
    left, base = b"", 0  # what earlier members hold of a record that goes on in the next
    for part in members(data) if data[:2] == b"\x1f\x8b" else [data]:
        left += part
        done = 0
        try:
            for at, stop, head, block in _records(left):
                yield head | {"": str(base + at)}, block
                done = stop
        except _Cut:
            pass
        left, base = left[done:], base + done
    for _ in _records(left):
        pass


def split_http(block: bytes) -> tuple[str, list[tuple[str, str]], bytes]:
    """(status line, headers in order, body) of an HTTP response; a block without a header part is all body."""
    if not block.startswith(b"HTTP/"):
        return "", [], block
    head, sep, body = block.partition(CRLF * 2)
    if not sep:
        head, sep, body = block.partition(b"\n\n")
    lines = head.replace(CRLF, b"\n").split(b"\n")
    pairs = [tuple(x.strip() for x in line.decode("utf-8", "replace").partition(":")[::2]) for line in lines[1:] if line.strip()]
    return lines[0].decode("utf-8", "replace"), pairs, body


def _chunked(body: bytes) -> bytes:
    """The chunks of a body in a row; ValueError where it is none."""
    out, at = [], 0
    while True:
        end = body.find(b"\n", at)
        size = body[at : end if end >= 0 else len(body)].split(b";")[0].strip()
        if not size or size.strip(b"0123456789abcdefABCDEF"):
            raise ValueError("a chunk without a size")
        n = int(size, 16)
        if not n:
            return b"".join(out)
        if end < 0 or end + 1 + n > len(body):
            raise ValueError("a chunk is cut")
        out.append(body[end + 1 : end + 1 + n])
        at = end + 1 + n
        if body[at : at + 2] == CRLF:
            at += 2
        elif body[at : at + 1] == b"\n":
            at += 1


def entity(pairs: list[tuple[str, str]], body: bytes) -> bytes:
    """The body without its transfer and content codings.  One that does not hold to its headers, as where a crawler has undone
    them already, stays as it is."""
    values = lambda name: [x.strip().lower() for k, v in pairs if k.lower() == name for x in v.split(",")]
    if "chunked" in values("transfer-encoding"):
        try:
            body = _chunked(body)
        except ValueError:
            pass
    for coding in reversed(values("content-encoding")):
        if coding not in ("gzip", "x-gzip", "deflate"):
            continue
        for bits in (31,) if "gzip" in coding else (15, -15):
            opener = zlib.decompressobj(bits)
            try:
                out = opener.decompress(body, MAX_BODY)
            except zlib.error:
                continue
            if opener.unconsumed_tail and not opener.eof:
                raise ValueError("a body is larger than MAX_BODY")
            body = out
            break
    return body


HIDDEN = re.compile(r"<!--|<(script|style|noscript|template)\b", re.I)
BLOCKS = frozenset("p div br li ul ol tr table h1 h2 h3 h4 h5 h6 section article header footer nav blockquote pre title body head html main aside hr td th".split())
TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)[^>]*>|<[/!?][^>]*>")
LINKS = {"a": "href", "area": "href", "link": "href", "img": "src", "script": "src", "iframe": "src"}
ATTRIBUTE = re.compile(r"""[\s/"'=]*([^\s>/"'=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]*)))?""")


def visible(markup: str) -> str:
    """The markup without comments, scripts, styles and templates, a blank in the place of each; the tag that opens a script stays."""
    out, at = [], 0
    ends = {n: re.compile(rf"</{n}\s*>", re.I) for n in ("script", "style", "noscript", "template")}
    while (m := HIDDEN.search(markup, at)) is not None:
        out += [markup[at : m.start()], " "]
        if m[1]:
            name = m[1].lower()
            end = ends[name].search(markup, m.end())
            at = end.end() if end else len(markup)
            if name == "script" and 0 <= (gt := markup.find(">", m.end(), at)):
                out.append(markup[m.start() : gt + 1])
        else:
            end = markup.find("-->", m.end())
            at = end + 3 if end >= 0 else len(markup)
    return "".join([*out, markup[at:]])


def plain_text(markup: str) -> str:
    """The visible text: blocks as lines, blanks collapsed, entities resolved, empty lines dropped."""
    text = visible(markup)
    last = text.rfind(">") + 1  # no tag ends beyond, so none begins there; and every search below ends at a ">"
    text = html.unescape(TAG.sub(lambda m: "\n" if m[2] and m[2].lower() in BLOCKS else "", text[:last]) + text[last:])
    lines = (" ".join(x.split()) for x in text.split("\n"))
    return "\n".join(x for x in lines if x)


def facts(markup: str, uri: str) -> dict:
    """Title and links of a page, links resolved against its URI."""
    title, links = None, []
    if (m := re.search(r"<title\b", markup, re.I)) and (lo := markup.find(">", m.end())) >= 0 and (end := re.compile("</title", re.I).search(markup, lo)):
        title = " ".join(html.unescape(markup[lo + 1 : end.start()]).split())
    text = visible(markup)
    last, at = text.rfind(">") + 1, 0
    while (m := TAG.search(text, at, last)) is not None:
        name = (m[2] or "").lower()
        at = m.end()
        if m[1] or name not in LINKS:
            continue
        here, target = m.end(2), None
        while (x := ATTRIBUTE.match(text, here)) is not None:
            here = x.end()
            if target is None and x[1].lower() == LINKS[name]:
                target = html.unescape(next((v for v in x.groups()[1:] if v is not None), ""))
        at = max(at, here)  # a quoted value may hold a ">"
        if target is not None:
            try:
                url = urljoin(uri, target)
            except ValueError:
                url = target
            links.append({"path": f"{name}@{LINKS[name]}", "url": url})
    return {"title": title, "links": links}


def response(uri: str, markup: str, key: str, date: str = "2024-01-01T00:00:00Z") -> bytes:
    """A response record around a page, for tables that hold pages without a crawl's headers."""
    body = markup.encode()
    http = CRLF.join([b"HTTP/1.1 200 OK", b"Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}".encode()]) + CRLF * 2
    head = {"WARC-Target-URI": " ".join(uri.split()), "WARC-Date": date, "WARC-Record-ID": record_id("response", key, uri), "Content-Type": "application/http; msgtype=response", "WARC-Payload-Digest": digest(body), "WARC-Block-Digest": digest(http + body)}
    return build("response", head, http + body)


def derive(head: dict[str, str], block: bytes) -> list[tuple[str, dict[str, str], bytes, dict]]:
    """(type, headers, block, facts) of the two derived records of a response."""
    status, pairs, sent = split_http(block)
    body = entity(pairs, sent)
    charset = re.search(r"charset=\"?([\w-]+)", next((v for k, v in pairs if k.lower() == "content-type"), ""))
    try:
        markup = body.decode(charset[1] if charset else "utf-8", "replace")
    except LookupError:
        markup = body.decode("utf-8", "replace")
    source, uri = head.get("warc-record-id", ""), head.get("warc-target-uri", "")
    basis = source or "|".join([digest(block), uri, head.get("warc-date", ""), head.get("", "")])
    payload = head.get("warc-payload-digest") or digest(sent)
    found = facts(markup, uri)
    text = plain_text(markup)
    kept = {k: head[k.lower()] for k in ("WARC-Target-URI", "WARC-Date") if k.lower() in head}
    refers = ({"WARC-Refers-To": source} if source else {}) | {k: head[old] for k, old in (("WARC-Refers-To-Target-URI", "warc-target-uri"), ("WARC-Refers-To-Date", "warc-date")) if old in head}
    envelope = {"source": {k: v for k, v in head.items() if k not in ("", "content-length")}, "http": {"status": status, "headers": pairs, "payload_bytes": len(sent), "entity_bytes": len(body), "payload_digest": payload}, "html": found}
    out = []
    for kind, media, data, more in (("metadata", "application/json", json.dumps(envelope, ensure_ascii=False, sort_keys=True).encode(), {"n_links": len(found["links"]), "title": found["title"], "n_chars": None}), ("conversion", "text/plain", text.encode(), {"n_links": None, "title": None, "n_chars": len(text)})):
        own = kept | {"WARC-Record-ID": record_id(kind, basis)} | refers | {"WARC-Source-Payload-Digest": payload, "Content-Type": media, "WARC-Block-Digest": digest(data)}
        out.append((kind, own, data, more | {"status": status, "source_payload_digest": payload}))
    return out


OUT = {"record_type": "string", "record_id": "string", "refers_to": "string", "target_uri": "string", "warc_date": "string", "source_payload_digest": "string", "block_digest": "string", "block_bytes": "long", "n_links": "long", "title": "string", "n_chars": "long", "record": "binary", "error": "string"}


def derivatives(df: DataFrame, keep: list[str], data_col: str = "warc") -> DataFrame:
    """``keep`` beside OUT: two rows for each response record in ``data_col`` (WARC bytes of any number of records).

    Records of other types give nothing.  Bytes that are no WARC, a null and what follows a fault give one row with
    ``error``; records and gzip members before the fault keep their rows.  ``record`` is the whole derived record.  Repeated
    rows each give their records, with equal ids; an empty table gives none; kept columns come back under free names.
    """
    names = common.free_names(keep, OUT)
    fields = T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in OUT.items())).fields
    schema = T.StructType([*(T.StructField(new, df.schema[old].dataType) for old, new in names), *fields])
    src = df.select(*[F.col(f"`{c}`").alias(f"k{i}") for i, (c, _) in enumerate(names)], F.col(f"`{data_col}`").cast("binary").alias("data"))
    kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}

    def rows_of(data: bytes | None) -> Iterator[dict]:
        if not data:
            yield {"error": "no data"}
            return
        try:
            for head, block in parse(data):
                if head.get("warc-type") != "response":
                    continue
                for kind, own, body, more in derive(head, block):
                    yield more | {"record_type": kind, "record_id": own["WARC-Record-ID"], "refers_to": own.get("WARC-Refers-To"), "target_uri": own.get("WARC-Target-URI"), "warc_date": own.get("WARC-Date"), "block_digest": own["WARC-Block-Digest"], "block_bytes": len(body), "record": build(kind, own, body)}
        except (ValueError, OSError, EOFError) as e:
            yield {"error": str(e)}

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        rows, take = [], []
        for i, data in enumerate(part.column(len(names)).to_pylist()):
            for r in rows_of(data):
                rows.append(r)
                take.append(i)
        at = pa.array(take, pa.int64())
        made = [pa.array([r.get(c) for r in rows], kinds[t]) for c, t in OUT.items()]
        return pa.RecordBatch.from_arrays([*(part.column(i).take(at) for i in range(len(names))), *made], names=schema.names)

    return common.map_arrow(src, run, schema, "data")


def pages_as_warc(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(id, warc): each page as a response record; null URLs and pages are empty ones."""
    schema = T.StructType([df.schema[id_col], T.StructField("warc", T.BinaryType())])
    src = df.select(F.col(id_col), F.coalesce(url_col, F.lit("")).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("text"))

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        made = [response(u, h, str(i)) for i, u, h in zip(*(c.to_pylist() for c in part.columns), strict=True)]
        return pa.RecordBatch.from_arrays([part.column(0), pa.array(made, pa.binary())], names=schema.names)

    return common.map_arrow(src, run, schema)


def write_files(df: DataFrame, folder: str, record_col: str = "record") -> int:
    """Write the records as gzip members, one file a partition, into a folder that the executors share; gives the count."""

    def run(batches):
        from pyspark import TaskContext

        at, body, n = TaskContext.get().partitionId(), [], 0
        for b in batches:
            for r in b.column(0).to_pylist():
                if r:
                    body.append(gzip.compress(r, mtime=0))
                    n += 1
        if n:
            common.put_file(f"{folder}/part-{at:05d}.warc.gz", b"".join(body))
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return df.select(record_col).mapInArrow(run, "n long").agg(F.sum("n")).first()[0] or 0
