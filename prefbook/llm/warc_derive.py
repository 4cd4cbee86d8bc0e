"""Derived records of web captures: linked metadata and plain-text conversion.

A capture is a WARC response record, whose block is an HTTP message. From each come a
metadata record, whose JSON block links to the source and lists its headers, title and
links, and a conversion record with the page's text. Both carry WARC-Refers-To with the
response's record id, its target URI and date, and the digest of the payload that they
were made from. Record ids are name-based, so a rerun after a lost executor writes the
same bytes.

Edge cases: a null page body is an empty payload and gives an empty conversion; a null
address leaves the target header out. Records of other types and bytes that are no WARC
record, broken gzip members among them, give no derivatives. A payload whose coding is
unknown or broken is left as it is: its metadata record names the codings that could not
be undone and has neither title nor links, and its conversion is empty. Repeated header
fields all stay, in order. A page is read in one forward pass, in time that follows its
length; a tag or comment without an end is text. Repeated captures of a page give the same records again. An
empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import base64
import functools
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

from .session import arrow_map, column, fields

VERSION = b"WARC/1.1"
_NAMES = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")  # fixed: the public namespace of URLs
#: Capture time of pages that come without one.
CAPTURED = "2024-01-01T00:00:00Z"

Headers = list[tuple[str, str]]


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMES, chr(10).join(parts))}>"


def record(headers: Headers, block: bytes) -> bytes:
    """One WARC record; length and block digest are added."""
    lines = [VERSION, *(f"{k}: {v}".encode() for k, v in headers), b"WARC-Block-Digest: " + digest(block).encode(), b"Content-Length: " + str(len(block)).encode()]
    return b"\r\n".join(lines) + b"\r\n\r\n" + block + b"\r\n\r\n"


def _fields(lines: list[bytes]) -> Headers:
    """Header fields; a line that begins with white space continues the one before."""
    out: Headers = []
    for line in lines:
        text = line.decode("utf-8", "replace")
        if text[:1] in " \t" and out:
            out[-1] = (out[-1][0], f"{out[-1][1]} {text.strip()}")
        elif ":" in text:
            name, _, value = text.partition(":")
            out.append((name.strip(), value.strip()))
    return out


def named(headers: Headers, name: str) -> str | None:
    return next((v for k, v in headers if k.lower() == name.lower()), None)


def parse_record(data: bytes) -> tuple[Headers, bytes] | None:
    """Headers and block of a record, None for anything else. A gzip member is opened first."""
    if data[:2] == b"\x1f\x8b":
        try:
            data = gzip.decompress(data)
        except (OSError, EOFError, zlib.error):
            return None
    head, parted, rest = data.partition(b"\r\n\r\n")
    lines = head.split(b"\r\n")
    if not parted or not lines[0].startswith(b"WARC/"):
        return None
    headers = _fields(lines[1:])
    length = named(headers, "Content-Length")
    return headers, rest[: int(length)] if length and length.isascii() and length.isdigit() else rest.removesuffix(b"\r\n\r\n")


def parse_response(block: bytes) -> tuple[str, Headers, bytes, list[str]]:
    """Status line, headers and payload of an HTTP message, transfer and content codings undone, and those that could not be."""
    head, _, body = block.partition(b"\r\n\r\n")
    first, *lines = head.split(b"\r\n")
    headers = _fields(lines)
    codings = [c.strip().lower() for name in ("Content-Encoding", "Transfer-Encoding") for k, v in headers if k.lower() == name.lower() for c in v.split(",")]
    left = [c for c in codings if c not in ("", "identity")]
    while left:
        opened = _opened(body, left[-1])
        if opened is None:
            break
        body = opened
        left.pop()
    return first.decode("utf-8", "replace"), headers, body, left


def _opened(body: bytes, coding: str) -> bytes | None:
    """The body without one coding; None if the coding is unknown or the body is not in it."""
    try:
        if coding == "chunked":
            return b"".join(_chunks(body))
        if coding in ("gzip", "x-gzip"):
            return zlib.decompressobj(31).decompress(body)
        if coding == "deflate":
            return zlib.decompressobj(15 if body[:1] == b"\x78" else -15).decompress(body)
    except zlib.error:
        pass
    return None


def _chunks(body: bytes) -> Iterator[bytes]:
    at = 0
    while (end := body.find(b"\r\n", at)) > 0:
        size = body[at:end].split(b";")[0].strip()
        if not re.fullmatch(rb"[0-9A-Fa-f]+", size) or not int(size, 16):
            return
        at = end + 2 + int(size, 16) + 2
        yield body[end + 2 : at - 2]


#: What begins a mark: a comment, a CDATA section, or a tag with its name, the inside up to the next bracket outside quotes, and its end.
_INSIDE = r"""(?:[^<>"']++|"[^"]*+"|'[^']*+')*+"""
_MARK = re.compile(rf"<(?:(!--)|(!\[CDATA\[)|(/?)([A-Za-z][^\s/<>\"']*+)({_INSIDE})(>?)|[!?/]{_INSIDE}(>?))")
_FIELD = re.compile(r"""([^\s=/"'<>]++)(?:\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s"'<>]++)))?+""")
#: Elements whose content is no markup, those whose content is not shown, those that begin a line, and those that link.
_RAW = frozenset(("script", "style"))
_UNSEEN = frozenset(("noscript", "template", "svg", "head"))
_BREAKS = frozenset("p div br li ul ol tr table h1 h2 h3 h4 h5 h6 article section nav header footer blockquote pre hr dd dt dl form main aside figure td th body html".split())
_LINKING = frozenset(("a", "link", "img", "script", "iframe"))
_BLANK = re.compile(r"[ \t\r\f\v\xa0]+")


class Page:
    """Title, visible text and links of a page, from one pass over its marks."""

    def __init__(self, page: str, address: str | None = None):
        self.page, self.missing = page, set()
        self.links: list[dict] = []
        shown: list[str] = []
        title: list[str] | None = None
        self.title: str | None = None
        at = hidden = title_end = 0
        while (m := _MARK.search(page, at)) is not None:
            if m.start() > at:
                self._add(page[at : m.start()], at >= hidden, shown, title if at < title_end else None)
            at = m.end()
            name = (m[4] or "").lower()
            if m[1] or m[2]:
                end = self._find("-->" if m[1] else "]]>", at)
                if end < 0:
                    self._add(m[0], m.start() >= hidden, shown, title if m.start() < title_end else None)
                    continue
                self._add(" ", at >= hidden, shown, None)
                at = end + 3
            elif not (m[6] or m[7]):  # without an end it is text
                self._add(m[0], m.start() >= hidden, shown, title if m.start() < title_end else None)
            elif name:
                if not m[3] and name in _LINKING:
                    self._link(name, m[5], address)
                if name in _BREAKS:
                    self._add("\n", at >= hidden, shown, None)
                if not m[3] and name in _RAW and (close := self._closing(name, at)) is not None:
                    self._add(" ", at >= hidden, shown, None)
                    at = close[1]
                elif not m[3] and name in _UNSEEN and at >= hidden and (close := self._closing(name, at)) is not None:
                    shown.append(" ")
                    hidden = close[1]
                elif not m[3] and name == "title" and title is None and (close := self._closing(name, at)) is not None:
                    title, title_end = [], close[0]
        self._add(page[at:], at >= hidden, shown, title if at < title_end else None)
        if title is not None:
            self.title = html.unescape("".join(title)).strip()
        lines = _BLANK.sub(" ", html.unescape("".join(shown))).split("\n")
        self.text = "\n".join(line for line in (x.strip() for x in lines) if line)

    def _add(self, text: str, seen: bool, shown: list[str], title: list[str] | None) -> None:
        if seen:
            shown.append(text)
        if title is not None:
            title.append(text)

    def _find(self, what: str, at: int) -> int:
        """As str.find; what is missing once is not looked for again."""
        found = -1 if what in self.missing else self.page.find(what, at)
        if found < 0:
            self.missing.add(what)
        return found

    def _closing(self, name: str, at: int) -> tuple[int, int] | None:
        """Begin and end of the element's next closing tag."""
        if name in self.missing:
            return None
        found = _closing_tag(name).search(self.page, at)
        if found is None:
            self.missing.add(name)
            return None
        return found.span()

    def _link(self, tag: str, inside: str, address: str | None) -> None:
        for m in _FIELD.finditer(inside):
            if m[1].lower() in ("href", "src"):
                value = next((x for x in m.groups()[1:] if x is not None), "")
                self.links.append({"tag": tag, "url": urljoined(address, html.unescape(value))})
                return


@functools.cache
def _closing_tag(name: str) -> re.Pattern:
    return re.compile(rf"(?i)</{name}\s*+>")


def plain_text(page: str) -> str:
    """Visible text, a line for each block; character references are resolved once, after the tags are gone."""
    return Page(page).text


def page_facts(page: str, address: str | None) -> dict:
    read = Page(page, address)
    return {"title": read.title, "links": read.links}


def urljoined(base: str | None, link: str) -> str:
    try:
        return urljoin(base or "", link.strip())
    except ValueError:  # an address that can't be parsed stays as it is
        return link


def response_record(address: str | None, body: str | None, captured: str = CAPTURED) -> bytes:
    """A capture of a page as a response record."""
    payload = (body or "").encode()
    message = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: " + str(len(payload)).encode() + b"\r\n\r\n" + payload
    own = digest(payload)
    headers: Headers = [("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", address or "", captured, own)), ("WARC-Date", captured)]
    if address is not None:
        headers.append(("WARC-Target-URI", address.replace("\r", " ").replace("\n", " ")))
    return record([*headers, ("WARC-Payload-Digest", own), ("Content-Type", "application/http; msgtype=response")], message)


def derivatives(source: bytes) -> list[tuple[Headers, bytes]]:
    """Headers and blocks of the metadata and conversion records of a response record; none for other input."""
    parsed = parse_record(source)
    if parsed is None or named(parsed[0], "WARC-Type") != "response":
        return []
    headers, block = parsed
    status, fields, payload, closed = parse_response(block)
    identity, address = named(headers, "WARC-Record-ID") or "", named(headers, "WARC-Target-URI")
    made_from = named(headers, "WARC-Payload-Digest") or digest(payload)
    charset = re.search(r"charset=\"?([\w.:-]+)", named(fields, "Content-Type") or "")
    page = Page("" if closed else _decoded(payload, charset[1] if charset else "utf-8"), address)
    facts = {
        "source": {"record_id": identity, "headers": [list(x) for x in headers], "payload_digest": made_from, "payload_length": len(payload)},
        "http": {"status": status, "headers": [list(x) for x in fields], "codings_left": closed},
        "title": page.title,
        "links": page.links,
    }
    shared: Headers = [("WARC-Date", named(headers, "WARC-Date") or CAPTURED), ("WARC-Refers-To", identity)]
    shared += [("WARC-Target-URI", address)] if address is not None else []
    shared += [("WARC-Source-Payload-Digest", made_from)]
    out = []
    for kind, form, body in (("metadata", "application/json", json.dumps(facts, ensure_ascii=False, sort_keys=True).encode("utf-8", "replace")), ("conversion", "text/plain; charset=utf-8", page.text.encode("utf-8", "replace"))):
        out.append(([("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, identity, made_from)), *shared, ("Content-Type", form)], body))
    return out


def _decoded(payload: bytes, charset: str) -> str:
    try:
        return payload.decode(charset, "replace")
    except (LookupError, UnicodeError):  # a charset that nobody knows, or that is none of text
        return payload.decode("utf-8", "replace")


def capture_pages(pages: DataFrame, id_column: str = "page_id", url_column: str = "url", body_column: str = "html") -> DataFrame:
    """(id, warc): a response record for each page; narrow."""
    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [response_record(u.as_py(), h.as_py()) for u, h in zip(batch.column(1), batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.binary())], names=[id_column, "warc"])

    return pages.select(*(column(c) for c in (id_column, url_column, body_column))).transform(arrow_map, build, fields(pages, [id_column], ("warc", "binary")))


_OUT = ("kind", "record_id", "refers_to", "target_uri", "date", "source_digest", "block_digest", "block")


def derive_records(captures: DataFrame, id_column: str = "page_id", warc_column: str = "warc") -> DataFrame:
    """Two rows per response record: its id, the derived record's main headers and block, and the whole record as a gzip member; narrow."""
    schema = fields(captures, [id_column], *((name, "string") for name in _OUT[:-1]), ("block", "binary"), ("warc", "binary"))

    def derive(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            origin, columns = [], [[] for _ in range(len(_OUT) + 1)]
            for i, source in enumerate(batch.column(1)):
                for headers, block in derivatives(source.as_py() or b""):
                    get = lambda name: named(headers, name)  # noqa: B023, E731
                    whole = gzip.compress(record(headers, block), 1, mtime=0)
                    row = (get("WARC-Type"), get("WARC-Record-ID"), get("WARC-Refers-To"), get("WARC-Target-URI"), get("WARC-Date"), get("WARC-Source-Payload-Digest"), digest(block), block, whole)
                    origin.append(i)
                    for column, value in zip(columns, row):
                        column.append(value)
            kinds = [pa.string()] * 7 + [pa.binary()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(origin, pa.int64())), *(pa.array(c, t) for c, t in zip(columns, kinds))], names=[id_column, *_OUT, "warc"])

    return captures.select(column(id_column), column(warc_column)).transform(arrow_map, derive, schema)


def derivative_report(pages: DataFrame) -> DataFrame:
    """Derived records of captured pages, with lengths and digests in place of blocks."""
    made = derive_records(capture_pages(pages))
    return made.select("page_id", *_OUT[:-1], F.octet_length("block").cast("long").alias("block_length"), F.sha2("block", 256).alias("block_sha256"), F.octet_length("warc").cast("long").alias("member_length"))
