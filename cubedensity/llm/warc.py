"""Derivatives of web-archive responses: linked metadata and plain-text conversion records.

A response record becomes a ``metadata`` record (JSON: source headers, page title, links) and a ``conversion`` record
(plain text). Both name the response in ``WARC-Refers-To``, its address and date, keep its digests, and carry the
digest of their own block. Identifiers are made from what a response holds (id, address, payload, nulls told apart), so
a task that runs again writes the same records, and different responses have different ones.

Inputs: a null payload counts as empty; a null address is left out of the headers; white space and control characters
of an address are percent-encoded in headers; equal rows are one response and give repeated records with equal
identifiers; pages of any length are read in time in proportion to it; an empty table gives none; extra columns, of
whatever name, are not returned.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import uuid
from html import unescape

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.markup import tokens

CRLF = "\r\n"
DATE = "2024-01-01T00:00:00Z"
_SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")  # the public namespace for URLs
#: fixed values: elements whose text is not shown, elements that begin a line, elements with links
SILENT = frozenset("script style noscript template title".split())
BREAK = frozenset("address article aside blockquote br dd div dl dt figure footer form h1 h2 h3 h4 h5 h6 header hr li main nav ol p pre section table td th tr ul body head html".split())
LINKED = frozenset("a link img script iframe area".split())
_REF = re.compile(r"""(?<![\w-])(href|src)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>][^\s>]*)""", re.I)
_CONTROL = re.compile(r"[\x00-\x20\x7f]")

RECORD = "response_id string, record_id string, refers_to string, type string, url string, date string, payload_digest string, block_digest string, length bigint, header string, block string"


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(kind: str, *parts) -> str:
    return f"<urn:uuid:{uuid.uuid5(_SPACE, kind + chr(0) + chr(0).join(str(p) for p in parts))}>"


def read(html: str) -> tuple[str, str | None, list[dict]]:
    """All text of a page, one line per block; its first title; its links. One pass over the page."""
    parts, title, links, hidden = [], None, [], 0
    for kind, tag, more in tokens(html):
        if kind == "text":
            if not hidden:
                parts.append(tag)
        elif kind == "raw":
            if tag not in SILENT and not hidden:
                parts.append(more)
            elif tag == "title" and title is None:
                title = " ".join(unescape(more).split())
        else:
            if kind == "open" and tag in LINKED:
                found = _REF.search(more)
                if found:
                    links.append({"path": f"{tag}@{found[1].lower()}", "url": unescape(found[2].strip("\"'"))})
            if tag == "template":
                hidden = max(0, hidden + (1 if kind == "open" else -1))
            if tag in BREAK and not hidden:
                parts.append("\n")
    return _lines(unescape("".join(parts))), title, links


def _lines(text: str) -> str:
    """White space inside a line becomes one space, empty lines go."""
    return "\n".join(x for x in (" ".join(line.split()) for line in text.split("\n")) if x)


def plain_text(html: str) -> str:
    """All text of a page, one line per block."""
    return read(html)[0]


def metadata(head: str, title: str | None, links: list[dict]) -> dict:
    """Source headers, title and links of a response."""
    first, *fields = head.split(CRLF)
    return {
        "status": first,
        "headers": [{"name": k, "value": v.strip()} for k, _, v in (x.partition(":") for x in fields if x)],
        "title": title,
        "links": links,
    }


def _address(url: str | None) -> str | None:
    """An address that fits a header line."""
    return None if url is None else _CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", url)


def _header(kind: str, mine: str, refers: str, url, date, payload: str, block: bytes, mime: str) -> str:
    fields = [
        ("WARC-Type", kind),
        ("WARC-Record-ID", mine),
        ("WARC-Refers-To", refers),
        ("WARC-Target-URI", _address(url)),
        ("WARC-Date", date),
        ("WARC-Payload-Digest" if kind == "response" else "WARC-Refers-To-Payload-Digest", payload),
        ("WARC-Block-Digest", digest(block)),
        ("Content-Type", mime),
        ("Content-Length", len(block)),
    ]
    return CRLF.join(["WARC/1.0", *(f"{k}: {v}" for k, v in fields if v is not None)])


def responses(pages: DataFrame, date: str | Column = DATE) -> DataFrame:
    """Response records ``(record_id, url, date, http_head, payload)`` of a table of pages.

    ``date`` is when they were fetched: a column, or one time for all where the table has none.
    """
    size = F.octet_length(F.coalesce("html", F.lit("")))
    head = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), size.cast("string"))
    told = lambda c: F.coalesce(F.concat(F.lit("v"), c), F.lit("n"))  # noqa: E731  a null is not an empty value, and takes its place
    parts = [told(F.sha2(F.col(c).cast("string"), 256)) for c in ("page_id", "url", "html") if c in pages.columns]
    name = F.sha2(F.concat_ws("/", F.lit("response"), *parts), 256)
    part = lambda a, n: F.substring(name, a, n)
    urn = F.concat(F.lit("<urn:uuid:"), part(1, 8), F.lit("-"), part(9, 4), F.lit("-8"), part(14, 3), F.lit("-8"), part(18, 3), F.lit("-"), part(21, 12), F.lit(">"))
    when = F.lit(date) if isinstance(date, str) else date.cast("string")
    return pages.select(urn.alias("record_id"), "url", when.alias("date"), head.alias("http_head"), F.col("html").alias("payload"), *(["page_id"] if "page_id" in pages.columns else []))


def _derived(rid, url, date, head, payload):
    html = payload or ""
    source = digest(html.encode())
    text, title, links = read(html)
    made = (
        ("metadata", json.dumps({"record": {"id": rid, "url": url, "payload-digest": source}, **metadata(head or "", title, links)}, ensure_ascii=False), "application/json"),
        ("conversion", text, "text/plain"),
    )
    for kind, block, mime in made:
        mine, data = record_id(kind, rid, url, source), block.encode()
        yield (rid, mine, rid, kind, url, date, source, digest(data), len(data), _header(kind, mine, rid, url, date, source, data, mime), block)


def derive(found: DataFrame) -> DataFrame:
    """Metadata and conversion records of response records; two rows for each response."""
    names = [f.split()[0] for f in RECORD.split(", ")]
    kinds = [pa.int64() if f.endswith("bigint") else pa.string() for f in RECORD.split(", ")]

    def run(batches):
        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("record_id", "url", "date", "http_head", "payload")]
            rows = [x for r in zip(*columns) for x in _derived(*r)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    return found.select("record_id", "url", "date", "http_head", "payload").mapInArrow(run, RECORD)


def write_records(records: DataFrame, path: str, compression: str = "gzip") -> None:
    """Records as WARC files: header, blank line, block, and the two line ends that close a record."""
    records.select(F.concat("header", F.lit(CRLF * 2), "block").alias("value")).write.option("lineSep", CRLF * 2).option(
        "compression", compression
    ).text(path)


def links(records: DataFrame) -> DataFrame:
    """Outgoing links ``(refers_to, url, path, target)`` of metadata records."""
    found = F.from_json("block", "links array<struct<path:string,url:string>>")["links"]
    return records.filter("type = 'metadata'").select("refers_to", "url", F.explode(found).alias("l")).select("refers_to", "url", "l.path", F.col("l.url").alias("target"))
