"""WARC derivatives: linked metadata and plain-text conversion records of response records.

A response keeps its record id; both derivatives name it in WARC-Refers-To and carry its target URI,
date and payload digest; the metadata record holds the source's headers, title and outgoing links, the
conversion record the text of the page. Records can be written to and read from WARC bytes.
"""

from __future__ import annotations

import base64
import hashlib
import html
import re
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DATE = "2024-01-01T00:00:00Z"
RECORD = (
    "page_id long, record_type string, record_id string, refers_to string, target_uri string, warc_date string, "
    "content_type string, source_headers map<string,string>, source_digest string, payload_digest string, block_digest string, content_length long, content string"
)
_SILENT = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|head)\b.*?(?:</\1\s*>|\Z)", re.I | re.S)
_BLOCK = re.compile(r"</?(?:p|div|br|li|ul|ol|tr|table|h[1-6]|article|section|nav|header|footer|blockquote|pre|hr|title|main|aside|td|th)\b[^>]*>", re.I)
_TAG = re.compile(r"<[/!?a-zA-Z][^>]*>")
_HREF = re.compile(r"<a\b[^>]*?\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_TITLE = re.compile(r"<title\b[^>]*>(.*?)</title\s*>", re.I | re.S)
_SPACE = re.compile(r"[ \t\x0b\x0c\r\xa0]+")
_LINES = re.compile(r"\s*\n\s*")


_CONTROL = re.compile(r"[\x00-\x1f\x7f]")


def one_line(value: str) -> str:
    """A header's value; control characters, which would end the line, are percent-encoded."""
    return _CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", value)


def digest(raw: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(raw).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(10).join(parts))}>"


def plain_text(page: str) -> str:
    """Text of a page: no scripts, styles, head or comments; a line for each block."""
    text = _TAG.sub("", _BLOCK.sub("\n", _SILENT.sub(" ", page)))
    return _LINES.sub("\n", _SPACE.sub(" ", html.unescape(text))).strip()


def links(page: str) -> list[str]:
    return list(dict.fromkeys(html.unescape(a or b or c) for a, b, c in _HREF.findall(page)))


def responses(pages: DataFrame, date: str = DATE) -> DataFrame:
    """Response records (page_id, record_id, target_uri, warc_date, headers, payload) of raw pages.

    Null pages have an empty payload; a null URL an empty target; control characters in URLs are
    percent-encoded. Ids depend on page_id, URL and payload, so repeated rows give equal records. Pages of any length
    are taken whole, an empty table gives no records, other columns are ignored."""

    def run(it):
        for batch in it:
            ids, urls, pages = (batch.column(k).to_pylist() for k in range(3))
            heads = [[("Content-Type", "text/html; charset=utf-8"), ("Content-Length", str(len((p or "").encode())))] for p in pages]
            names = [record_id("response", str(i), u or "", digest((p or "").encode())) for i, u, p in zip(ids, urls, pages)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64()), pa.array(names), pa.array([one_line(u or "") for u in urls]), pa.array([date] * len(ids), pa.string()), pa.array(heads, pa.map_(pa.string(), pa.string())), pa.array([p or "" for p in pages])],
                names=["page_id", "record_id", "target_uri", "warc_date", "headers", "payload"],
            )

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, record_id string, target_uri string, warc_date string, headers map<string,string>, payload string")


def derive(found: DataFrame) -> DataFrame:
    """Two derived records for each response: `metadata` and `conversion` (columns RECORD).

    A response without text still gets both, with empty content for the conversion."""

    def run(it):
        for batch in it:
            rows = []
            for page, rid, uri, date, heads, payload in zip(*(batch.column(k).to_pylist() for k in range(6))):
                heads, source = list(heads or []), digest(payload.encode())
                title = _TITLE.search(payload)
                fields = [f"sourceDigest: {source}", *(f"sourceHeader: {k}: {v}" for k, v in heads)]
                fields += [f"title: {_SPACE.sub(' ', html.unescape(title[1])).strip()}"] if title else []
                fields += [f"outlink: {x} L a/@href" for x in links(payload)]
                for kind, mime, body in (("metadata", "application/warc-fields", "".join(x.replace("\r", " ").replace("\n", " ") + "\r\n" for x in fields)), ("conversion", "text/plain; charset=utf-8", plain_text(payload))):
                    raw = body.encode("utf-8", "replace")
                    rows.append((page, kind, record_id(kind, rid), rid, uri, date, mime, heads, source, digest(raw), digest(raw), len(raw), body))
            if rows:
                kinds = (pa.int64(), *[pa.string()] * 6, pa.map_(pa.string(), pa.string()), *[pa.string()] * 3, pa.int64(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows), kinds)], names=[f.split()[0] for f in RECORD.split(", ")])

    return found.select("page_id", "record_id", "target_uri", "warc_date", "headers", "payload").mapInArrow(run, RECORD)


def build(pages: DataFrame, date: str = DATE) -> DataFrame:
    """Metadata and conversion records of every page, two rows each."""
    return derive(responses(pages, date))


def to_bytes(row: dict) -> bytes:
    """One derived record in WARC/1.1 form."""
    body = row["content"].encode("utf-8", "replace")
    heads = [("WARC-Type", row["record_type"]), ("WARC-Record-ID", row["record_id"]), ("WARC-Date", row["warc_date"]), ("WARC-Refers-To", row["refers_to"])]
    heads += [("WARC-Target-URI", row["target_uri"]), ("WARC-Block-Digest", row["block_digest"]), ("WARC-Payload-Digest", row["payload_digest"])]
    heads += [("WARC-Source-Digest", row["source_digest"])] + [(f"X-Source-{k}", v) for k, v in dict(row["source_headers"]).items()]
    heads += [("Content-Type", row["content_type"]), ("Content-Length", str(len(body)))]
    return b"WARC/1.1\r\n" + "".join(f"{one_line(k)}: {one_line(v)}\r\n" for k, v in heads).encode("utf-8", "replace") + b"\r\n" + body + b"\r\n\r\n"


def from_bytes(raw: bytes) -> list[tuple[dict[str, str], bytes]]:
    """Headers and content of each record."""
    out, at = [], 0
    while at < len(raw):
        end = raw.index(b"\r\n\r\n", at)
        heads = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in raw[at:end].decode().split("\r\n")[1:])
        body = raw[end + 4 : end + 4 + int(heads["Content-Length"])]
        out.append((heads, body))
        at = end + 4 + len(body) + 4
    return out


def archives(records: DataFrame, shards: int = 16) -> DataFrame:
    """(shard, part, archive): gzip members of each task's records, a member for each record."""

    def run(it):
        for batch in it:
            packed = []
            for row in batch.to_pylist():
                z = zlib.compressobj(wbits=31)
                packed.append(z.compress(to_bytes(row)) + z.flush())
            if packed:
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(packed)], pa.binary()), pa.array([len(packed)], pa.int64())], names=["archive", "records"])

    return records.repartition(shards, "refers_to").mapInArrow(run, "archive binary, records long")
