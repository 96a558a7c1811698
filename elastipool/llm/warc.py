"""WARC derivatives: metadata and plain-text conversion records of response records.

A response record becomes two records that refer to it (WARC-Refers-To its WARC-Record-ID): *metadata*, with the facts of the exchange and of the page as
application/warc-fields, and *conversion*, the page's visible text as UTF-8 text/plain. Both keep the response's target URI and date, and its payload
digest as WARC-Source-Payload-Digest; the metadata also carries the source's HTTP headers, and names the conversion as WARC-Concurrent-To.
Record ids are version-5 UUIDs of the response's id and the kind, so a repeated run makes the same records. A reader and a writer for (gzip-compressed or plain)
WARC bytes are included. Pages without a stored capture are first written as responses.

Null html is an empty payload; a null url an empty target. A response whose HTTP head can't be read is taken as a payload without head. A record whose Content-Length is no number
is passed over, and a damaged gzip member gives the records read before the damage. Repeated rows give repeated records
with equal ids. Other columns are not read; an empty table gives no records.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from elastipool.llm.common import prepare, table

#: Compressed bytes read at once; the capture time written where a source has none.
CHUNK = 1 << 20
CAPTURED = "2024-01-01T00:00:00Z"
SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")
OUT = "page_id long, warc_type string, record_id string, refers_to string, target_uri string, warc_date string, content_type string, payload_digest string, block_digest string, source_payload_digest string, content_length long, record_sha256 string"
_DROP = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|head)\b.*?(?:</\1\s*>|\Z)", re.S | re.I)
_BLOCK = re.compile(r"</?(?:address|article|aside|blockquote|body|br|caption|dd|div|dl|dt|fieldset|figure|footer|form|h[1-6]|header|hr|html|li|main|nav|ol|p|pre|section|table|td|th|tr|ul)\b[^>]*>", re.I)
_TAG = re.compile(r"<[a-zA-Z/!?][^>]*(?:>|\Z)")
_TITLE = re.compile(r"<title[^>]*>(.*?)</title", re.S | re.I)
_HREF = re.compile(r"""<a\s[^>]*?href\s*=\s*["']?([^"'\s>]+)""", re.I)
_LANG = re.compile(r"""<html[^>]*?\slang\s*=\s*["']?([\w-]+)""", re.I)


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(SPACE, chr(31).join(parts))}>"


def _clean(value: str) -> str:
    return " ".join(value.split())


def write_record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    """One WARC/1.1 record; Content-Length is added."""
    head = "".join(f"{k}: {_clean(v)}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def _stretches(data: bytes) -> Iterator[bytes]:
    """The bytes of a plain file, or of the gzip members of one. A damaged member gives what was read of it and ends a stretch; reading goes
    on at the next place that looks like a member."""
    if data[:2] != b"\x1f\x8b":
        yield data
        return
    held = []
    while data:
        z, at = zlib.decompressobj(31), 0
        try:
            while at < len(data) and not z.eof:
                held.append(z.decompress(data[at : at + CHUNK]))
                at += CHUNK
            data = z.unused_data + data[at:]
            if data[:2] == b"\x1f\x8b":
                continue
        except zlib.error:
            data = data[2:]
        yield b"".join(held)
        held.clear()
        at = data.find(b"\x1f\x8b\x08")
        data = data[at:] if at >= 0 else b""
    if held:
        yield b"".join(held)


def read_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers by lower-case name, block) of each record. A record without a proper length is passed over; a cut last record ends its stretch."""
    for part in _stretches(data):
        yield from _records(part)


def _records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        headers, last = {}, ""
        for line in data[at:end].decode("utf-8", "replace").split("\r\n")[1:]:
            if line[:1] in " \t" and last:
                headers[last] += " " + line.strip()
                continue
            k, _, v = line.partition(":")
            last = k.strip().lower()
            headers[last] = v.strip()
        length = headers.get("content-length", "")
        if not (length.isascii() and length.isdigit() and len(length) < 19):
            at = end + 4
            continue
        n = int(length)
        if end + 4 + n > len(data):
            return
        yield headers, data[end + 4 : end + 4 + n]
        at = end + 4 + n


def response(url: str, html: str, key: str, captured: str = CAPTURED) -> bytes:
    """A response record of a page that was stored without its capture."""
    payload = html.encode()
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode() + payload
    return write_record(
        [
            ("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", key, url)), ("WARC-Date", captured), ("WARC-Target-URI", url),
            ("WARC-Payload-Digest", digest(payload)), ("WARC-Block-Digest", digest(block)), ("Content-Type", "application/http; msgtype=response"),
        ],
        block,
    )


def split_http(block: bytes) -> tuple[str, list[tuple[str, str]], bytes]:
    """(status line, headers, payload) of an HTTP response; an unreadable head is no head."""
    head, sep, payload = block.partition(b"\r\n\r\n")
    if not sep or not head.startswith(b"HTTP/"):
        return "", [], block
    lines = head.decode("iso-8859-1").split("\r\n")
    return lines[0], [(k.strip(), v.strip()) for k, c, v in (x.partition(":") for x in lines[1:]) if c], payload


def _decoded(payload: bytes, http: list[tuple[str, str]]) -> str:
    low = {k.lower(): v for k, v in http}
    if "gzip" in low.get("content-encoding", "").lower():
        try:
            payload = gzip.decompress(payload)
        except (OSError, EOFError, zlib.error):
            pass
    m = re.search(r"charset=[\"']?([\w-]+)", low.get("content-type", ""), re.I)
    try:
        return payload.decode(m.group(1) if m else "utf-8", "replace")
    except LookupError:
        return payload.decode("utf-8", "replace")


def visible_text(html: str) -> str:
    """Text a reader sees, one line for each block, white space as single spaces."""
    s = _TAG.sub("", _BLOCK.sub("\n", _DROP.sub(" ", html.replace("\n", " ").replace("\r", " "))))
    lines = (" ".join((unescape(x) if "&" in x else x).split()) for x in s.split("\n"))
    return "\n".join(x for x in lines if x)


def derive(headers: dict[str, str], block: bytes) -> list[tuple[list[tuple[str, str]], bytes]]:
    """The metadata and conversion records (headers, block) of a response."""
    rid = headers.get("warc-record-id", "")
    status, http, payload = split_http(block)
    html = _decoded(payload, http)
    source = headers.get("warc-payload-digest") or digest(payload)
    text = visible_text(html).encode()
    meta_id, text_id = record_id("metadata", rid), record_id("conversion", rid)
    title = _TITLE.search(html)
    lang = _LANG.search(html)
    facts = [("http-status-line", status)] + [(f"http-header-{k.lower()}", v) for k, v in http]
    facts += [("title", unescape(title.group(1)) if title else ""), ("declared-language", lang.group(1) if lang else ""), ("payload-length", str(len(payload))), ("text-length", str(len(text)))]
    facts += [("outlink", unescape(x)) for x in _HREF.findall(html)]
    body = "".join(f"{k}: {_clean(v)}\r\n" for k, v in facts if v).encode()
    shared = [("WARC-Refers-To", rid), ("WARC-Target-URI", headers.get("warc-target-uri", "")), ("WARC-Date", headers.get("warc-date", CAPTURED)), ("WARC-Source-Payload-Digest", source)]
    if "warc-block-digest" in headers:
        shared.append(("WARC-Source-Block-Digest", headers["warc-block-digest"]))
    return [
        ([("WARC-Type", "metadata"), ("WARC-Record-ID", meta_id), *shared, ("WARC-Concurrent-To", text_id), ("WARC-Block-Digest", digest(body)), ("Content-Type", "application/warc-fields")], body),
        ([("WARC-Type", "conversion"), ("WARC-Record-ID", text_id), *shared, ("WARC-Payload-Digest", digest(text)), ("WARC-Block-Digest", digest(text)), ("Content-Type", "text/plain; charset=utf-8")], text),
    ]


def _row(page, headers: dict[str, str], block: bytes, record: bytes):
    h = headers.get
    return (page, h("warc-type"), h("warc-record-id"), h("warc-refers-to"), h("warc-target-uri"), h("warc-date"), h("content-type"), h("warc-payload-digest"), h("warc-block-digest"), h("warc-source-payload-digest"), len(block), hashlib.sha256(record).hexdigest())


def captured(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, record) with a response record for each page."""
    prepare(pages.sparkSession)

    def run(batches):
        for b in batches:
            got = [response(u or "", h or "", str(i)) for i, u, h in zip(*(c.to_pylist() for c in b.columns))]
            yield pa.RecordBatch.from_pydict({"page_id": b.column(0), "record": pa.array(got, pa.binary())})

    return pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].cast("string").alias("url"), pages[html_col].cast("string").alias("html")).mapInArrow(run, "page_id long, record binary")


def derived(records: DataFrame, id_col: str = "page_id", record_col: str = "record", keep_bytes: bool = False) -> DataFrame:
    """Derived records of every response in the WARC bytes of each row (one record, or a whole file); with ``keep_bytes`` the records themselves."""
    prepare(records.sparkSession)
    names = [x.split()[0] for x in OUT.split(", ")] + ["record"] * keep_bytes

    def run(batches):
        for b in batches:
            rows = []
            for page, data in zip(b.column(0).to_pylist(), b.column(1)):
                for headers, block in read_records(data.as_py() or b""):
                    if headers.get("warc-type") != "response":
                        continue
                    for h, body in derive(headers, block):
                        record = write_record(h, body)
                        rows.append(_row(page, {k.lower(): v for k, v in h}, body, record) + (record,) * keep_bytes)
            if rows:
                cols = list(zip(*rows))
                kinds = [pa.int64(), *[pa.string()] * 9, pa.int64(), pa.string(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    return records.select(records[id_col].cast("long").alias("page_id"), records[record_col].alias("record")).mapInArrow(run, OUT + ", record binary" * keep_bytes)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derived(captured(table(spark, sf_dir, "pages")))
