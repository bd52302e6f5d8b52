"""WARC derivatives: responses become linked metadata records and plain-text conversion records.

A derivative keeps its response's target, date and identifier (WARC-Refers-To), carries the digests of the response's
block and payload and its own block's digest, and repeats the source headers in the metadata.  Records are whole WARC/1.0 records in
bytes, so a sink can write them one after another.
"""

from __future__ import annotations

import base64
import contextlib
import gzip
import hashlib
import html as entities
import json
import re
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import tidy

DATE = "2024-01-01T00:00:00Z"
_TAG = re.compile(r"<!--|<([a-zA-Z/!?][^\s>/]*)", re.S)
_LINK = re.compile(r"""\b(?:href|src)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
# Elements that end a line of text, and those whose content is no text.
BLOCKS = frozenset("p div br li ul ol tr table h1 h2 h3 h4 h5 h6 article section nav header footer title pre blockquote hr td th".split())
SILENT = ("script", "style", "noscript", "template")
#: Of ASCII letters alone, in the page as it is: lower-casing it would move positions.
_CLOSING = {name: re.compile(f"</{name}", re.I | re.A) for name in (*SILENT, "title")}
DERIVED = ("page_id long, record_type string, record_id string, refers_to string, target_uri string, block_digest string, "
           "source_block_digest string, source_payload_digest string, block_length long, record binary")


def sha1(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def urn(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(10).join(parts))}>"


def record(kind: str, record_id: str, headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = [("WARC-Type", kind), ("WARC-Record-ID", record_id), *headers, ("WARC-Block-Digest", sha1(block)), ("Content-Length", str(len(block)))]
    clean = (f"{k}: {' '.join(v.split())}\r\n" for k, v in lines)
    return b"WARC/1.0\r\n" + "".join(clean).encode("utf-8", "replace") + b"\r\n" + block + b"\r\n\r\n"


def _unzipped(data: bytes) -> bytes:
    """data without its gzip members, as far as they can be read."""
    out = []
    while data[:2] == b"\x1f\x8b":
        z = zlib.decompressobj(31)
        try:
            out.append(z.decompress(data))
        except zlib.error:
            break
        data = z.unused_data
    return b"".join(out)


def records(data: bytes):
    """Yield (headers, block, error) of the records in data, which may be gzipped as a whole or record by record.

    A record without an end of headers, a length or an id, or that is cut short, has an error in place of its block; reading goes
    on at the next record's first line.
    """
    data = _unzipped(data) if data[:2] == b"\x1f\x8b" else data
    at = data.find(b"WARC/")
    while at >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            yield {}, None, "no end of headers"
            return
        headers = {k.strip(): v.strip() for k, _, v in (x.partition(":") for x in data[at:end].decode("utf-8", "replace").split("\r\n")[1:])}
        length = headers.get("Content-Length", "")
        size = int(length) if length.isascii() and length.isdigit() else -1
        error = "no length" if size < 0 else "no record id" if not headers.get("WARC-Record-ID") else "cut short" if end + 4 + size > len(data) else None
        yield headers, None if error else data[end + 4:end + 4 + size], error
        at = data.find(b"WARC/", end + 4 + size if error in (None, "no record id") else end + 4)


def parse(data: bytes):
    """Yield (headers, block) of the whole records in data."""
    return ((headers, block) for headers, block, error in records(data) if error is None)


def payload(head: bytes, body: bytes) -> str:
    """The text of an HTTP response: chunks joined, compression undone and bytes decoded, each as far as the headers tell and the data allow."""
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode("latin-1").split("\r\n")[1:])}
    if fields.get("transfer-encoding", "").lower().endswith("chunked"):
        parts, at = [], 0
        while (end := body.find(b"\r\n", at)) >= 0:
            size = body[at:end].partition(b";")[0].strip()
            if not re.fullmatch(rb"[0-9A-Fa-f]{1,8}", size) or not int(size, 16):
                break
            parts.append(body[end + 2:end + 2 + int(size, 16)])
            at = end + 4 + int(size, 16)
        body = b"".join(parts) if parts else body
    coding = fields.get("content-encoding", "").lower()
    if coding in ("gzip", "x-gzip", "deflate"):
        for bits in (47, -15):  # with a header of either kind, or bare
            with contextlib.suppress(zlib.error):
                body = zlib.decompressobj(bits).decompress(body)
                break
    charset = re.search(r"charset\s*=\s*[\"']?([\w.:-]+)", fields.get("content-type", ""), re.I)
    try:
        return body.decode(charset[1] if charset else "utf-8", "replace")
    except LookupError:
        return body.decode("utf-8", "replace")


def http_block(html: str) -> bytes:
    body = html.encode("utf-8", "replace")
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(body) + body


def response(page_id, url: str, html: str) -> bytes:
    block = http_block(html)
    return record("response", urn("response", str(page_id), url), [("WARC-Target-URI", url), ("WARC-Date", DATE), ("Content-Type", "application/http; msgtype=response"),
                  ("WARC-Payload-Digest", sha1(block.partition(b"\r\n\r\n")[2]))], block)


def text_and_links(page: str) -> tuple[str, str, list[str]]:
    """(title, text, links).  One pass from tag to tag: comments and silent elements are skipped to their end, or to the end of the page."""
    at, out, links, title = 0, [], [], None
    while m := _TAG.search(page, at):
        out.append(page[at:m.start()])
        name = (m[1] or "").lower()
        if not name:
            end = page.find("-->", m.end())
            at = len(page) if end < 0 else end + 3
            continue
        end = page.find(">", m.end())
        end = len(page) if end < 0 else end
        bare = name.lstrip("/")
        if name in SILENT:
            close = _CLOSING[name].search(page, end)
            at = close.start() if close else len(page)
            continue
        if name in ("a", "img", "link", "iframe") and (found := _LINK.search(page, m.end(), end)):
            links.append(entities.unescape(found[1] or found[2] or found[3] or ""))
        if name == "title" and title is None:
            close = _CLOSING[name].search(page, end)
            title = " ".join(entities.unescape(page[end + 1:close.start() if close else len(page)]).split())
        if bare in BLOCKS:
            out.append("\n")
        at = min(end + 1, len(page))
    out.append(page[at:])
    lines = (" ".join(x.split()) for x in entities.unescape("".join(out)).split("\n"))
    return title or "", "\n".join(x for x in lines if x), links


def derive(headers: dict, block: bytes) -> list[tuple]:
    """Of one response: (record_type, record_id, refers_to, target_uri, block digest, source digests, length, record)."""
    head, _, body = block.partition(b"\r\n\r\n")
    page = payload(head, body)
    title, text, links = text_and_links(page)
    rid, uri, date = headers.get("WARC-Record-ID", ""), headers.get("WARC-Target-URI", ""), headers.get("WARC-Date", DATE)
    source = headers.get("WARC-Block-Digest") or sha1(block), headers.get("WARC-Payload-Digest") or sha1(body)
    status, *fields = head.decode("utf-8", "replace").split("\r\n")
    meta = {"warc-headers": headers, "http": {"status": status, "headers": {k.strip(): v.strip() for k, _, v in (x.partition(":") for x in fields)}},
            "payload": {"length": len(body), "digest": source[1]}, "html": {"title": title, "links": links}}
    meta_id, text_id = urn("metadata", rid), urn("conversion", rid)
    out = []
    for kind, own, other, mime, data in (("metadata", meta_id, text_id, "application/json", json.dumps(meta, sort_keys=True, ensure_ascii=False).encode("utf-8", "replace")),
                                         ("conversion", text_id, meta_id, "text/plain", text.encode("utf-8", "replace"))):
        made = record(kind, own, [("WARC-Target-URI", uri), ("WARC-Date", date), ("WARC-Refers-To", rid), ("WARC-Concurrent-To", other), ("Content-Type", mime)], data)
        out.append((kind, own, rid, uri, sha1(data), *source, len(data), made))
    return out


def _derived(rows: list[tuple], schema) -> pa.RecordBatch:
    kinds = [pa.int64(), *[pa.string()] * 7, pa.int64(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows) if rows else [[]] * len(kinds), kinds)], names=[x.split()[0] for x in schema.split(", ")])


def derivatives(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Two rows per page, a metadata and a conversion record, by way of the page's response record.

    Null urls and pages count as empty; null ids pass through.  Repeated rows give equal records.  One pass without a shuffle.
    """

    def run(batches):
        for b in batches:
            rows = []
            for page_id, url, page in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                for headers, block in parse(response(page_id, url or "", page.as_py() or "")):
                    rows += [(page_id, *r) for r in derive(headers, block)]
            yield _derived(rows, DERIVED)

    d = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return d.mapInArrow(tidy(run), DERIVED)


RESPONSES = "record_id string, target_uri string, date string, headers map<string,string>, block binary, error string"


def read_responses(spark: SparkSession, path: str) -> DataFrame:
    """The response records in WARC files, gzipped or not, in the schema RESPONSES.

    Records that cannot be read, of whatever type, come with an error and no block, so that they can be counted.  A folder without
    files gives no rows.
    """

    def run(batches):
        kinds = pa.string(), pa.string(), pa.string(), pa.map_(pa.string(), pa.string()), pa.binary(), pa.string()
        for b in batches:
            for data in b.column(0):
                rows = [(h.get("WARC-Record-ID"), h.get("WARC-Target-URI"), h.get("WARC-Date"), list(h.items()), block, error)
                        for h, block, error in records(data.as_py()) if error or h.get("WARC-Type") == "response"]
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows) if rows else [[]] * len(kinds), kinds)],
                                                 names=["record_id", "target_uri", "date", "headers", "block", "error"])

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content")
    return files.mapInArrow(tidy(run), RESPONSES)


def convert(responses: DataFrame) -> DataFrame:
    """Derivatives of rows of read_responses that have no error; page_id is null."""

    def run(batches):
        for b in batches:
            rows = [(None, *r) for h, block in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for r in derive(dict(h or []), block or b"")]
            yield _derived(rows, DERIVED)

    return responses.where("error is null").select("headers", "block").mapInArrow(tidy(run), DERIVED)


def gzipped(data: bytes) -> bytes:
    """A record as a gzip member of its own, as WARC files hold them."""
    return gzip.compress(data, mtime=0)
