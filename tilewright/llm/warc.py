"""WARC derivatives: metadata and plain-text conversion records of web responses.

A response record gets two derivatives: a `metadata` record (JSON: the source record's headers, its
HTTP status and headers, title, links and lengths) and a `conversion` record (text/plain). Both
carry WARC-Refers-To with the response's record id and the response's target, date and payload
digest (as WARC-Refers-To-Payload-Digest), and digests of their own blocks. Record ids are name
based, so a task that runs again gives the same records.

Null HTML is an empty payload, a null url an empty target; both still give two records. A page
without a body converts to an empty block. Mark-up is read once from start to end, however broken.
Repeated rows give repeated records, an empty table none. Broken records in a file raise ValueError
with their offset. Only page_id, url and html are read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import json
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .html_extract import ATTR, NAME, tokens

FIXED_DATE = "2024-01-01T00:00:00Z"
_SPACE = uuid.uuid5(uuid.NAMESPACE_URL, "urn:warc:derivatives")
# Elements that begin a line, that link, and that stand in a head.
_BREAK = frozenset("p div h1 h2 h3 h4 h5 h6 li ul ol tr table article section header footer nav aside blockquote pre br".split())
_LINK = {"a": "href", "img": "src", "link": "href", "script": "src", "iframe": "src", "form": "action"}
_HEAD = frozenset("head title meta link base".split())


def sha1(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(_SPACE, json.dumps(parts))}>"


def serialise(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record of an uncompressed file."""
    at = 0
    while at < len(data):
        end = data.find(b"\r\n\r\n", at)
        if end < 0 or not data.startswith(b"WARC/", at):
            raise ValueError(f"no WARC record at byte {at}")
        lines = data[at:end].decode().split("\r\n")[1:]
        headers = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
        size = int(headers.get("Content-Length", "-1"))
        block = data[end + 4 : end + 4 + size]
        if size < 0 or len(block) < size:
            raise ValueError(f"record at byte {at} is cut short")
        yield headers, block
        at = end + 4 + size + 4


def response_record(page_id: int | None, url: str | None, page: str | None, date: str = FIXED_DATE) -> tuple[list[tuple[str, str]], bytes]:
    """Headers and block of the response that a stored page stands for."""
    body = (page or "").encode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    target = re.sub(r"\s", "%20", url or "")
    headers = [
        ("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", page_id, target, sha1(body))), ("WARC-Date", date), ("WARC-Target-URI", target),
        ("Content-Type", "application/http; msgtype=response"), ("WARC-Payload-Digest", sha1(body)), ("WARC-Block-Digest", sha1(http + body)),
    ]
    return headers, http + body


def plain_text(page: str) -> str:
    """The text outside the head, one line for each block."""
    parts, at, head = [], 0, False
    for begin, end, closing, tag, _ in tokens(page):
        if not head:
            parts.append(page[at:begin])
        at = end
        if tag == "head":
            head = not closing
        elif head and tag and tag not in _HEAD:
            head = False
        parts.append("\n" if tag in _BREAK else " ")
    if not head:
        parts.append(page[at:])
    # Line breaks of the source are no more than spaces.
    lines = "".join(x if x == "\n" else x.replace("\n", " ") for x in parts).split("\n")
    lines = (" ".join(html.unescape(x).split()) for x in lines)
    return "\n".join(x for x in lines if x)


def title_and_links(page: str) -> tuple[str | None, list[dict[str, str]]]:
    title, begun, links = None, None, []
    for begin, end, closing, tag, attrs in tokens(page):
        if tag == "title" and title is None:
            if closing and begun is not None:
                title = html.unescape(page[begun:begin]).strip()
            elif not closing and begun is None:
                begun = end
        if not tag:  # a script or the like, with its content
            head = NAME.match(page, begin, end)
            tag, attrs = (head[2].lower(), page[head.end() : page.find(">", begin)]) if head else ("", "")
        if not closing and tag in _LINK:
            found = next((a or b or c for name, a, b, c in ATTR.findall(attrs) if name.lower() == _LINK[tag]), None)
            if found is not None:
                links.append({"tag": tag, "url": html.unescape(found)})
    return title, links


def derivatives(headers: list[tuple[str, str]], block: bytes) -> list[tuple[list[tuple[str, str]], bytes]]:
    """The metadata and the conversion record of a response record."""
    source = dict(headers)
    head, _, body = block.partition(b"\r\n\r\n")
    status, *fields = head.decode("utf-8", "replace").split("\r\n")
    page = body.decode("utf-8", "replace")
    title, links = title_and_links(page)
    text = plain_text(page).encode()
    meta = json.dumps({
        "Envelope": {"WARC-Header-Metadata": source, "Payload-Metadata": {
            "HTTP-Response-Metadata": {
                "Response-Message": status, "Headers": dict(f.split(": ", 1) for f in fields if ": " in f), "Entity-Length": len(body), "Entity-Digest": sha1(body),
                "HTML-Metadata": {"Title": title, "Links": links},
            }}},
        "Derivatives": {"conversion": record_id("conversion", source["WARC-Record-ID"])},
    }, ensure_ascii=False, sort_keys=True).encode()
    out = []
    for kind, content, media in (("metadata", meta, "application/json"), ("conversion", text, "text/plain")):
        out.append(([
            ("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, source["WARC-Record-ID"])), ("WARC-Date", source["WARC-Date"]), ("WARC-Target-URI", source["WARC-Target-URI"]),
            ("WARC-Refers-To", source["WARC-Record-ID"]), ("WARC-Refers-To-Target-URI", source["WARC-Target-URI"]), ("WARC-Refers-To-Date", source["WARC-Date"]),
            ("WARC-Refers-To-Payload-Digest", source["WARC-Payload-Digest"]), ("Content-Type", media), ("WARC-Block-Digest", sha1(content)),
        ], content))
    return out


RECORD = "page_id long, record_type string, record_id string, refers_to string, target_uri string, source_payload_digest string, block_digest string, block_length long, record binary"


def build_derivatives(pages: DataFrame) -> DataFrame:
    """Two rows for each page: the fields of RECORD, `record` being the whole serialised record."""

    def build(batches):
        names = [x.split()[0] for x in RECORD.split(", ")]
        for batch in batches:
            rows = []
            for p, u, h in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html"))):
                for headers, block in derivatives(*response_record(p, u, h)):
                    v = dict(headers)
                    rows.append((p, v["WARC-Type"], v["WARC-Record-ID"], v["WARC-Refers-To"], v["WARC-Target-URI"], v["WARC-Refers-To-Payload-Digest"], v["WARC-Block-Digest"], len(block), serialise(headers, block)))
            kinds = [pa.int64(), *[pa.string()] * 6, pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(build, RECORD)


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """path, headers (map) and block of every record of the WARC files (.warc, .warc.gz) under path."""

    def records(batches):
        for batch in batches:
            for p, c in zip(batch.column("path").to_pylist(), batch.column("content").to_pylist()):
                found = list(parse(gzip.decompress(c) if c[:2] == b"\x1f\x8b" else c))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([p] * len(found)), pa.array([list(h.items()) for h, _ in found], pa.map_(pa.string(), pa.string())), pa.array([b for _, b in found], pa.binary())],
                    ["path", "headers", "block"],
                )

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(records, "path string, headers map<string,string>, block binary")


def warc_members(records: DataFrame) -> DataFrame:
    """One gzip member per record (their concatenation is a .warc.gz file)."""

    def squeeze(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("record_id"), pa.array([gzip.compress(r, mtime=0) for r in batch.column("record").to_pylist()], pa.binary())], ["record_id", "member"])

    return records.select("record_id", "record").mapInArrow(squeeze, "record_id string, member binary")
