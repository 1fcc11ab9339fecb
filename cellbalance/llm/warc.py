"""WARC derivatives: metadata and plain-text conversion records for response records.

Every response yields two records that point back to it. The metadata record lists title, language and
outlinks of the page (relative ones resolved) as WARC fields, after the status line and every header of
the response; the conversion record holds the page's text. Both keep the response's target address and
date and name it in WARC-Refers-To; the conversion record keeps the digest of its source and all its
header lines, as one JSON array in WARC-Source-Headers. Records have their own block digests and ids
derived from the response's id, so a rerun writes the same bytes. `warc_members` turns records into gzip
members, `read_members` reads joined members back.

Defined results: null or empty payloads give a metadata record without page fields and an empty
conversion; a null address is left out; a response without a record id has no WARC-Refers-To, and its
derivatives' ids come from its address, date, headers, payload and key; repeated responses give repeated
records with the same ids; a folded header line joins the line before it. Long pages are read once from
start to end. Columns of the input other than the named ones are not read.
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
from urllib.parse import urljoin, urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StructField, StructType

_SPACE = uuid.uuid5(uuid.NAMESPACE_URL, "urn:cellbalance:warc")
_PIECE = re.compile(
    r"<!--(?:.*?-->|.*)|<(script|style|noscript|template)\b(?:.*?</\1\s*>|.*)|<title\b[^<>]*>(?P<title>[^<]*)|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9]*)(?P<attrs>(?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<![^<>]*>",
    re.DOTALL | re.IGNORECASE,
)
_ATTR = re.compile(r"(?<![-\w:.])([a-zA-Z_:][-\w:.]*)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
#: Tags that start a new line, and tags and attributes that link.
_BLOCKS = set("p div section article header footer nav aside main h1 h2 h3 h4 h5 h6 ul ol li table tr td th br hr pre blockquote form dl dt dd figure body".split())
_LINKS = {"a": "href", "area": "href", "link": "href", "img": "src", "iframe": "src", "source": "src", "video": "src", "audio": "src", "embed": "src"}


def digest(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def read_page(page: str, address: str | None) -> tuple[str, str | None, str | None, list[tuple[str, str]]]:
    """Text, title, language and (address, tag/attribute) of links in order."""
    out, title, lang, links, last = [], None, None, [], 0
    for m in _PIECE.finditer(page):
        out.append(page[last : m.start()])
        last = m.end()
        if m["title"] is not None:
            title = title or " ".join(html.unescape(m["title"]).split()) or None
            continue
        tag = (m["tag"] or "").lower()
        if tag in _BLOCKS:
            out.append("\n")
        if m["end"] == "" and tag and (tag in _LINKS or tag in ("html", "base")):
            attrs = {k.lower(): html.unescape(a or b or c) for k, a, b, c in _ATTR.findall(m["attrs"])}
            if tag == "html":
                lang = lang or attrs.get("lang")
            elif tag == "base":
                address = attrs.get("href", address)
            elif target := attrs.get(_LINKS[tag], "").strip():
                try:
                    target = urljoin(address, target) if address else target
                    urlsplit(target)
                except ValueError:
                    continue
                links.append((re.sub(r"\s", "%20", target), f"{tag}/@{_LINKS[tag]}"))
    out.append(page[last:])
    lines = (" ".join(line.split()) for line in html.unescape("".join(out)).split("\n"))
    return "\n".join(x for x in lines if x), title, lang, list(dict.fromkeys(links))


def header_lines(raw: str | None) -> list[str]:
    """Status line and headers of a response, folded lines joined."""
    lines = re.sub(r"\r?\n[ \t]+", " ", raw or "").splitlines()
    return [x.strip() for x in lines if x.strip()]


def _name_of(source: dict, payload: bytes) -> str:
    """What the ids of a response's derivatives are made of."""
    if source["record_id"]:
        return source["record_id"]
    rest = (source.get("key"), source["target_uri"], source["date"], source["http_headers"], digest(payload))
    return json.dumps(["no record id", *rest])


def _record(kind: str, source: dict, name: str, content_type: str, block: bytes, extra: dict) -> dict:
    record_id = f"<urn:uuid:{uuid.uuid5(_SPACE, kind + name)}>"
    headers = {
        "WARC-Type": kind,
        "WARC-Record-ID": record_id,
        "WARC-Date": source["date"],
        "WARC-Target-URI": source["target_uri"],
        "WARC-Refers-To": source["record_id"],
        **extra,
        "Content-Type": content_type,
        "WARC-Block-Digest": digest(block),
        "Content-Length": str(len(block)),
    }
    return {
        "record_type": kind,
        "record_id": record_id,
        "refers_to": source["record_id"],
        "target_uri": source["target_uri"],
        "headers": "".join(f"{k}: {v}\r\n" for k, v in headers.items() if v is not None),
        "block": block,
        "block_digest": headers["WARC-Block-Digest"],
        "content_length": len(block),
    }


def derive(source: dict) -> list[dict]:
    """The metadata and conversion records of one response."""
    payload = source["payload"] or b""
    text, title, lang, links = read_page(payload.decode("utf-8", "replace"), source["target_uri"])
    lines, name = header_lines(source["http_headers"]), _name_of(source, payload)
    status = lines.pop(0) if lines and lines[0].upper().startswith("HTTP/") else None
    fields = [("http-status", status), *(("http-header", x) for x in lines), ("title", title), ("language", lang), *(("outlink", f"{a} {by}") for a, by in links)]
    meta = "".join(f"{k}: {v}\r\n" for k, v in fields if v).encode()
    every = [status, *lines] if status else lines
    refers = {"WARC-Refers-To-Target-URI": source["target_uri"], "WARC-Refers-To-Date": source["date"]}
    conversion = _record(
        "conversion", source, name, "text/plain; charset=utf-8", text.encode(),
        {**refers, "WARC-Source-Payload-Digest": source["payload_digest"] or digest(payload), "WARC-Source-Headers": json.dumps(every) if every else None},
    )
    linked = _record("metadata", source, name, "application/warc-fields", meta, {"WARC-Concurrent-To": conversion["record_id"]})
    return [linked, conversion]


def serialised(record: dict, member: bool = True) -> bytes:
    """The record's bytes; as a gzip member of its own, without a time stamp, unless told otherwise."""
    raw = b"WARC/1.1\r\n" + record["headers"].encode() + b"\r\n" + record["block"] + b"\r\n\r\n"
    return gzip.compress(raw, 6, mtime=0) if member else raw


_ARROW = pa.struct(
    [("record_type", pa.string()), ("record_id", pa.string()), ("refers_to", pa.string()), ("target_uri", pa.string()), ("headers", pa.string()),
     ("block", pa.binary()), ("block_digest", pa.string()), ("content_length", pa.int64())]
)
_SOURCE = ("record_id", "target_uri", "date", "http_headers", "payload", "payload_digest")


def derivatives(responses: DataFrame, key_col: str) -> DataFrame:
    """Two records a response, with the response's key. Responses have the columns record_id,
    target_uri, date, http_headers, payload (binary) and payload_digest, any of them null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 128):
                part = batch.slice(a, 128)
                records = [(r["key"], x) for r in part.to_pylist() for x in derive(r)]
                found = pa.array([x for _, x in records], _ARROW)
                yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in records], pa.int64()), *found.flatten()], names=[key_col, *(f.name for f in _ARROW)])

    schema = f"{key_col} long, record_type string, record_id string, refers_to string, target_uri string, headers string, block binary, block_digest string, content_length long"
    return responses.select(F.col(key_col).cast("long").alias("key"), *_SOURCE).mapInArrow(run, schema)


def page_responses(pages: DataFrame, date: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Raw pages as response records; the id comes from page and address, the digest from the payload."""
    name = F.sha2(F.concat_ws(" ", F.col("page_id").cast("string"), "url"), 256)
    parts = [F.substring(name, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]
    return pages.select(
        "page_id",
        F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *parts), F.lit(">")).alias("record_id"),
        F.col("url").alias("target_uri"),
        F.lit(date).alias("date"),
        F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n").alias("http_headers"),
        F.col("html").cast("binary").alias("payload"),
        F.lit(None).cast("string").alias("payload_digest"),
    )


def warc_members(records: DataFrame) -> DataFrame:
    """The records with `member`, the gzip member of each, ready to be joined into WARC files."""
    columns = records.columns
    headers, block = columns.index("headers"), columns.index("block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 128):
                part = batch.slice(a, 128)
                members = [serialised({"headers": h, "block": b}) for h, b in zip(part.column(headers).to_pylist(), part.column(block).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(members, pa.binary())], names=[*columns, "member"])

    return records.mapInArrow(run, StructType([*records.schema.fields, StructField("member", BinaryType())]))


def read_members(joined: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of joined gzip members."""
    raw = gzip.decompress(joined)
    at = 0
    while at < len(raw):
        start, end = raw.index(b"\r\n", at) + 2, raw.index(b"\r\n\r\n", at)
        held = dict(line.split(": ", 1) for line in raw[start:end].decode().split("\r\n"))
        n = int(held["Content-Length"])
        yield held, raw[end + 4 : end + 4 + n]
        at = end + 4 + n + 4
