"""WARC derivatives: response records become linked metadata (JSON) and plain-text conversion records.

A page becomes a response record; each derivative refers to its response's id and carries the source's target URI,
date and payload digest; digests are SHA-1 in base 32 over the block or payload, as WARC files give them. Ids are name-based UUIDs, so a
task that runs again writes the same records.

Headers are kept in order with their names as written; one that stands several times (Set-Cookie, WARC-Concurrent-To) is a list of its values.
Pages of a table have neither status nor date, so their responses say 200 and the date that is given; records of WARC files keep their own.

Defined cases: a null or empty html gives derivatives with an empty payload; a null url an empty target; repeated rows
repeat their records; a null page_id is kept; other columns are ignored; an empty table gives an empty result; malformed html is read as far as tags can be told. Of a
file that ends within a record, the whole records before are read; gzipped files are read member by member.
"""

from __future__ import annotations

import base64
import hashlib
import html
import json
import re
import uuid
import zlib
from collections.abc import Iterable, Iterator
from urllib.parse import urljoin

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import ship, sliced

EPOCH = "1970-01-01T00:00:00Z"
CRLF = "\r\n"


def digest(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def record_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join(map(str, parts)))}>"


class Record:
    """A WARC record: named fields in order, and a block."""

    def __init__(self, fields: list[tuple[str, str]], block: bytes):
        self.fields, self.block = fields, block

    def get(self, name: str) -> str | None:
        return next((v for k, v in self.fields if k.lower() == name.lower()), None)

    def to_bytes(self) -> bytes:
        head = CRLF.join(["WARC/1.0", *(f"{k}: {v}" for k, v in self.fields), f"Content-Length: {len(self.block)}"])
        return head.encode() + b"\r\n\r\n" + self.block + b"\r\n\r\n"


def unzipped(data: bytes) -> bytes:
    """The members of gzipped data, one after the other, as far as they are whole; other data as it is."""
    if data[:2] != b"\x1f\x8b":
        return data
    out = []
    while data[:2] == b"\x1f\x8b":
        member = zlib.decompressobj(wbits=31)
        try:
            out.append(member.decompress(data))
        except zlib.error:
            break
        data = member.unused_data
    return b"".join(out)


def parse(data: bytes) -> Iterator[Record]:
    """The records of WARC data, as far as they are whole."""
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        fields = named(data[at:end].decode("utf-8", "replace").split(CRLF)[1:])
        length = next((v for k, v in fields if k.lower() == "content-length"), "")
        if not length.isdecimal():
            at = end
            continue
        stop = end + 4 + int(length)
        if stop > len(data):
            return
        yield Record([f for f in fields if f[0].lower() != "content-length"], data[end + 4 : stop])
        at = stop


def named(rows: list[str]) -> list[tuple[str, str]]:
    """(name, value) of header lines; a line that begins with a blank goes on with the one before."""
    out: list[tuple[str, str]] = []
    for x in rows:
        if out and x[:1] in (" ", "\t"):
            out[-1] = out[-1][0], f"{out[-1][1]} {x.strip()}".strip()
        elif x:
            k, _, v = x.partition(":")
            out.append((k.strip(), v.strip()))
    return out


def headers_json(fields: list[tuple[str, str]]) -> dict[str, str | list[str]]:
    """Headers by name, in order; a repeated one has all its values, under its first spelling."""
    out: dict[str, tuple[str, list[str]]] = {}
    for k, v in fields:
        out.setdefault(k.lower(), (k, []))[1].append(v)
    return {k: v[0] if len(v) == 1 else v for k, v in out.values()}


def response(page_id: object, url: str | None, body: str | None, date: str = EPOCH) -> Record:
    payload = (body or "").encode("utf-8", "replace")
    block = CRLF.join(["HTTP/1.1 200 OK", "Content-Type: text/html; charset=utf-8", f"Content-Length: {len(payload)}", "", ""]).encode() + payload
    fields = [
        ("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", page_id, url, digest(payload))), ("WARC-Date", date), ("WARC-Target-URI", re.sub(r"\s", "%20", url or "")),
        ("Content-Type", "application/http; msgtype=response"), ("WARC-Payload-Digest", digest(payload)), ("WARC-Block-Digest", digest(block)),
    ]
    return Record(fields, block)


def split_http(block: bytes) -> tuple[str, list[tuple[str, str]], bytes]:
    """Status line, headers and payload of an HTTP response."""
    head, gap, payload = block.partition(b"\r\n\r\n")
    first, *rest = head.decode("iso-8859-1").split(CRLF)
    return first, named(rest), payload if gap else b""


_DROP = re.compile(r"<!--.*?(?:-->|$)|<(script|style|noscript|template)\b[^>]*>.*?(?:</\1\s*>|$)", re.I | re.S)
_TITLE = re.compile(r"<title\b[^>]*>(.*?)</title\s*>", re.I | re.S)
_HEAD = re.compile(r"<title\b[^>]*>.*?(?:</title\s*>|$)", re.I | re.S)
_BLOCK = re.compile(r"</?(?:p|div|br|li|ul|ol|h[1-6]|tr|td|th|table|article|section|header|footer|nav|aside|main|blockquote|pre|hr|dl|dt|dd|form|option)\b[^>]*>", re.I)
_TAG = re.compile(r"<[/!?a-zA-Z][^>]*>")
_LINK = re.compile(r"<(a|img|link|script|iframe|form)\b[^>]*?\b(href|src|action)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_META = re.compile(r"<meta\b[^>]*>", re.I)
_ATTR = re.compile(r"([a-zA-Z:-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")
_BLANK = re.compile(r"[ \t\r\f\v\xa0]+")


def plain_text(page: str) -> str:
    """The visible text, one line for each block, without blank lines."""
    page = _TAG.sub("", _BLOCK.sub("\n", _HEAD.sub("\n", _DROP.sub(" ", page))))
    lines = (_BLANK.sub(" ", x).strip() for x in html.unescape(page).split("\n"))
    return "\n".join(x for x in lines if x)


def page_metadata(page: str, base: str) -> dict:
    title = _TITLE.search(page)
    links = []
    for m in _LINK.finditer(page):
        href = html.unescape(m[3] or m[4] or m[5] or "")
        try:
            links.append({"path": f"{m[1].upper()}@/{m[2].lower()}", "url": urljoin(base, href)})
        except ValueError:
            links.append({"path": f"{m[1].upper()}@/{m[2].lower()}", "url": href})
    metas = [{k.lower(): html.unescape(a or b or c or "") for k, a, b, c in _ATTR.findall(m[0])} for m in _META.finditer(page)]
    return {"Head": {"Title": html.unescape(title[1]).strip() if title else "", "Metas": metas}, "Links": links}


def derivatives(source: Record) -> list[Record]:
    """The metadata and the conversion record of a response."""
    status, headers, payload = split_http(source.block)
    page, uri = payload.decode("utf-8", "replace"), source.get("WARC-Target-URI") or ""
    origin = source.get("WARC-Record-ID") or ""
    envelope = {
        "Envelope": {
            "WARC-Header-Metadata": headers_json(source.fields),
            "Payload-Metadata": {"HTTP-Response-Metadata": {"Response-Message": status, "Headers": headers_json(headers), "Entity-Length": len(payload), "Entity-Digest": digest(payload), "HTML-Metadata": page_metadata(page, uri)}},
        }
    }
    out = []
    for kind, content, block in (
        ("metadata", "application/json", json.dumps(envelope, ensure_ascii=False, separators=(",", ":")).encode("utf-8", "replace")),
        ("conversion", "text/plain", plain_text(page).encode("utf-8", "replace")),
    ):
        out.append(Record([
            ("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, origin)), ("WARC-Refers-To", origin), ("WARC-Date", source.get("WARC-Date") or EPOCH), ("WARC-Target-URI", uri),
            ("Content-Type", content), ("WARC-Payload-Digest", source.get("WARC-Payload-Digest") or digest(payload)), ("WARC-Block-Digest", digest(block)),
        ], block))
    return out


SCHEMA = "page_id bigint, record_type string, record_id string, refers_to string, target_uri string, warc_date string, source_payload_digest string, block_digest string, content_length bigint, block string"
_NAMES = [x.split()[0] for x in SCHEMA.split(", ")]
_FIELDS = ("WARC-Type", "WARC-Record-ID", "WARC-Refers-To", "WARC-Target-URI", "WARC-Date", "WARC-Payload-Digest", "WARC-Block-Digest")


def _row(page_id: int | None, r: Record) -> tuple:
    return (page_id, *(r.get(f) for f in _FIELDS), len(r.block), r.block.decode("utf-8", "replace"))


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * len(_NAMES)
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if n in ("page_id", "content_length") else pa.string()) for n, c in zip(_NAMES, cols, strict=True)], names=_NAMES)


def build_derivatives(pages: DataFrame, date: str = EPOCH) -> DataFrame:
    """Two rows for each page (page_id, url, html): its metadata and its conversion record."""
    ship(pages.sparkSession)

    def made(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, 256):
            yield _batch([_row(i, r) for i, u, h in zip(*(c.to_pylist() for c in b.columns), strict=True) for r in derivatives(response(i, u, h, date))])

    return pages.select(pages["page_id"].cast("bigint").alias("page_id"), "url", "html").mapInArrow(made, SCHEMA)


def record_bytes(rows: DataFrame) -> DataFrame:
    """Each derivative row as the bytes of its record (column ``record``), to be written to WARC files."""
    ship(rows.sparkSession)

    def made(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                kind = "application/json" if r["record_type"] == "metadata" else "text/plain"
                fields = list(zip(_FIELDS, (r[n] or "" for n in _NAMES[1:8]), strict=True))
                out.append(Record([*fields, ("Content-Type", kind)], (r["block"] or "").encode("utf-8", "replace")).to_bytes())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.binary())], names=["page_id", "record_type", "record"])

    return rows.select(*_NAMES).mapInArrow(made, "page_id bigint, record_type string, record binary")


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """The derivative rows of the response records of WARC files, gzipped or not, through Spark's binary reader (a file is one value: at most 2 GB); page_id is null."""
    ship(spark)

    def made(batches):
        for b in sliced(batches, 1):
            rows: list[tuple] = []
            for r in parse(unzipped(b.column(0)[0].as_py())):
                rows += [_row(None, d) for d in derivatives(r)] if r.get("WARC-Type") == "response" else []
                if len(rows) >= 256:
                    yield _batch(rows)
                    rows = []
            yield _batch(rows)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(made, SCHEMA)


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_derivatives(spark.read.parquet(f"{sf_dir}/pages.parquet"))
