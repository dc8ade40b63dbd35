"""WARC derivatives: metadata and plain-text conversion records made from response records.

A response record becomes a metadata record (what its headers, title, language and links say) and a
conversion record (its text). Both carry WARC-Refers-To with the id of the response, its target URI
and date, and digests: each record's own block digest, and the payload digest of the source. Ids are
derived from the source's id and the kind of record, so a run that is repeated makes the same ones.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import re
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._blocks import table

CRLF = b"\r\n"
VERSION = b"WARC/1.1"
#: Capture date of pages that come without one.
NO_DATE = "1970-01-01T00:00:00Z"

RECORD_SCHEMA = T.StructType(
    [
        T.StructField("source_key", T.StringType()), T.StructField("record_type", T.StringType()), T.StructField("record_id", T.StringType()), T.StructField("refers_to", T.StringType()),
        T.StructField("target_uri", T.StringType()), T.StructField("warc_date", T.StringType()), T.StructField("content_type", T.StringType()), T.StructField("content_length", T.LongType()),
        T.StructField("block_digest", T.StringType()), T.StructField("payload_digest", T.StringType()), T.StructField("source_headers", T.MapType(T.StringType(), T.StringType())), T.StructField("block", T.BinaryType()),
    ]
)


def digest(data: bytes) -> str:
    """The usual form of WARC digests: SHA-1 in base 32."""
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode("ascii")


@dataclass
class Record:
    """One record: its headers in order, and its block."""

    headers: list[tuple[str, str]]
    block: bytes = b""

    def get(self, name: str) -> str | None:
        return next((v for k, v in self.headers if k.lower() == name.lower()), None)

    def to_bytes(self) -> bytes:
        lines = [VERSION, *(f"{k}: {v}".encode() for k, v in self.headers), f"Content-Length: {len(self.block)}".encode()]
        return CRLF.join(lines) + CRLF * 2 + self.block + CRLF * 2


def record_id(*parts: str) -> str:
    """A record id that depends on its parts alone."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(31).join(parts))}>"


def one_line(value: str) -> str:
    """A value that may stand in a header."""
    return re.sub(r"[\r\n\t\x00]+", " ", value).strip()


def response(key: str, url: str, body: str, date: str = NO_DATE) -> Record:
    """A response record for a page; its id depends on the key, the address and the payload."""
    payload = body.encode("utf-8", "surrogatepass")
    head = CRLF.join([b"HTTP/1.1 200 OK", b"Content-Type: text/html; charset=utf-8", f"Content-Length: {len(payload)}".encode()])
    block = head + CRLF * 2 + payload
    return Record(
        [
            ("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", key, url, digest(payload))), ("WARC-Date", date), ("WARC-Target-URI", one_line(url)),
            ("Content-Type", "application/http; msgtype=response"), ("WARC-Block-Digest", digest(block)), ("WARC-Payload-Digest", digest(payload)),
        ],
        block,
    )


def parse(data: bytes) -> Iterator[Record]:
    """The records of an uncompressed WARC file; a record that is cut off raises ValueError."""
    at = 0
    while at < len(data):
        if data[at : at + 2] == CRLF:
            at += 2
            continue
        end = data.find(CRLF * 2, at)
        if not data.startswith(b"WARC/", at) or end < 0:
            raise ValueError(f"no WARC record at byte {at}")
        headers: list[tuple[str, str]] = []
        for line in data[at:end].split(CRLF)[1:]:
            if line[:1] in b" \t" and headers:
                headers[-1] = (headers[-1][0], headers[-1][1] + " " + line.decode("utf-8", "replace").strip())
            else:
                name, _, value = line.decode("utf-8", "replace").partition(":")
                headers.append((name.strip(), value.strip()))
        record = Record([h for h in headers if h[0].lower() != "content-length"])
        size = int(next((v for k, v in headers if k.lower() == "content-length"), "0"))
        record.block = data[end + 4 : end + 4 + size]
        if len(record.block) < size:
            raise ValueError(f"the record at byte {at} is cut off")
        yield record
        at = end + 4 + size


@dataclass
class Http:
    """The message in a response record's block."""

    status: str = ""
    headers: list[tuple[str, str]] = field(default_factory=list)
    payload: bytes = b""

    @classmethod
    def of(cls, block: bytes) -> Http:
        head, found, payload = block.partition(CRLF * 2)
        if not block.startswith(b"HTTP/") or not found:
            return cls(payload=block)
        first, *rest = head.split(CRLF)
        split = (line.decode("latin-1").partition(":") for line in rest)
        return cls(first.decode("latin-1"), [(k.strip(), v.strip()) for k, _, v in split], payload)

    def charset(self) -> str:
        """From the header, else from the first bytes of the page, else UTF-8."""
        own = next((v for k, v in self.headers if k.lower() == "content-type"), "")
        m = re.search(r"charset=[\"']?([\w.-]+)", own, re.I) or re.search(r"<meta[^>]{0,200}charset=[\"']?([\w.-]+)", self.payload[:2048].decode("latin-1"), re.I)
        name = m[1] if m else "utf-8"
        try:
            b"".decode(name)
        except LookupError:
            return "utf-8"
        return name

    def text(self) -> str:
        return self.payload.decode(self.charset(), "replace")


_DROPPED = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|head)\b.*?(?:</\1\s*>|\Z)", re.S | re.I)
_BLOCK = re.compile(r"</?(?:p|div|br|hr|li|ul|ol|dl|dt|dd|table|tr|td|th|h[1-6]|article|section|header|footer|nav|aside|main|form|pre|blockquote|figure|figcaption|body|html|title)\b[^>]*>", re.I)
_TAG = re.compile(r"<[/!?a-zA-Z][^>]*(?:>|\Z)")
_BLANKS, _LINES = re.compile(r"[ \t\r\f\v\xa0]+"), re.compile(r" ?\n[ \n]*")


def plain_text(page: str) -> str:
    """The readable text of a page: one line for each block, entities decoded, blanks collapsed."""
    page = page.replace("\r\n", "\n").replace("\n", " ")
    page = _TAG.sub("", _BLOCK.sub("\n", _DROPPED.sub(" ", page)))
    return _LINES.sub("\n", _BLANKS.sub(" ", html.unescape(page).replace("\r", " "))).strip()


def facts(page: str) -> list[tuple[str, str]]:
    """Fields of a metadata record: title, language, number of links and the links."""
    title = re.search(r"<title[^>]*>(.*?)</title", page, re.S | re.I)
    lang = re.search(r"<html[^>]*\blang=[\"']?([\w-]+)", page, re.I)
    links = list(dict.fromkeys(one_line(html.unescape(a or b)) for a, b in re.findall(r"<a\b[^>]*\bhref=(?:\"([^\"]*)\"|'([^']*)')", page, re.I)))
    out = [("title", one_line(html.unescape(_TAG.sub("", title[1]))))] if title else []
    out += [("language", lang[1])] if lang else []
    return [*out, ("links", str(len(links))), *(("outlink", x) for x in links)]


def derive(source: Record) -> list[Record]:
    """The metadata and the conversion record of a response; none for records of other types."""
    if (source.get("WARC-Type") or "").lower() != "response":
        return []
    http = Http.of(source.block)
    page = http.text()
    origin = source.get("WARC-Record-ID") or record_id("unnamed", digest(source.block))
    shared = [("WARC-Date", source.get("WARC-Date") or NO_DATE), ("WARC-Target-URI", source.get("WARC-Target-URI") or ""), ("WARC-Refers-To", origin)]
    payload = source.get("WARC-Payload-Digest") or digest(http.payload)
    fields = [("http-status", http.status), *((f"http-header-{k.lower()}", v) for k, v in http.headers), *((f"source-{k.lower()}", v) for k, v in source.headers), ("source-payload-digest", payload), ("charset", http.charset()), *facts(page)]
    made = []
    for kind, content_type, block in (
        ("metadata", "application/warc-fields", b"".join(f"{k}: {one_line(v)}\r\n".encode("utf-8", "replace") for k, v in fields)),
        ("conversion", "text/plain; charset=utf-8", plain_text(page).encode("utf-8", "replace")),
    ):
        own = [("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, origin)), *shared, ("Content-Type", content_type), ("WARC-Block-Digest", digest(block))]
        made.append(Record([*own, ("WARC-Source-Payload-Digest", payload)], block))
    return made


def _rows(key: str | None, source: Record, made: Iterable[Record]) -> Iterator[dict]:
    for r in made:
        yield {
            "source_key": key, "record_type": r.get("WARC-Type"), "record_id": r.get("WARC-Record-ID"), "refers_to": r.get("WARC-Refers-To"), "target_uri": r.get("WARC-Target-URI"), "warc_date": r.get("WARC-Date"),
            "content_type": r.get("Content-Type"), "content_length": len(r.block), "block_digest": r.get("WARC-Block-Digest"), "payload_digest": r.get("WARC-Source-Payload-Digest"),
            "source_headers": list({k.lower(): v for k, v in source.headers}.items()), "block": r.block,
        }


def _batches(rows: Iterator[dict], schema: pa.Schema, most: int = 256) -> Iterator[pa.RecordBatch]:
    held: list[dict] = []
    for row in rows:
        held.append(row)
        if len(held) == most:
            yield pa.RecordBatch.from_pylist(held, schema)
            held = []
    if held:
        yield pa.RecordBatch.from_pylist(held, schema)


_ARROW = pa.schema(
    [(n, pa.string()) for n in ("source_key", "record_type", "record_id", "refers_to", "target_uri", "warc_date", "content_type")]
    + [("content_length", pa.int64()), ("block_digest", pa.string()), ("payload_digest", pa.string()), ("source_headers", pa.map_(pa.string(), pa.string())), ("block", pa.binary())]
)


def derivatives_of_pages(pages: DataFrame, key: str = "page_id", url: str = "url", body: str = "html", date: str = NO_DATE) -> DataFrame:
    """Two linked records (metadata, conversion) for the response record of each page, as rows of RECORD_SCHEMA.

    A null body counts as an empty page and a null address as an empty one; both still give their two
    records. Repeated rows give records with equal ids. Other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for batch in batches:
                for i in range(batch.num_rows):
                    k, u, b = (batch.column(c)[i].as_py() for c in range(3))
                    source = response(k or "", u or "", b or "", date)
                    yield from _rows(k, source, derive(source))

        yield from _batches(rows(), _ARROW)

    return pages.select(F.col(key).cast("string"), F.col(url).cast("string"), F.col(body).cast("string")).mapInArrow(run, RECORD_SCHEMA)


def derivatives_of_files(spark: SparkSession, path: str) -> DataFrame:
    """The same for the response records of WARC files (plain or gzip), one file a task at a time."""
    files = spark.read.format("binaryFile").load(path).select("path", "content")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for batch in batches:
                for i in range(batch.num_rows):
                    name, data = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                    for source in parse(gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data):
                        yield from _rows(name, source, derive(source))

        yield from _batches(rows(), _ARROW)

    return files.mapInArrow(run, RECORD_SCHEMA)


def as_warc(records: DataFrame) -> DataFrame:
    """Each row of RECORD_SCHEMA as one gzip member of a WARC file: record_id, content.

    Members that are written one behind the other make a valid compressed WARC file.
    """
    schema = T.StructType([T.StructField("record_id", T.StringType()), T.StructField("content", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            members = []
            for r in batch.to_pylist():
                headers = [("WARC-Type", r["record_type"]), ("WARC-Record-ID", r["record_id"]), ("WARC-Date", r["warc_date"]), ("WARC-Target-URI", r["target_uri"]), ("WARC-Refers-To", r["refers_to"])]
                headers += [("Content-Type", r["content_type"]), ("WARC-Block-Digest", r["block_digest"]), ("WARC-Source-Payload-Digest", r["payload_digest"])]
                members.append(gzip.compress(Record([(k, v) for k, v in headers if v is not None], r["block"]).to_bytes(), mtime=0))
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index("record_id")), pa.array(members, pa.binary())], schema.names)

    return records.mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op4: metadata and conversion records of every page; the block as text."""
    made = derivatives_of_pages(table(spark, sf_dir, "pages"))
    headers = F.to_json(F.map_from_entries(F.array_sort(F.map_entries("source_headers")))).alias("source_headers")
    return made.select(F.col("source_key").cast("long").alias("page_id"), *[c for c in RECORD_SCHEMA.names if c not in ("source_key", "source_headers", "block")], headers, F.col("block").cast("string").alias("content"))
