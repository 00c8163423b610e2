"""WARC derivatives: metadata and conversion records linked to their responses.

A response is a row (record_id, target_uri, date, http_header, payload).  Each gives one
``metadata`` record (WARC fields: source header lines, title, outlinks) and one
``conversion`` record (plain text).  Both refer to the response by id, target and date, carry
its payload digest and have digests of their own; ids are name-based, so a retried task
writes the same records.

A null or empty payload gives empty text and no outlinks; a null target keeps its records and
leaves out the header lines.  Repeated rows give repeated records of equal id; other columns,
whatever their names, are left behind, an empty table gives no records.  White space and control
characters of a target are percent-encoded in header lines; the column keeps the target as it is.
A page is scanned once from left to right, so its time grows with its length only.
"""

from __future__ import annotations

import base64
import gzip
import html
import io
import re
import uuid
import zlib
from collections.abc import Iterator
from hashlib import sha1

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.llm import kernels

DATE = "1970-01-01T00:00:00Z"
#: Elements whose content is no text; each with what closes it.
_DROP = {name: re.compile(rf"</{name}\s*>", re.I) for name in ("script", "style", "noscript", "template")}
_BREAK = set("p div br li ul ol tr table h1 h2 h3 h4 h5 h6 section article nav header footer title head body blockquote pre hr td th".split())
_NAME = re.compile(r"</?([A-Za-z][A-Za-z0-9]*)(?!\w)")
_HREF = re.compile(r"""<a\b[^>]*?\bhref\s*=\s*(?:"([^">]*)"|'([^'>]*)'|([^\s>]+))""", re.I)
_TITLE = re.compile(r"<title\b[^>]*>", re.I), re.compile(r"</title", re.I)
_SPACE = re.compile(r"[ \t\r\f\v\xa0]+")
_UNSAFE = re.compile(r"[\x00-\x20\x7f]")
SCHEMA = "page_id long, warc_type string, record_id string, refers_to string, target_uri string, source_digest string, block_digest string, content_length long, header string, block string"


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(sha1(data).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(0).join(parts))}>"


def scan(page: str) -> tuple[list[str], list[str]]:
    """(pieces of text and white space for tags, link targets), in one pass from left to right.

    Comments and the content of ``_DROP`` elements are skipped if they are closed; what is searched for in vain once is
    not searched for again, so the time is in proportion to the page.
    """
    pieces, links, at, missing = [], [], 0, set()
    while (start := page.find("<", at)) >= 0:
        pieces.append(page[at:start])
        if page.startswith("<!--", start) and "comment" not in missing:
            end = page.find("-->", start + 4)
            if end >= 0:
                pieces.append(" ")
                at = end + 3
                continue
            missing.add("comment")
        end = page.find(">", start)
        if end < 0:
            return [*pieces, page[start:]], links
        name = _NAME.match(page, start)
        kind = name[1].lower() if name else ""
        if kind in _DROP and kind not in missing and page[start + 1] != "/":
            close = _DROP[kind].search(page, end + 1)
            if close:
                pieces.append(" ")
                at = close.end()
                continue
            missing.add(kind)
        if kind == "a" and (link := _HREF.match(page, start, end + 1)):
            links.append(link[1] or link[2] or link[3] or "")
        pieces.append("\n" if kind in _BREAK else " ")
        at = end + 1
    return [*pieces, page[at:]], links


def plain_text(page: str) -> str:
    """Visible text: scripts, styles and comments are gone, block tags break lines, entities are resolved."""
    text = html.unescape("".join(scan(page)[0]))
    lines = (_SPACE.sub(" ", line).strip() for line in text.split("\n"))
    return "\n".join(line for line in lines if line)


def _title(page: str) -> str | None:
    begin = _TITLE[0].search(page)
    end = begin and _TITLE[1].search(page, begin.end())
    return page[begin.end() : end.start()] if end else None


def metadata_fields(page: str, http_header: str) -> list[tuple[str, str]]:
    """WARC fields of a response: its header lines, title and outlinks, each on one line."""
    title = _title(page)
    one_line = lambda s: " ".join(html.unescape(s).split())
    fields = [("source-header", line) for line in http_header.splitlines() if line.strip()]
    fields += [("title", one_line(title))] if title is not None else []
    return fields + [("outlink", f"{one_line(link)} L a/@href") for link in scan(page)[1]]


def safe(uri: str | None) -> str | None:
    """A URI without white space and control characters, which would end or add a header line; they are percent-encoded."""
    return None if uri is None else _UNSAFE.sub(lambda m: f"%{ord(m[0]):02X}", uri)


def header_block(fields: list[tuple[str, str | None]]) -> str:
    return "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields if v is not None) + "\r\n"


def derived(source_id: str, target: str | None, date: str | None, http_header: str | None, page: str | None) -> Iterator[tuple]:
    """(type, id, source digest, block digest, length, header, block) of a response's two derivatives."""
    page, http_header = page or "", http_header or ""
    of = digest(page.encode("utf-8", "surrogatepass"))
    fields = "".join(f"{k}: {v}\r\n" for k, v in metadata_fields(page, http_header))
    for kind, content, block in (("metadata", "application/warc-fields", fields), ("conversion", "text/plain; charset=utf-8", plain_text(page))):
        raw = block.encode("utf-8", "replace")
        own = record_id(kind, source_id, of)
        head = header_block([
            ("WARC-Type", kind), ("WARC-Record-ID", own), ("WARC-Date", date or DATE), ("WARC-Target-URI", safe(target)), ("WARC-Refers-To", source_id),
            ("WARC-Refers-To-Target-URI", safe(target)), ("WARC-Refers-To-Date", date or DATE), ("X-Source-Payload-Digest", of), ("WARC-Block-Digest", digest(raw)),
            ("Content-Type", content), ("Content-Length", str(len(raw))),
        ])
        yield kind, own, of, digest(raw), len(raw), head, raw.decode()


def responses(pages: DataFrame, date: str = DATE) -> DataFrame:
    """Responses from a table of (page_id, url, html); ids come from the url and the page number."""
    header = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.coalesce(F.octet_length("html"), F.lit(0)).cast("string"), F.lit("\r\n"))
    name = F.md5(F.concat_ws("\u0000", F.coalesce(F.col("url"), F.lit("")), F.col("page_id").cast("string")))
    made = F.concat(F.lit("<urn:uuid:"), F.regexp_replace(name, "^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5"), F.lit(">"))
    return pages.select(F.col("page_id").cast("long").alias("page_id"), made.alias("record_id"), F.col("url").alias("target_uri"), F.lit(date).alias("date"), header.alias("http_header"), F.col("html").alias("payload"))


def derive(source: DataFrame) -> DataFrame:
    """Both derivatives of every response."""
    fields = [(n, pa.int64() if n in ("page_id", "content_length") else pa.string()) for n in (x.split()[0] for x in SCHEMA.split(", "))]

    def rows(batches):
        for batch in batches:
            for page_id, own, target, date, head, page in zip(*(batch.column(i) for i in range(6))):
                source_id, uri = own.as_py(), target.as_py()
                for kind, made, of, block_digest, length, header, block in derived(source_id or "", uri, date.as_py(), head.as_py(), page.as_py()):
                    yield page_id.as_py(), kind, made, source_id, uri, of, block_digest, length, header, block

    wanted = source.select("page_id", "record_id", "target_uri", "date", "http_header", "payload")
    return wanted.mapInArrow(lambda batches: kernels.row_batches(rows(batches), pa.schema(fields), 500), SCHEMA)


def record_bytes(header: str, block: str) -> bytes:
    return header.encode() + block.encode() + b"\r\n\r\n"


def parse_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record of an uncompressed file."""
    return stream_records(io.BytesIO(data))


def stream_records(file) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record, read one by one; a record that is cut short or has no length ends the file."""
    while True:
        line = file.readline()
        while line in (b"\r\n", b"\n"):
            line = file.readline()
        if not line.startswith(b"WARC/"):
            return
        fields = {}
        while (line := file.readline()) not in (b"", b"\r\n", b"\n"):
            name, _, value = line.decode("utf-8", "replace").partition(":")
            fields[name.strip()] = value.strip()
        size = fields.get("Content-Length", "")
        if not size.isdigit():
            return
        block = file.read(int(size))
        if len(block) < int(size):
            return
        yield fields, block


class _Inflated(io.RawIOBase):
    """The gzip members in ``data``, decompressed as they are read; a damaged or missing end is the end."""

    def __init__(self, data: pa.Buffer, chunk: int = 1 << 16):
        self.data, self.chunk, self.at, self.state, self.rest = data, chunk, 0, zlib.decompressobj(31), b""

    def readable(self) -> bool:
        return True

    def readinto(self, into) -> int:
        while not self.rest:
            feed = self.state.unconsumed_tail
            if not feed and self.state.eof:
                feed, self.state = self.state.unused_data, zlib.decompressobj(31)
            if not feed:
                feed = self.data[self.at : self.at + self.chunk].to_pybytes()
                self.at += len(feed)
                if not feed:
                    return 0
            try:
                self.rest = self.state.decompress(feed, 1 << 20)
            except zlib.error:
                self.at, self.state = self.data.size, zlib.decompressobj(31)
                return 0
        n = min(len(into), len(self.rest))
        into[:n], self.rest = self.rest[:n], self.rest[n:]
        return n


def body_text(head: str, body: bytes) -> str:
    """The payload as text: gzip and deflate are undone, the header's charset is used if it is known, else UTF-8."""
    fields = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in head.split("\r\n")[1:])}
    coding = fields.get("content-encoding", "").lower()
    if coding in ("gzip", "x-gzip", "deflate"):
        try:
            body = zlib.decompressobj(47 if "gzip" in coding else 15 if body[:1] == b"\x78" else -15).decompress(body)
        except zlib.error:
            return ""
    charset = re.search(r"charset\s*=\s*[\"']?([\w.-]+)", fields.get("content-type", ""), re.I)
    try:
        return body.decode(charset[1] if charset else "utf-8", "replace")
    except LookupError:
        return body.decode("utf-8", "replace")


def read_responses(spark, path: str) -> DataFrame:
    """Responses of the WARC files under ``path`` (one task per file, gzip or plain); a file's records are decompressed one by one."""
    names = ("page_id", "record_id", "target_uri", "date", "http_header", "payload")
    schema = pa.schema([(n, pa.int64() if n == "page_id" else pa.string()) for n in names])

    def rows(batches):
        for batch in batches:
            for content in batch.column("content"):
                data = content.as_buffer()
                zipped = data[:2].to_pybytes() == b"\x1f\x8b"
                for fields, block in stream_records(io.BufferedReader(_Inflated(data) if zipped else pa.BufferReader(data))):
                    if fields.get("WARC-Type") == "response":
                        head, _, body = block.partition(b"\r\n\r\n")
                        head = head.decode("latin-1")
                        yield None, fields.get("WARC-Record-ID"), fields.get("WARC-Target-URI"), fields.get("WARC-Date"), head, body_text(head, body)

    files = spark.read.format("binaryFile").load(path).select("content")
    return files.mapInArrow(lambda b: kernels.row_batches(rows(b), schema, 200), "page_id long, record_id string, target_uri string, date string, http_header string, payload string")


def write_records(records: DataFrame, path: str) -> None:
    """Write derivatives under ``path`` as Parquet rows (record_id, record); each record is a gzip member, so their concatenation is a WARC file."""
    schema = pa.schema([("record_id", pa.string()), ("record", pa.binary())])

    def rows(batches):
        for batch in batches:
            for own, header, block in zip(*(batch.column(c).to_pylist() for c in ("record_id", "header", "block"))):
                yield own, gzip.compress(record_bytes(header, block), mtime=0)

    wanted = records.select("record_id", "header", "block")
    wanted.mapInArrow(lambda b: kernels.row_batches(rows(b), schema, 500), "record_id string, record binary").write.parquet(path)


def op1_warc_derivatives(spark, sf_dir: str) -> DataFrame:
    """Both derivatives of every page of ``pages``."""
    return derive(responses(spark.read.parquet(f"{sf_dir}/pages.parquet")))
