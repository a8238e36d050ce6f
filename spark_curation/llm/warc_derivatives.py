"""WARC derivatives: response records to linked metadata and plain-text conversion records.

A record is a row: version and named fields, the block's bytes and the digests. A
response's derivatives carry WARC-Refers-To with its record id, the target URI and
date they were made from, and a digest of their own; the metadata record keeps the
HTTP headers of the source. Record ids are derived from content, so that a retried
task or a second run makes the same archive.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_curation.llm.markup import ATTRIBUTE, Scanner

VERSION = "WARC/1.1"
SCHEMA = (
    "page_id long, record_type string, record_id string, refers_to string, target_uri string, warc_date string, "
    "content_type string, block_digest string, payload_digest string, content_length long, block binary"
)
_NAMES = [c.split()[0] for c in SCHEMA.split(", ")]
_KINDS = [pa.int64(), *[pa.string()] * 8, pa.int64(), pa.binary()]
#: Elements whose content is no text, that end a line, and cells.
HIDDEN = frozenset("script style title noscript template svg iframe object".split())
LINES = frozenset("p div li ul ol dl dt dd h1 h2 h3 h4 h5 h6 nav article section header footer main aside form table tr blockquote pre figure figcaption body html br hr address fieldset option".split())
CELLS = frozenset(("td", "th"))
_CHARSET = re.compile(r"charset\s*=\s*\"?([\w.:-]+)")
_LINE_END = re.compile(r"[\r\n\0]+")


def digest(data: bytes) -> str:
    """A labelled SHA-1 in base 32, as archives write it."""
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(31).join(map(str, parts)))}>"


@dataclass
class Page:
    """What one pass over a page's markup finds."""

    text: str
    title: str = ""
    language: str = ""
    links: list[str] = field(default_factory=list)


def read_page(page: str) -> Page:
    """The visible text, one block on a line, character references decoded; title, declared language and link targets.

    A head counts as a head only if it is closed before the first block.
    """
    lines: list[list[str]] = [[]]
    found = Page("")
    head = -1
    for text, name, more in Scanner(page.replace("\0", ""), HIDDEN):
        lines[-1].append(html.unescape(text) if "&" in text else text)
        bare = name.removeprefix("/")
        if bare == "head":
            if name[0] == "/" and head >= 0:
                del lines[head:]
                lines.append([])
            head = len(lines) - 1 if name == "head" else -1
            if head >= 0:
                lines.append([])
                head += 1
        elif bare in LINES:
            lines.append([])
            if bare != "html":
                head = -1
        elif bare in CELLS or name in HIDDEN or name == "!":
            lines[-1].append(" ")
        if name == "title" and not found.title:
            found.title = " ".join(html.unescape(more[: more.lower().rfind("</title")] if "</" in more else more).split())
        elif name in ("a", "html"):
            get = {k.lower(): html.unescape(a or b or c) for k, a, b, c in reversed(ATTRIBUTE.findall(more))}
            if name == "a" and "href" in get:
                found.links.append(get["href"])
            elif name == "html" and not found.language:
                found.language = get.get("lang", "")
    found.text = "\n".join(x for x in (" ".join("".join(parts).split()) for parts in lines) if x)
    return found


def plain_text(page: str) -> str:
    return read_page(page).text


def response(page_id: int | None, url: str | None, page: str | None, date: str) -> tuple:
    """A response record of a stored page; a null page is an empty one."""
    body = (page or "").encode("utf-8", "surrogatepass")
    date = date or ""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    block, url = head + body, url or ""
    return page_id, "response", record_id("response", page_id, url, date, digest(body)), None, url, date, "application/http; msgtype=response", digest(block), digest(body), len(block), block


def split_http(block: bytes) -> tuple[list[tuple[str, str]], bytes]:
    """Header fields and body of a response's block; a block without headers is all body."""
    head, gap, body = block.partition(b"\r\n\r\n")
    if not gap or not head.startswith(b"HTTP/"):
        return [], block
    lines = head.decode("latin-1").split("\r\n")
    return [(k.strip(), v.strip()) for k, _, v in (x.partition(":") for x in lines[1:]) if _], body


def header(headers: list[tuple[str, str]], name: str) -> str:
    return next((v for k, v in headers if k.lower() == name), "")


def charset(headers: list[tuple[str, str]]) -> str:
    name = (_CHARSET.search(header(headers, "content-type")) or [None, "utf-8"])[1]
    try:
        b"".decode(name)
    except LookupError:
        return "utf-8"
    return name


def _unchunked(body: bytes) -> bytes:
    out, at = [], 0
    while True:
        end = body.index(b"\r\n", at)
        size = int(body[at:end].split(b";")[0], 16)
        if not size:
            return b"".join(out)
        out.append(body[end + 2 : end + 2 + size])
        at = end + 4 + size


def payload(headers: list[tuple[str, str]], body: bytes) -> bytes:
    """The body with its transfer and content encodings undone; one that does not decode was stored decoded and stays."""
    codes = [x.strip().lower() for name in ("transfer-encoding", "content-encoding") for x in reversed(header(headers, name).split(","))]
    undo = {
        "chunked": _unchunked,
        "gzip": lambda b: zlib.decompress(b, 47),
        "x-gzip": lambda b: zlib.decompress(b, 47),
        "deflate": lambda b: zlib.decompress(b, 47 if b[:1] == b"\x78" else -15),
        "zstd": lambda b: zstandard.ZstdDecompressor().decompressobj().decompress(b),
    }
    for code in codes:
        try:
            body = undo[code](body) if code in undo else body
        except (ValueError, zlib.error, zstandard.ZstdError):
            pass
    return body


def named_fields(fields: list[tuple[str, str | None]]) -> bytes:
    """Lines of names and values; a line end within either becomes a space, so no value can start a field of its own."""
    one = lambda x: _LINE_END.sub(" ", x)
    return "".join(f"{one(k).replace(':', ' ')}: {one(v)}\r\n" for k, v in fields if v).encode("utf-8", "surrogatepass")


def derive(record: tuple) -> list[tuple]:
    """The metadata and the conversion record of one response record."""
    page_id, _, source, _, url, date, _, block_digest, payload_digest, _, block = record
    headers, body = split_http(block or b"")
    page = read_page(payload(headers, body).decode(charset(headers), "replace"))
    fields = [("source-block-digest", block_digest), ("source-payload-digest", payload_digest)]
    fields += [(f"http-{k.lower()}", v) for k, v in headers]
    fields += [("title", page.title), ("languages-declared", page.language)]
    fields += [("outlink", x) for x in page.links]
    meta = named_fields(fields)
    text = page.text.encode("utf-8", "surrogatepass")
    out = []
    for kind, content, data in (("metadata", "application/warc-fields", meta), ("conversion", "text/plain; charset=utf-8", text)):
        out.append((page_id, kind, record_id(kind, source, digest(data)), source, url, date, content, digest(data), digest(data), len(data), data))
    return out


def serialize(record: tuple) -> bytes:
    """A record as archive bytes: named fields, an empty line, the block, two line ends."""
    _, kind, rid, refers, url, date, content, block_digest, payload_digest, length, block = record
    block = block or b""
    fields = [("WARC-Type", kind), ("WARC-Record-ID", rid), ("WARC-Date", date), ("WARC-Target-URI", url), ("WARC-Refers-To", refers)]
    if refers:
        fields += [("WARC-Refers-To-Target-URI", url), ("WARC-Refers-To-Date", date)]
    fields += [("WARC-Block-Digest", block_digest), ("WARC-Payload-Digest", payload_digest if kind == "response" else None), ("Content-Type", content), ("Content-Length", str(length))]
    return VERSION.encode() + b"\r\n" + named_fields(fields) + b"\r\n" + block + b"\r\n\r\n"


def members(data: bytes) -> Iterator[bytes]:
    """An archive's bytes, decompressed if it is compressed, in pieces."""
    if data[:2] != b"\x1f\x8b":
        yield data
        return
    at = memoryview(data)
    while len(at):
        one = zlib.decompressobj(31)
        while not one.eof and len(at):
            yield one.decompress(at[: 1 << 20])
            at = at[1 << 20 :] if not one.eof else memoryview(bytes(one.unused_data) + bytes(at[1 << 20 :]))


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """The records of an archive's bytes, as fields by lower-case name and block, one after the other."""
    held = bytearray()
    pieces = members(data)

    def more(test) -> bool:
        while not test():
            piece = next(pieces, None)
            if piece is None:
                return test()
            held.extend(piece)
        return True

    while True:
        while more(lambda: len(held) >= 2) and held[:2] == b"\r\n":
            del held[:2]
        if not held:
            return
        if not more(lambda: b"\r\n\r\n" in held):
            raise ValueError("a record's fields do not end")
        end = held.index(b"\r\n\r\n")
        lines = held[:end].decode("utf-8", "replace").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("no record starts here")
        fields: dict[str, str] = {}
        for x in lines[1:]:
            k, _, v = x.partition(":")
            fields.setdefault(k.strip().lower(), v.strip())
        size = int(fields.get("content-length", 0))
        if not more(lambda: len(held) >= end + 4 + size):
            raise ValueError("a block is cut off")
        yield fields, bytes(held[end + 4 : end + 4 + size])
        del held[: end + 4 + size]


def from_archive(fields: dict[str, str], block: bytes) -> tuple:
    """A record row of a parsed record; digests that the archive lacks are made."""
    kind, get = fields.get("warc-type", ""), fields.get
    body = split_http(block)[1] if kind == "response" else block
    return None, kind, get("warc-record-id"), get("warc-refers-to"), get("warc-target-uri", "").strip("<>"), get("warc-date"), get("content-type"), get("warc-block-digest") or digest(block), get("warc-payload-digest") or digest(body), len(block), block


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [[]] * len(_NAMES)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, _KINDS, strict=True)], _NAMES)


def responses(pages: DataFrame, date: str | Column = "2024-01-01T00:00:00Z") -> DataFrame:
    """Response records of stored pages (``page_id``, ``url``, ``html``), for inputs that are no archive yet.

    ``date`` is one for all or a column of ``pages``. A null page is an empty one, a
    null URL an empty one; repeated rows give repeated records; an empty table gives none.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                yield _rows([response(*(c.as_py() for c in row)) for row in zip(*b.slice(at, 256).columns, strict=True)])

    when = F.lit(date) if isinstance(date, str) else date.cast("string")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"), when.alias("date"))
    return rows.mapInArrow(run, SCHEMA)


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Records of all types of the archive files under ``path``, compressed or not, through Spark's own reader.

    A file is one task's work and held in memory as it is stored; its records are
    decompressed and given out one batch after the other. A damaged file fails its task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                held, size = [], 0
                for fields, block in parse(content.as_py()):
                    held.append(from_archive(fields, block))
                    size += len(block)
                    if size > 8 << 20:
                        yield _rows(held)
                        held, size = [], 0
                yield _rows(held)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, SCHEMA)


def derivatives(records: DataFrame) -> DataFrame:
    """Two rows for each response row: its metadata and its conversion record.

    Rows of other types are passed over. An empty page gives an empty conversion
    record. Repeated rows give repeated derivatives with the same ids; an empty table
    gives none.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                yield _rows([d for row in zip(*b.slice(at, 256).columns, strict=True) for d in derive(tuple(c.as_py() for c in row))])

    return records.where("record_type = 'response'").select(*_NAMES).mapInArrow(run, SCHEMA)


def archive_members(records: DataFrame) -> DataFrame:
    """``(record_id, member)``: each record as a gzip member of its own, ready to be joined to archive files.

    Rows keep their number; null fields are left out and a null block is an empty one.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [tuple(c.as_py() for c in row) for row in zip(*b.columns, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([r[2] for r in rows], pa.string()), pa.array([gzip.compress(serialize(r), mtime=0) for r in rows], pa.binary())], ["record_id", "member"])

    return records.select(*_NAMES).mapInArrow(run, "record_id string, member binary")


def digests(records: DataFrame) -> DataFrame:
    """Records with their block as a digest and, for text, its length in code points; one row for each row."""
    text = F.when(F.col("record_type") == "conversion", F.length(F.col("block").cast("string")).cast("long"))
    return records.select(*[c for c in _NAMES if c != "block"], F.sha2("block", 256).alias("block_sha256"), text.alias("n_chars"))
