"""WARC records, and a builder of derivatives: linked metadata and plain-text conversion records.

A response record goes in, two records come out. Both name the response in WARC-Refers-To, keep its target
URI and date, and carry digests of their own blocks; the metadata record also keeps the response's own headers, its
HTTP headers and digests, and what the page says of itself (title, language, links); the conversion record has the page's text.
Identifiers are name-based, so a repeated task writes the same bytes.

Defined cases: null html is an empty body and null url leaves the target URI out; a response that can't be read
(no HTTP head, no identifier) gives no derivative but a row of kind "broken" with its reason, identifier and bytes, and
the records after it go on; where the framing itself breaks, one such row with the whole input ends that input; rows
that repeat give equal records;
very long pages are scanned in linear time; an empty table gives an empty result; further columns of the input
are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html as entities
import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import quote, urljoin

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import table

NAMESPACE = uuid.uuid5(uuid.NAMESPACE_URL, "urn:corpus-derivatives")
DATE = "2024-01-01T00:00:00Z"
SOFTWARE = "warc-derivatives/1"

Headers = list[tuple[str, str]]


def digest(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def record_id(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(NAMESPACE, chr(31).join(parts))}>"


def clean_uri(uri: str) -> str:
    """A URI on one line, without blanks."""
    return re.sub(r"[\x00-\x20\x7f]+", lambda m: quote(m[0]), uri)


def one_line(value: str) -> str:
    return re.sub(r"[\x00-\x1f\x7f]+", " ", value).strip()


@dataclass
class Record:
    headers: Headers
    block: bytes

    def get(self, name: str, default: str | None = None) -> str | None:
        return next((v for k, v in self.headers if k.lower() == name.lower()), default)

    def to_bytes(self, compress: bool = False) -> bytes:
        """The record; compressed ones are gzip members of their own, with no time stamp."""
        head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in self.headers) + "\r\n"
        raw = head.encode() + self.block + b"\r\n\r\n"
        return gzip.compress(raw, mtime=0) if compress else raw


def make_record(kind: str, rid: str, block: bytes, content_type: str, extra: Headers = (), date: str = DATE) -> Record:
    named = [("WARC-Type", kind), ("WARC-Record-ID", rid), ("WARC-Date", date), *extra]
    return Record([*named, ("WARC-Block-Digest", digest(block)), ("Content-Type", content_type), ("Content-Length", str(len(block)))], block)


def parse_headers(raw: bytes) -> tuple[str, Headers]:
    """First line and the headers below it; folded lines belong to the one before."""
    lines = raw.decode("utf-8", "replace").split("\r\n" if b"\r\n" in raw else "\n")
    out: Headers = []
    for line in lines[1:]:
        if line[:1] in (" ", "\t") and out:
            out[-1] = (out[-1][0], f"{out[-1][1]} {line.strip()}")
        elif ":" in line:
            k, _, v = line.partition(":")
            out.append((k.strip(), v.strip()))
    return lines[0], out


def parse_records(data: bytes) -> Iterator[Record]:
    """All records of a file's bytes, plain or as gzip members."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    at = 0
    while at < len(data):
        if data[at : at + 2] == b"\r\n":
            at += 2
            continue
        end = data.find(b"\r\n\r\n", at)
        if end < 0 or data[at : at + 5] != b"WARC/":
            raise ValueError(f"no record at byte {at}")
        _, headers = parse_headers(data[at:end])
        size = next((v for k, v in headers if k.lower() == "content-length"), "")
        if not size.isdigit() or end + 4 + int(size) > len(data):
            raise ValueError(f"bad length at byte {at}")
        yield Record(headers, data[end + 4 : end + 4 + int(size)])
        at = end + 4 + int(size)


def response_record(page_id, url: str | None, body: str | None, date: str = DATE) -> Record:
    payload = (body or "").encode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode() + payload
    extra = [("WARC-Target-URI", clean_uri(url))] if url else []
    return make_record("response", record_id("response", str(page_id), url or "", digest(payload)), http, "application/http; msgtype=response", [*extra, ("WARC-Payload-Digest", digest(payload))], date)


_TAG = re.compile(r"</?([a-zA-Z][a-zA-Z0-9:-]*+)")
_TAG_END = re.compile(r"""(?:[^>"']++|"[^"]*+"|'[^']*+')*+>""")
_ATTRIBUTE = re.compile(r"""([a-zA-Z-]++)\s*+=\s*+("[^"]*+"|'[^']*+'|[^\s>"']++)""")
_BLANK = re.compile(r"[ \t\r\n\f\v ]+")
_RAW = {n: re.compile(rf"</{n}\b[^>]*>?", re.I) for n in ("script", "style", "noscript", "template", "iframe", "textarea")}
_BREAKS = set("address article aside blockquote body br dd div dl dt fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section table tr ul".split())


@dataclass
class Page:
    text: str
    title: str = ""
    language: str = ""
    links: list[str] = None


def read_page(source: str) -> Page:
    """Text, title, language and links of a page, in one pass from left to right."""
    out, title, language, links = [], [], "", []
    at, quotes, into = 0, True, out
    while at < len(source):
        lt = source.find("<", at)
        if lt < 0:
            into.append(source[at:])
            break
        into.append(source[at:lt])
        if source.startswith("<!--", lt):
            end = source.find("-->", lt + 4)
            at = end + 3 if end >= 0 else len(source)
            continue
        tag = _TAG.match(source, lt)
        if not tag:
            if source[lt + 1 : lt + 2] in ("!", "?"):
                end = source.find(">", lt)
                at = end + 1 if end >= 0 else len(source)
            else:
                into.append("<")
                at = lt + 1
            continue
        stop = _TAG_END.match(source, tag.end()) if quotes else None
        if stop:
            end = stop.end()
        else:  # a quote is never closed: from here on only the bracket counts
            quotes = False
            end = source.find(">", tag.end()) + 1 or len(source)
        name, opening = tag[1].lower(), source[lt + 1] != "/"
        if opening and name in ("a", "html"):
            given = {k.lower(): entities.unescape(v.strip("\"'")) for k, v in _ATTRIBUTE.findall(source, tag.end(), end)}
            if name == "a" and given.get("href"):
                links.append(given["href"])
            elif name == "html":
                language = given.get("lang", language)
        at = end
        if opening and name in _RAW and source[end - 2 : end - 1] != "/":
            close = _RAW[name].search(source, end)
            at = close.end() if close else len(source)
        elif name == "title":
            into = title if opening else out
        elif name == "head" and not opening or name == "body":
            into = out
        elif name in ("td", "th"):
            into.append(" ")
        if name in _BREAKS:
            into.append("\x00")
    text = _BLANK.sub(" ", entities.unescape("".join(out)))
    lines = (line.strip() for line in text.split("\x00"))
    return Page("\n".join(x for x in lines if x), one_line(entities.unescape("".join(title).replace("\x00", " "))), one_line(language), links)


def derive(response: Record) -> tuple[Record, Record]:
    """The metadata and the conversion record of a response."""
    rid = response.get("WARC-Record-ID")
    if response.get("WARC-Type") != "response" or not rid:
        raise ValueError("not a response")
    head, sep, payload = response.block.partition(b"\r\n\r\n")
    if not sep or not head.startswith(b"HTTP/"):
        raise ValueError("no HTTP head")
    status, http = parse_headers(head)
    kind = next((v for k, v in http if k.lower() == "content-type"), "")
    charset = re.search(r"charset=\"?([\w-]+)", kind)
    try:
        body = payload.decode(charset[1] if charset else "utf-8", "replace")
    except LookupError:
        body = payload.decode("utf-8", "replace")
    page = read_page(body)
    uri, date = response.get("WARC-Target-URI"), response.get("WARC-Date", DATE)
    linked = [("WARC-Refers-To", rid)] + ([("WARC-Refers-To-Target-URI", uri), ("WARC-Target-URI", uri)] if uri else []) + [("WARC-Refers-To-Date", date)]
    source = [("source-" + k, v) for k, v in response.headers if k.lower() not in ("warc-type", "content-length", "content-type")]
    fields = [*source, ("source-payload-digest-found", digest(payload)), ("http-status", status), *(("http-" + k, v) for k, v in http)]
    fields += [("title", page.title), ("language", page.language), ("text-characters", str(len(page.text)))]
    for link in page.links:
        try:
            fields.append(("outlink", clean_uri(urljoin(uri or "", link))))
        except ValueError:
            fields.append(("outlink", clean_uri(link)))
    meta = "".join(f"{k}: {one_line(v)}\r\n" for k, v in fields).encode()
    text = page.text.encode()
    kept = [("WARC-Source-Payload-Digest", response.get("WARC-Payload-Digest") or digest(payload))]
    conversion = make_record("conversion", record_id("conversion", rid), text, "text/plain; charset=utf-8", [*linked, *kept, ("WARC-Payload-Digest", digest(text))], date)
    metadata = make_record("metadata", record_id("metadata", rid), meta, "application/warc-fields", [*linked, ("WARC-Concurrent-To", conversion.get("WARC-Record-ID")), *kept], date)
    return metadata, conversion


RESPONSES = "page_id long, record binary"
DERIVED = "page_id long, kind string, record_id string, refers_to string, target_uri string, content_type string, content_length long, block_digest string, source_payload_digest string, reason string, record binary"


def response_records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: str = DATE) -> DataFrame:
    """One response record per page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [response_record(*row, date).to_bytes() for row in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(made, pa.binary())], ["page_id", "record"])

    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html")).mapInArrow(run, RESPONSES)


def derivatives(records: DataFrame, compress: bool = False) -> DataFrame:
    """Metadata and conversion records of every response in (page_id, record); a record holds one response or a file of them."""

    def rows_of(page, raw) -> Iterator[tuple]:
        try:
            for response in parse_records(raw or b""):
                if response.get("WARC-Type") != "response":
                    continue
                try:
                    made = derive(response)
                except ValueError as e:  # this response only: the next record starts where its length says
                    yield (page, "broken", None, response.get("WARC-Record-ID"), response.get("WARC-Target-URI"), None, None, None, None, str(e), response.to_bytes(compress))
                    continue
                for r in made:
                    yield (page, r.get("WARC-Type"), r.get("WARC-Record-ID"), r.get("WARC-Refers-To"), r.get("WARC-Target-URI"), r.get("Content-Type"), len(r.block), r.get("WARC-Block-Digest"), r.get("WARC-Source-Payload-Digest"), None, r.to_bytes(compress))
        except (ValueError, OSError, EOFError) as e:  # framing: where the next record starts is not known
            yield (page, "broken", None, None, None, None, None, None, None, str(e), raw)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), *[pa.string()] * 5, pa.int64(), *[pa.string()] * 3, pa.binary()]
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                rows = [r for page, raw in zip(*(c.to_pylist() for c in part.columns), strict=True) for r in rows_of(page, raw)]
                cols = list(zip(*rows, strict=True)) or [()] * len(kinds)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [x.split()[0] for x in DERIVED.split(", ")])

    return records.select("page_id", "record").mapInArrow(run, DERIVED)


def read_warc_files(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, record) with a file's bytes in each row, for `derivatives`; page_id is null."""
    return spark.read.format("binaryFile").load(path).select(F.lit(None).cast("long").alias("page_id"), F.col("content").alias("record"))


SEPARATOR = b"\r\n\r\nWARC/1."


def read_warc_records(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, record) with one record in each row, streamed, for files of any size; page_id is null.

    Lines end where the next record's version line begins. A block that holds such a line itself is put together again by its
    Content-Length, from the pieces that follow in the same task: a compressed file is one task. (Where an uncompressed file is cut
    between two tasks inside such a block, its halves come out as broken records.)
    """
    lines = spark.read.text(path, lineSep=SEPARATOR.decode()).select(F.col("value").cast("binary").alias("piece"))

    def missing(raw: bytes) -> bool:
        head, _, block = raw.partition(b"\r\n\r\n")
        length = next((x.split(b":", 1)[1] for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:")), b"")
        return length.strip().isdigit() and len(block) < int(length)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = b""
        for batch in batches:
            whole = []
            for piece in batch.column(0).to_pylist():
                starts = piece.startswith(b"WARC/1.")
                raw = piece if starts else SEPARATOR[4:] + piece
                if held and missing(held) and not starts:
                    held += SEPARATOR + piece
                    continue
                if held:
                    whole.append(held + b"\r\n\r\n")
                held = raw
            yield pa.RecordBatch.from_arrays([pa.nulls(len(whole), pa.int64()), pa.array(whole, pa.binary())], ["page_id", "record"])
        if held.strip():
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.array([held.rstrip(b"\r\n") + b"\r\n\r\n" if not missing(held) else held], pa.binary())], ["page_id", "record"])

    return lines.mapInArrow(run, RESPONSES)


def op6_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derivatives(response_records(table(spark, sf_dir, "pages")))
