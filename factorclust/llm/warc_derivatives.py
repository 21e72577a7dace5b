"""Derivatives of web archives: a metadata record and a plain-text conversion record for each response.

Each derived record has an id of its own, refers to the response it comes from (WARC-Refers-To), keeps its
target URI, date and payload digest, and carries the digest of its own block. The metadata block is JSON
with the source's record and HTTP headers, title and links; the conversion block is the visible text.
Responses and derived records are written to gzip members in two files a partition in the shared folder, so
every reference resolves; the derived ones are read again and returned.

Pages are read in one pass, whatever is wrong with them: a ``<`` that no letter, ``/``, ``!`` or ``?`` follows is
text; an unfinished tag or comment takes the rest of the page, and so does an open script, style or title;
other hidden elements without an end only lose their tag.

A page without a URL gets urn:page:<page_id> as its target; null html is an empty payload. An id is made of the
page and the place of its response in the archive, so repeated rows, and pages that share id and URL, have
records of their own. An empty table gives no records; extra columns aren't read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import json
import re
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.llm.shared import cut, fresh_path

#: The tables have no date of capture.
CAPTURED = "2024-01-01T00:00:00Z"
_SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")  # fixed value: the name space of URLs

#: Elements whose content isn't shown, those of them that hold no tags, and those that begin a line.
HIDDEN = frozenset("script style noscript template head".split())
RAW = frozenset("script style title textarea".split())
BLOCKS = frozenset("p div br li ul ol h1 h2 h3 h4 h5 h6 tr table section article nav header footer blockquote pre title".split())

TOLD = HIDDEN | RAW | {"a"}
# the last group of a tag is empty where the page ends before the tag does
_OPEN = re.compile(r"""<(?:(/?)([A-Za-z][^\s/>]*)([^>"']*(?:"[^"]*"[^>"']*|'[^']*'[^>"']*)*)(>?)|(!--)|[!?/])""")
_HREF = re.compile(r"""(?:^|[\s"'/])href\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
# single spaces stay as they are, so they needn't be found; lines are joined after runs of spaces are
_SPACES = re.compile(r"[^\S\n]{2,}|[^\S\n ]")
_LINES = re.compile(r" ?\n\s*")


@dataclass
class Record:
    kind: str
    block: bytes
    headers: dict[str, str] = field(default_factory=dict)


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(kind: str, page: object, uri: str, place: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(_SPACE, f'{kind} {page} {uri} {place}')}>"


def response(page: int | None, url: str | None, body: str | None, place: str = "0") -> Record:
    """The response record of a page, with an HTTP head in its block; ``place`` tells it from others of the same page."""
    payload = (body or "").encode("utf-8", "surrogatepass")
    uri = (url or f"urn:page:{page}").replace("\r", "%0D").replace("\n", "%0A")
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    return Record("response", head + payload, {
        "WARC-Record-ID": record_id("response", page, uri, place), "WARC-Date": CAPTURED, "WARC-Target-URI": uri, "Content-Type": "application/http; msgtype=response",
        "WARC-Payload-Digest": digest(payload), "WARC-Block-Digest": digest(head + payload),
    })


@dataclass
class Page:
    text: str
    title: str | None
    links: list[str]


def read_page(page: str) -> Page:
    """Visible text, title and links of a page, from left to right."""
    out: list[str] = []
    links: list[str] = []
    title: str | None = None
    at, end = 0, len(page)
    none_left: set[str] = set()  # elements that aren't closed any more

    def closing(name: str, start: int) -> tuple[int, int] | None:
        if name in none_left:
            return None
        m = _closers(name).search(page, start)
        if not m:
            none_left.add(name)
        return m and m.span()

    while at < end:
        m = _OPEN.search(page, at)
        if not m:
            out.append(page[at:])
            break
        out.append(page[at : m.start()])
        slash, name, rest, done, comment = m.groups()
        if comment:
            at = page.find("-->", m.end()) + 3
            if at == 2:
                break
            out.append(" ")
            continue
        if name is None:
            at = page.find(">", m.end()) + 1
            if not at:
                break
            continue
        if not done:
            break
        at = m.end()
        name = name.lower()
        if name in BLOCKS:
            out.append("\n")
        if slash or name not in TOLD:
            continue
        if name == "a" and (href := _HREF.search(rest)):
            links.append(html.unescape(next(filter(None, href.groups()), "")))
        if name == "title" and title is None:
            title = page[at : (closing(name, at) or (end, end))[0]]
        if name in HIDDEN or name in RAW:
            span = closing(name, at)
            if span is None and name in RAW:
                break
            if span is not None:
                if name == "head" and title is None and (inside := _TITLE.search(page, at, span[0])):
                    title = inside[1]
                out.append(" " if name in HIDDEN else page[at : span[0]] + "\n")
                at = span[1]
    text = html.unescape("".join(out))
    return Page(_LINES.sub("\n", _SPACES.sub(" ", text)).strip(), " ".join(html.unescape(title).split()) if title is not None else None, links)


_TITLE = re.compile(r"<title(?=[\s/>])[^>]*>(.*?)</title\s*>", re.S | re.I)
_closer: dict[str, re.Pattern] = {}


def _closers(name: str) -> re.Pattern:
    """The end tag of an element; only names of RAW and HIDDEN are asked for."""
    if name not in _closer:
        _closer[name] = re.compile(rf"</{name}\s*>", re.I)
    return _closer[name]


def derive(source: Record, page: object) -> tuple[Record, Record]:
    """(metadata, conversion) of a response record."""
    head, _, payload = source.block.partition(b"\r\n\r\n")
    status, *lines = head.decode("latin-1").split("\r\n")
    found = read_page(payload.decode("utf-8", "replace"))
    http = dict(x.split(": ", 1) for x in lines if ": " in x)
    uri, of = source.headers["WARC-Target-URI"], source.headers["WARC-Record-ID"]
    linked = {"WARC-Date": source.headers["WARC-Date"], "WARC-Target-URI": uri, "WARC-Refers-To": of, "WARC-Source-Payload-Digest": source.headers["WARC-Payload-Digest"]}
    envelope = {"warc": source.headers, "http": {"status": status, "headers": http}, "html": {"title": found.title, "links": found.links}}
    out = []
    for kind, mime, block in (("metadata", "application/json", json.dumps(envelope, ensure_ascii=False, sort_keys=True).encode("utf-8", "surrogatepass")), ("conversion", "text/plain", found.text.encode("utf-8", "surrogatepass"))):
        out.append(Record(kind, block, {"WARC-Record-ID": record_id(kind, page, uri, of), **linked, "Content-Type": mime, "WARC-Block-Digest": digest(block)}))
    return out[0], out[1]


def dump(record: Record, level: int = 1) -> bytes:
    """One gzip member: version line, headers, block."""
    lines = ["WARC/1.1", f"WARC-Type: {record.kind}", *(f"{k}: {v}" for k, v in record.headers.items()), f"Content-Length: {len(record.block)}", "", ""]
    return gzip.compress("\r\n".join(lines).encode("utf-8", "surrogatepass") + record.block + b"\r\n\r\n", level, mtime=0)


def load(stream) -> Iterator[Record]:
    """Records of a file of gzip members; raises where one is cut short."""
    with gzip.open(stream) as f:
        while line := f.readline():
            if line != b"WARC/1.1\r\n":
                raise ValueError(f"not a record: {line[:40]!r}")
            headers: dict[str, str] = {}
            while (line := f.readline()) not in (b"\r\n", b""):
                name, _, value = line.decode("utf-8", "surrogatepass").rstrip("\r\n").partition(": ")
                headers[name] = value
            n = int(headers.pop("Content-Length"))
            block = f.read(n)
            if len(block) != n or f.read(4) != b"\r\n\r\n":
                raise ValueError("a record is cut short")
            yield Record(headers.pop("WARC-Type"), block, headers)


def write(pages: DataFrame, to: str) -> DataFrame:
    """Writes each partition's responses and derived records to two files below ``to``; returns their uris and the records derived."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, top = pafs.FileSystem.from_uri(to)
        system.create_dir(top, recursive=True)
        name, n = uuid.uuid4().hex, 0
        stem = f"{top}/{name}"
        with system.open_output_stream(f"{stem}.responses.tmp") as archive, system.open_output_stream(f"{stem}.tmp") as out:
            for b in batches:
                for page, url, body in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                    source = response(page, url, body, f"{name}/{n}")
                    archive.write(dump(source))
                    for r in derive(source, page):
                        r.headers["Page-ID"] = "" if page is None else str(page)
                        out.write(dump(r))
                        n += 1
        system.move(f"{stem}.responses.tmp", f"{stem}.responses.warc.gz")
        system.move(f"{stem}.tmp", f"{stem}.warc.gz")
        if n:
            root = f"{to[: len(to) - len(top)]}{stem}"
            yield pa.RecordBatch.from_pydict({"uri": [f"{root}.warc.gz"], "responses": [f"{root}.responses.warc.gz"], "records": [n]})

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return cut(rows.mapInArrow(run, "uri string, responses string, records long"), "warcs")


_FIELDS = (("page_id", pa.int64()), ("record_type", pa.string()), ("record_id", pa.string()), ("refers_to", pa.string()), ("target_uri", pa.string()), ("warc_date", pa.string()), ("source_digest", pa.string()), ("block_digest", pa.string()), ("content_type", pa.string()), ("content_length", pa.int64()), ("digest_ok", pa.bool_()), ("block", pa.string()))
SCHEMA = "page_id long, record_type string, record_id string, refers_to string, target_uri string, warc_date string, source_digest string, block_digest string, content_type string, content_length long, digest_ok boolean, block string"


def row(r: Record) -> tuple:
    h = r.headers
    page = h.get("Page-ID", "")
    return (int(page) if page else None, r.kind, h["WARC-Record-ID"], h.get("WARC-Refers-To"), h["WARC-Target-URI"], h["WARC-Date"], h.get("WARC-Source-Payload-Digest"), h["WARC-Block-Digest"], h["Content-Type"], len(r.block), digest(r.block) == h["WARC-Block-Digest"], r.block.decode("utf-8", "replace"))


def _batches(rows: Iterable[tuple], n: int = 256) -> Iterator[pa.RecordBatch]:
    held: list[tuple] = []
    for r in rows:
        held.append(r)
        if len(held) == n:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*held, strict=True), _FIELDS, strict=True)], names=[k for k, _ in _FIELDS])
            held = []
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*held, strict=True), _FIELDS, strict=True)], names=[k for k, _ in _FIELDS])


def read(files: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for uri in b.column(0).to_pylist():
                system, path = pafs.FileSystem.from_uri(uri)
                with system.open_input_stream(path, compression=None) as source:
                    yield from _batches(map(row, load(source)))

    n = max(int(files.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    return files.select("uri").repartition(n).mapInArrow(run, SCHEMA)


def build(pages: DataFrame) -> DataFrame:
    return read(write(pages, fresh_path(pages.sparkSession, "warc")))
