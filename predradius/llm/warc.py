"""Derivatives of web archives: plain-text conversion records and linked metadata records from responses.

Every response yields a conversion record (the page's text) and a metadata record (JSON: HTTP headers, title, links,
payload digest). Both name the response in WARC-Refers-To, repeat its target URI and date, and carry digests of their own blocks;
record identifiers derive from the response's, so a task that runs again makes the same records.

Edge cases: null or empty HTML gives an empty text and no links; a null URL is left out of the headers and the payload; a
payload that is not HTML is passed on as it is; line breaks in a URL are percent-encoded in the headers; an empty table gives no
records; rows that repeat give records that repeat; very long pages are scanned once, also if tags or comments are left open;
extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
import html
import json
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RECORD = "page_id long, kind string, record_id string, refers_to string, headers string, block string"
OPENER = re.compile(r"<!--|<(script|style|noscript|template|head)\b", re.I)
CLOSERS = {name: re.compile(rf"</{name}\s*>", re.I) for name in ("script", "style", "noscript", "template", "head", "title")}
BREAKS = re.compile(r"</?(?:p|div|br|li|ul|ol|h[1-6]|tr|table|section|article|header|footer|nav|aside|main|pre|blockquote|form|dl|dt|dd)\b[^>]*>", re.I)
TAG = re.compile(r"<[^>]*>")
BLANKS = re.compile(r"[ \t\f\v ]+")
TITLE = re.compile(r"<title\b", re.I)
ANCHOR = re.compile(r"<a\b", re.I)
HREF = re.compile(r"""\bhref\s*=\s*(?:"|'|(?=[^\s>]))""", re.I)
BARE = re.compile(r"[^\s>]+")


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def derived_id(*parts) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(31).join(map(str, parts)))}>"


def header_text(fields: list[tuple[str, object]]) -> str:
    """Line breaks inside a value are percent-encoded, so no value can add a field."""
    line = lambda v: str(v).replace("\r", "%0D").replace("\n", "%0A")
    return "WARC/1.1\r\n" + "".join(f"{k}: {line(v)}\r\n" for k, v in fields if v is not None) + "\r\n"


def header_fields(headers: str) -> dict[str, str]:
    return dict(line.split(": ", 1) for line in headers.split("\r\n")[1:] if ": " in line)


def visible(markup: str) -> str:
    """Markup without comments, scripts, styles, templates and the head; an unclosed one stays. One pass, whatever the markup."""
    out, at, unclosed = [], 0, set()
    for m in OPENER.finditer(markup):
        kind = (m[1] or "").lower()
        if m.start() < at or kind in unclosed:
            continue
        if kind:
            end = CLOSERS[kind].search(markup, m.end())
            stop = end.end() if end else -1
        else:
            stop = markup.find("-->", m.end()) + 3 if markup.find("-->", m.end()) >= 0 else -1
        if stop < 0:
            unclosed.add(kind)
        else:
            out += [markup[at : m.start()], " "]
            at = stop
    return "".join([*out, markup[at:]])


def page_text(markup: str) -> str:
    shown = visible(markup)
    last = shown.rfind(">") + 1  # what follows holds no whole tag
    text = TAG.sub("", BREAKS.sub("\n", shown[:last])) + shown[last:]
    lines = (line.strip() for line in BLANKS.sub(" ", html.unescape(text)).split("\n"))
    return "\n".join(line for line in lines if line)


def page_title(markup: str) -> str | None:
    m = TITLE.search(markup)
    start = markup.find(">", m.end()) + 1 if m else 0
    end = CLOSERS["title"].search(markup, start) if start else None
    return html.unescape(markup[start : end.start()]).strip() if end else None


def page_links(markup: str) -> list[str]:
    """The targets of the anchors, in order; a quoted target may hold '>'."""
    found, at = [], 0
    while m := ANCHOR.search(markup, at):
        close = markup.find(">", m.end())
        if close < 0:
            close = len(markup)
        at = close
        if not (h := HREF.search(markup, m.end(), close)):
            continue
        quote = markup[h.end() - 1]
        if quote in "\"'":
            end = markup.find(quote, h.end())
            if end >= 0:
                found.append(html.unescape(markup[h.end() : end]))
                at = max(close, end)
        elif bare := BARE.match(markup, h.end()):
            found.append(html.unescape(bare[0]))
    return found


def response(page_id, url: str | None, markup: str | None, date: str) -> tuple:
    """A response record around a page, as a crawler would have stored it."""
    payload = (markup or "").encode("utf-8", "replace")
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n{payload.decode()}"
    record_id = derived_id("response", page_id, url)
    fields = [("WARC-Type", "response"), ("WARC-Record-ID", record_id), ("WARC-Date", date), ("WARC-Target-URI", url), ("Content-Type", "application/http; msgtype=response"),
              ("WARC-Payload-Digest", digest(payload)), ("WARC-Block-Digest", digest(block.encode())), ("Content-Length", len(block.encode()))]
    return (page_id, "response", record_id, None, header_text(fields), block)


def derivatives(record: tuple) -> list[tuple]:
    """The conversion and the metadata record of a response record."""
    page_id, _, source_id, _, headers, block = record
    source = header_fields(headers)
    http, _, payload = block.partition("\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in http.split("\r\n")[1:] if ": " in line)
    is_html = "html" in fields.get("Content-Type", "html").lower()
    text = page_text(payload) if is_html else payload
    links = page_links(payload) if is_html else []
    title = page_title(payload) if is_html else None
    envelope = {"refers-to": source_id, "source": {k: source[k] for k in sorted(source)}, "http": {"status": http.split("\r\n")[0], "headers": fields},
                "html": {"title": title, "links": links}}
    made = []
    for kind, content, media in (("conversion", text, "text/plain; charset=utf-8"), ("metadata", json.dumps(envelope, ensure_ascii=False, sort_keys=True), "application/json")):
        data = content.encode("utf-8", "replace")
        record_id = derived_id(kind, source_id)
        own = [("WARC-Type", kind), ("WARC-Record-ID", record_id), ("WARC-Date", source.get("WARC-Date")), ("WARC-Target-URI", source.get("WARC-Target-URI")), ("WARC-Refers-To", source_id),
               ("Content-Type", media), ("WARC-Block-Digest", digest(data)), ("WARC-Source-Payload-Digest", source.get("WARC-Payload-Digest")), ("Content-Length", len(data))]
        made.append((page_id, kind, record_id, source_id, header_text(own), data.decode()))
    return made


def record_batch(rows: list[tuple]) -> pa.RecordBatch:
    names = [x.split()[0] for x in RECORD.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], pa.int64() if j == 0 else pa.string()) for j in range(len(names))], names)


def responses(pages: DataFrame, date: str = "2020-01-01T00:00:00Z") -> DataFrame:
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield record_batch([response(*row, date) for row in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True)])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(make, RECORD)


def build_derivatives(records: DataFrame) -> DataFrame:
    """Conversion and metadata records for every response record; other records are passed by."""
    names = [x.split()[0] for x in RECORD.split(", ")]

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True)
            yield record_batch([made for row in rows for made in derivatives(row)])

    return records.filter("kind = 'response'").select(*names).mapInArrow(make, RECORD)


def page_derivatives(pages: DataFrame, date: str = "2020-01-01T00:00:00Z") -> DataFrame:
    """build_derivatives(responses(pages)) in one pass, without the responses leaving the worker."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True)
            yield record_batch([made for row in rows for made in derivatives(response(*row, date))])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(make, RECORD)


def write_records(records: DataFrame, path: str) -> None:
    """Records as WARC text files, one for each partition."""
    records.select(F.concat("headers", "block", F.lit("\r\n\r\n")).alias("value")).write.option("lineSep", "").text(path)
