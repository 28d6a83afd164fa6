"""WARC derivatives: metadata and plain-text conversion records for each response record.

Records refer to the response by its record id, and carry its target, date, headers and digests on.
"""

from __future__ import annotations

import base64
import hashlib
import html
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import lean, small_batches

#: Fixed names of the record format.
VERSION = b"WARC/1.1"
CRLF = b"\r\n"

_OPEN = re.compile(r"<!--|<!|<(script|style|noscript|template|head)\b", re.I)
_CLOSE = {x: re.compile(rf"</{x}\s*>", re.I) for x in ("script", "style", "noscript", "template", "head", "title")}
_CLOSE["--"] = re.compile("-->")
_END = re.compile(">")
_BREAK = re.compile(r"<\s*(?:/\s*)?(?:p|div|br|li|ul|ol|tr|table|h[1-6]|article|section|nav|footer|header|aside|main|blockquote|pre|td|th|dd|dt|dl|form|hr)\b[^>]*>", re.I)
_TAG = re.compile(r"</?[a-zA-Z][^>]*>")
_TITLE = re.compile(r"<title\b[^>]*>", re.I)
_HTML = re.compile(r"<html\b", re.I)
_LANG = re.compile(r"\blang\s*=\s*[\"']?([\w-]+)", re.I)
_ANCHOR = re.compile(r"<a\b", re.I)
_HREF = re.compile(r"\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_BLANKS = re.compile(r"[ \t\r\f\v]+")


def record_id(*parts: str) -> str:
    """A stable id: the same parts always give the same one, so reruns and retries write the same records."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join(parts))}>"


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = CRLF.join([VERSION, *(f"{k}: {v}".encode() for k, v in headers), f"Content-Length: {len(block)}".encode()])
    return head + CRLF * 2 + block + CRLF * 2


def read_records(data: bytes) -> list[tuple[dict[str, str], bytes]]:
    """Headers and blocks of a run of uncompressed records."""
    out, at = [], 0
    while at < len(data):
        stop = data.index(CRLF * 2, at)
        lines = data[at:stop].split(CRLF)
        if lines[0] != VERSION:
            raise ValueError(f"no record at {at}")
        headers = dict(x.decode().split(": ", 1) for x in lines[1:])
        a = stop + 4
        b = a + int(headers["Content-Length"])
        if data[b : b + 4] != CRLF * 2:
            raise ValueError(f"bad length at {at}")
        out.append((headers, data[a:b]))
        at = b + 4
    return out


class _Next:
    """First match at or after a place that only grows. A match found once is kept until it is passed, so all calls together read the page once."""

    def __init__(self, pattern: re.Pattern, page: str):
        self.pattern, self.page = pattern, page
        self.at: re.Match | None = None
        self.asked = self.over = False

    def after(self, place: int) -> re.Match | None:
        if not self.over and (not self.asked or self.at.start() < place):
            self.at = self.pattern.search(self.page, place)
            self.asked, self.over = True, self.at is None
        return self.at


def _without_hidden(page: str) -> str:
    """The page without comments, declarations, and elements that show no text. An element that is not closed stays, in time linear in the page."""
    end = _Next(_END, page)
    close = {k: _Next(p, page) for k, p in _CLOSE.items()}
    kept, at = [], 0
    for m in _OPEN.finditer(page):
        if m.start() < at:
            continue
        if m[1]:
            tag = end.after(m.end())
            stop = close[m[1].lower()].after(tag.end()) if tag else None
        else:
            stop = (close["--"].after(m.end()) if m[0] == "<!--" else None) or end.after(m.start() + 2)
        if stop:
            kept.append(page[at : m.start()])
            at = stop.end()
    return "".join(kept) + page[at:]


def _replaced(pattern: re.Pattern, by: str, page: str) -> str:
    """``pattern.sub`` for a pattern that ends in >: the rest after the last > is not tried."""
    k = page.rfind(">") + 1
    return pattern.sub(by, page[:k]) + page[k:]


def plain_text(page: str) -> str:
    """Text of a page: no scripts, styles, comments or head; block elements end lines; entities resolved; blank lines dropped."""
    text = html.unescape(_replaced(_TAG, "", _replaced(_BREAK, "\n", _without_hidden(page))))
    lines = (_BLANKS.sub(" ", x).strip() for x in text.split("\n"))
    return "\n".join(x for x in lines if x)


def _title(page: str) -> str | None:
    start = _TITLE.search(page, 0, page.rfind(">") + 1)
    stop = _CLOSE["title"].search(page, start.end()) if start else None
    return page[start.end() : stop.start()] if stop else None


def _language(page: str) -> str | None:
    end, at = _Next(_END, page), 0
    for m in _HTML.finditer(page):
        if m.start() >= at:
            tag = end.after(m.end())
            at = tag.start() if tag else len(page)
            found = _LANG.search(page, m.end(), at)
            if found:
                return found[1]
    return None


def _links(page: str) -> list[str]:
    end, href, out, at = _Next(_END, page), _Next(_HREF, page), [], 0
    for m in _ANCHOR.finditer(page):
        if m.start() < at:
            continue
        tag, found = end.after(m.end()), href.after(m.end())
        if found is None:
            break
        stop = tag.start() if tag else len(page)
        if found.start() < stop:
            out.append(html.unescape(found[1] or found[2] or found[3] or ""))
            at = found.end()
        else:
            at = stop
    return out


def page_metadata(page: str) -> list[tuple[str, str]]:
    """Fields of the metadata record: title, language, number of links, then the links in order."""
    title, lang, links = _title(page), _language(page), _links(page)
    out = [("title", _BLANKS.sub(" ", html.unescape(title).replace("\n", " ")).strip())] if title is not None else []
    out += [("languages-html", lang)] if lang else []
    return [*out, ("outlink-count", str(len(links))), *(("outlink", " ".join(x.split())) for x in links)]


def _clean(x: str) -> str:
    return " ".join(x.split())


def derive(page_id: object, url: str, page: str, date: str) -> list[tuple[str, str, str, dict, bytes]]:
    """(type, id, refers to, headers, record) of a response and what is made of it."""
    payload = page.encode()
    http = b"HTTP/1.1 200 OK" + CRLF + b"Content-Type: text/html; charset=utf-8" + CRLF + f"Content-Length: {len(payload)}".encode() + CRLF * 2
    target = _clean(url)
    response = record_id("response", str(page_id), url, digest(payload))
    made = []

    def add(kind: str, own: str, refers: str, content: str, block: bytes, more: list[tuple[str, str]]) -> None:
        headers = [("WARC-Type", kind), ("WARC-Record-ID", own), ("WARC-Date", date), ("WARC-Target-URI", target), *more, ("WARC-Block-Digest", digest(block)), ("Content-Type", content)]
        if refers:
            headers.insert(2, ("WARC-Refers-To", refers))
        made.append((kind, own, refers, dict(headers), record(headers, block)))

    source = [("WARC-Payload-Digest", digest(payload))]
    add("response", response, "", "application/http; msgtype=response", http + payload, source)
    carried = [("WARC-Refers-To-Target-URI", target), ("WARC-Refers-To-Date", date), ("WARC-Source-Payload-Digest", digest(payload)), ("WARC-Source-Content-Type", "text/html; charset=utf-8")]
    fields = "".join(f"{k}: {v}\r\n" for k, v in page_metadata(page)).encode()
    add("metadata", record_id("metadata", response), response, "application/warc-fields", fields, carried)
    text = plain_text(page).encode()
    add("conversion", record_id("conversion", response), response, "text/plain; charset=utf-8", text, carried)
    return made


SCHEMA = "page_id long, warc_type string, record_id string, refers_to string, target_uri string, block_digest string, source_payload_digest string, content_length long, record binary"


def derivatives(pages: DataFrame, date: str = "2024-01-01T00:00:00Z", kinds: tuple[str, ...] = ("response", "metadata", "conversion")) -> DataFrame:
    """Records of every page: one row per page and kind, ``record`` being the bytes as they stand in a file.

    A null url or html counts as empty. Rows that repeat get the same ids and the same bytes. The response record is
    rebuilt from the stored html; its id depends on page id, url and payload. Further columns are ignored.
    """
    small_batches(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in SCHEMA.split(", ")]
        types = [pa.int64(), *[pa.string()] * 6, pa.int64(), pa.binary()]

        def batch_of(out: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names=names)

        for batch in batches:
            out, size = [], 0
            for page_id, url, page in zip(batch["page_id"].to_pylist(), batch["url"].to_pylist(), batch["html"].to_pylist()):
                for kind, own, refers, headers, data in derive(page_id, url, page, date):
                    if kind in kinds:
                        length = len(data) - data.index(CRLF * 2) - 8
                        out.append((page_id, kind, own, refers or None, headers["WARC-Target-URI"], headers["WARC-Block-Digest"], headers.get("WARC-Source-Payload-Digest") or headers.get("WARC-Payload-Digest"), length, data))
                        size += len(data)
                if size > 1 << 23:
                    yield batch_of(out)
                    out, size = [], 0
            if out:
                yield batch_of(out)

    return rows.mapInArrow(lean(work), SCHEMA)


def write_files(records: DataFrame, path: str, compression: str = "gzip") -> None:
    """Records as files under ``path`` that hold nothing else: each part file is a run of whole records, by default one gzip stream.

    Written by Spark's own writer and its committer, so that a task that is lost or run twice leaves no half file and no record twice. The writer ends each row
    by the two line breaks that end a record. It names files ``part-*.txt.gz``; readers of the format look at the content alone.
    A record with bytes that are no UTF-8 is written as it is. An empty table gives files without records.
    """
    body = F.expr("substring(record, 1, octet_length(record) - 4)").cast("string")
    records.select(body.alias("value")).write.mode("overwrite").option("lineSep", (CRLF * 2).decode()).option("compression", compression).text(path)


def digest_rows(records: DataFrame) -> DataFrame:
    """Records by their headers and digests, without the bytes, which are checked by a hash of the whole record."""
    return records.select("page_id", "warc_type", "record_id", "refers_to", "target_uri", "block_digest", "source_payload_digest", "content_length", F.sha2("record", 256).alias("record_sha256"))
