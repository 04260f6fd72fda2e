"""WARC derivatives: linked metadata and plain-text conversion records from responses.

Each response gives a ``metadata`` record (outlinks, title, content type, as
JSON) and a ``conversion`` record (plain text).  Both name the response in
WARC-Refers-To and keep its target URI and date, the headers of the source and
its digests.  What the table knows of a response (record id, date, HTTP header,
digests) is carried through; where it holds no such column or a null, the id is
derived from the content, the date is ``DATE``, and no header is made up.
Record ids of derivatives come from the content, so a rerun gives the same
records.
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

from .frames import batches

DATE = "1970-01-01T00:00:00Z"  # where the table has no capture date
_NAMESPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")  # fixed value: the URL namespace of RFC 4122

# where each construct begins; its end is looked for from there, and after a failure not again, so every scan is linear
_SKIPPED = re.compile(r"<!--|<(script|style|noscript|template)\b", re.I)
_ENDS = {n: re.compile(rf"</{n}\s*>", re.I) for n in ("script", "style", "noscript", "template", "title", "head")}
_TITLE, _HEAD = re.compile(r"<title\b", re.I), re.compile(r"<head\b", re.I)
_BREAK = re.compile(r"</?(?:address|article|aside|blockquote|br|dd|div|dl|dt|figure|footer|form|h[1-6]|header|hr|li|main|nav|ol|p|pre|section|table|td|th|tr|ul)\b", re.I)
_TAG = re.compile(r"<[/!?a-zA-Z]")
_LINK = re.compile(r"<(a|area|link|img|iframe|script)\b", re.I)
_NAME = re.compile(r"\b(href|src)\s*=\s*", re.I)
_BARE = re.compile(r"[^\s>]+")
_BLANKS = re.compile(r"[^\S\n]+")
_NUMBER = re.compile(r"&#(?:0*([1-9][0-9]{7,})|[xX]0*([1-9a-fA-F][0-9a-fA-F]{6,}));?")


def unescaped(text: str) -> str:
    """Character references resolved; numbers beyond all code points, of any length, become the replacement character."""
    return html.unescape(_NUMBER.sub("\ufffd", text))


def _replaced(page: str, opening: re.Pattern, end_of, put: str) -> str:
    """``page`` with what begins at ``opening`` and ends at ``end_of(page, match)`` replaced; an end of -1 stops the scan."""
    out, at = [], 0
    while m := opening.search(page, at):
        end = end_of(page, m)
        if end < 0:
            break
        out += (page[at : m.start()], put)
        at = end
    return "".join([*out, page[at:]])


def _tag_end(page: str, m: re.Match) -> int:
    return page.find(">", m.end()) + 1 or -1


def _head_end(page: str, m: re.Match) -> int:
    body = _tag_end(page, m)
    close = _ENDS["head"].search(page, body) if body > 0 else None
    return close.end() if close else -1


def without_skipped(page: str) -> str:
    """``page`` without comments and without scripts, styles and the like; what isn't closed goes on to the end."""
    out, at, look, tags = [], 0, 0, True
    while m := _SKIPPED.search(page, look):
        if m[1] is None:
            end = page.find("-->", m.end()) + 3
            end = len(page) if end < 3 else end
        else:
            body = _tag_end(page, m) if tags else -1
            if body < 0:  # no tag ends after here
                tags, look = False, m.end()
                continue
            close = _ENDS[m[1].lower()].search(page, body)
            end = close.end() if close else len(page)
        out.append(page[at : m.start()])
        at = look = end
    return "".join([*out, page[at:]])


def title_of(page: str) -> str | None:
    m = _TITLE.search(page)
    body = _tag_end(page, m) if m else -1
    if body < 0:
        return None
    close = _ENDS["title"].search(page, body)
    return page[body : close.start() if close else len(page)]


def links_of(page: str) -> list[tuple[str, str, str]]:
    """(tag, attribute, value) of the first link attribute of every linking tag; a quoted value may hold ``>``."""
    out, at, open_quotes = [], 0, {'"': True, "'": True}
    while m := _LINK.search(page, at):
        limit = page.find(">", m.end())
        limit = len(page) if limit < 0 else limit
        at, look = limit, m.end()
        while name := _NAME.search(page, look, limit):
            begin, value, end = name.end(), None, -1
            quote = page[begin : begin + 1]
            if open_quotes.get(quote):
                end = page.find(quote, begin + 1)
                if end < 0:
                    open_quotes[quote] = False
                else:
                    value, end = page[begin + 1 : end], end + 1
            if value is None and (bare := _BARE.match(page, begin)):
                value, end = bare[0], bare.end()
            if value is not None:
                out.append((m[1], name[1], value))
                at = end
                break
            look = name.start() + 1
        if at >= len(page):
            break
    return out


def digest(raw: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(raw).digest()).decode()


def record_id(kind: str, uri: str, key: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMESPACE, f'{kind} {key} {uri}')}>"


def plain_text(page: str) -> str:
    """Visible text, one line for each block; blank lines are left out."""
    page = _replaced(without_skipped(page), _HEAD, _head_end, "")
    page = _replaced(_replaced(page, _BREAK, _tag_end, "\n"), _TAG, _tag_end, "")
    lines = (_BLANKS.sub(" ", x).strip() for x in unescaped(page).split("\n"))
    return "\n".join(x for x in lines if x)


def page_metadata(page: str, size: int) -> str:
    title = title_of(page)
    links = [{"path": f"{tag.upper()}@/{name.lower()}", "url": unescaped(value)} for tag, name, value in links_of(without_skipped(page))]
    value = {"title": " ".join(unescaped(title).split()) if title is not None else None, "content-length": size, "links": links}
    return json.dumps(value, ensure_ascii=False, sort_keys=True)


def header_block(fields: list[tuple[str, str]]) -> str:
    return "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + "\r\n"


def as_record(header: str, content: bytes) -> bytes:
    return header.encode() + content + b"\r\n\r\n"


def parse_records(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Records of an uncompressed WARC file."""
    at = 0
    while at < len(raw):
        end = raw.index(b"\r\n\r\n", at)
        version, *lines = raw[at:end].decode().split("\r\n")
        if not version.startswith("WARC/"):
            raise ValueError(f"no record at byte {at}")
        fields = dict(x.split(": ", 1) for x in lines)
        size = int(fields["Content-Length"])
        body = raw[end + 4 : end + 4 + size]
        if len(body) != size or raw[end + 4 + size : end + 8 + size] != b"\r\n\r\n":
            raise ValueError(f"a record is cut at byte {end}")
        yield fields, body
        at = end + 8 + size


def _clean(x: str) -> str:
    """A header value stays on one line."""
    return re.sub(r"[\r\n]+", " ", x)


def derive(page_id: int | None, url: str | None, page: str | None, date: str | None = None, response_id: str | None = None, http_header: str | None = None, payload_digest: str | None = None, block_digest: str | None = None) -> list[tuple]:
    """The response's id and its two derivatives as (type, id, header, content)."""
    uri, payload, date = _clean(url or ""), (page or "").encode("utf-8", "replace"), _clean(date or DATE)
    key = f"{page_id} {digest(payload)}"
    source = _clean(response_id) if response_id else record_id("response", uri, key)
    shared = [("WARC-Target-URI", uri), ("WARC-Date", date), ("WARC-Refers-To", source), ("WARC-Refers-To-Target-URI", uri), ("WARC-Refers-To-Date", date)]
    origin = [("WARC-Source-Payload-Digest", _clean(payload_digest or digest(payload)))]
    if http_header is not None or block_digest is not None:
        block = digest((http_header or "").encode("utf-8", "replace") + payload)
        origin.append(("WARC-Source-Block-Digest", _clean(block_digest or block)))
    for line in (http_header or "").replace("\r\n", "\n").split("\n")[1:]:  # after the status line
        name, colon, value = line.partition(":")
        if colon and re.fullmatch(r"[A-Za-z0-9-]+", name.strip()):
            origin.append((f"WARC-Source-{name.strip()}", _clean(value.strip())))
    origin.append(("WARC-Source-Payload-Length", str(len(payload))))
    out = []
    for kind, mime, content in (("metadata", "application/json", page_metadata(page or "", len(payload))), ("conversion", "text/plain; charset=utf-8", plain_text(page or ""))):
        raw = content.encode("utf-8", "replace")
        fields = [("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, uri, key)), *shared, *origin, ("WARC-Block-Digest", digest(raw)), ("Content-Type", mime), ("Content-Length", str(len(raw)))]
        out.append((kind, dict(fields)["WARC-Record-ID"], source, header_block(fields), content))
    return out


CARRIED = ("warc_date", "response_id", "http_header", "payload_digest", "block_digest")  # columns of a response that are carried through


def build_derivatives(pages: DataFrame) -> DataFrame:
    """(page_id, record_type, record_id, refers_to, target_uri, payload_digest, block_digest, content_length, header, content).

    Two rows for every row of ``pages`` (page_id, url, html and, where present, the ``CARRIED`` columns), whatever is
    null in it: a null page is an empty payload, a null url an empty target.  Repeated rows give equal records; an
    empty table gives none.  Other columns play no part.  Very long pages are read whole, in time linear in their length.
    """
    names = ["page_id", "record_type", "record_id", "refers_to", "target_uri", "payload_digest", "block_digest", "content_length", "header", "content"]

    def run(rows):
        for batch in batches(rows, 512):
            out = [[] for _ in names]
            for key, url, page, *carried in zip(*(batch.column(k).to_pylist() for k in range(3 + len(CARRIED))), strict=True):
                payload = carried[3] or digest((page or "").encode("utf-8", "replace"))
                for kind, own, source, header, content in derive(key, url, page, *carried):
                    raw = content.encode("utf-8", "replace")
                    for column, v in zip(out, (key, kind, own, source, _clean(url or ""), payload, digest(raw), len(raw), header, content), strict=True):
                        column.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64() if n in ("page_id", "content_length") else pa.string()) for n, x in zip(names, out, strict=True)], names)

    kept = [(F.col(c) if c in pages.columns else F.lit(None)).cast("string").alias(c) for c in CARRIED]
    source = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"), *kept)
    return source.mapInArrow(run, ", ".join(f"{n} {'long' if n in ('page_id', 'content_length') else 'string'}" for n in names))


def warc_files(derivatives: DataFrame, kind: str) -> DataFrame:
    """One binary row for each partition: the uncompressed WARC file of its records of a kind, with digests and lengths intact."""

    def run(rows):
        for batch in rows:
            raw = [as_record(h, c.encode()) for h, c in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            if raw:
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(raw)], pa.binary())], ["warc"])

    return derivatives.where(F.col("record_type") == kind).select("header", "content").mapInArrow(run, "warc binary")
