"""WARC derivative builder: responses to linked metadata and text records.

A response gives two records. The conversion record holds the page's visible
text; the metadata record holds named fields about the response. Both refer to
the response by its identifier, carry its target, date and payload digest, and
have digests of their own blocks. Identifiers follow from the response's, so
reruns build the same bytes. Each record is one gzip member that can be joined
to others into a file.

The metadata record also keeps every HTTP header of the response and, where
the source has a column ``warc`` with header lines, its WARC headers: in order,
with repeats, one field ``http-header`` or ``source-header`` each.

Edge cases: a null payload counts as empty and converts to an empty block; a
null url or header is left out; repeated responses give repeated records; other
columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import html
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import lean

_UNSEEN = re.compile(
    r"<!--.*?(?P<comment>-->|$)|<(?P<name>script|style|noscript|template|head)\b[^>]*>.*?(?P<body></(?P=name)\s*>|$)|<![^>]*>|<\?[^>]*>", re.I | re.S
)
_BREAK = re.compile(
    r"</?(?:address|article|aside|blockquote|body|br|center|dd|details|dialog|div|dl|dt|fieldset|figcaption|figure|footer|form|h[1-6]|header|hr|html"
    r"|li|main|nav|ol|option|p|pre|section|table|tbody|tfoot|thead|tr|ul)\b[^>]*>", re.I,
)
_CELL, _TAG = re.compile(r"<t[dh]\b[^>]*>", re.I), re.compile(r"</?[A-Za-z][^>]*>")
_TITLE, _TITLE_END = re.compile(r"<title\b", re.I), re.compile(r"</title", re.I)
_LINK, _HREF = re.compile(r"<a\s([^>]*)", re.I), re.compile(r"\bhref\s*=", re.I)
_GAP = re.compile(r"[ \r\n\f\t]+")


def _closed(text: str) -> int:
    """End of the last tag. Up to it every ``[^>]*>`` finds its end, so no scan of a tag is in vain and time grows with the text."""
    return text.rfind(">") + 1


def _sub(pattern: re.Pattern, by: str, text: str) -> str:
    end = _closed(text)
    return pattern.sub(by, text[:end]) + text[end:]


def _seen(page: str) -> str:
    """The page without comments, scripts, declarations; an open one lasts to the end."""
    end, at, out = _closed(page), 0, []
    for m in _UNSEEN.finditer(page, 0, end):
        out.append(page[at : m.start()])
        at = m.end()
        if m["comment"] == "" or m["body"] == "":
            return "".join(out)
    return "".join([*out, page[at:end], page[end:].partition("<!--")[0]])


def visible_text(page: str) -> str:
    """Everything visible of a page: blocks on lines, table cells apart by tabs, entities decoded."""
    flat = _GAP.sub(" ", _seen(page))
    flat = html.unescape(_sub(_TAG, "", _sub(_CELL, "\t", _sub(_BREAK, "\n", flat))))
    return "\n".join(line for x in flat.split("\n") if (line := x.strip(" \t")))


def title_of(page: str) -> str:
    """Text of the first title element that is closed, entities decoded."""
    opened = _TITLE.search(page)
    begin = page.find(">", opened.end()) + 1 if opened else 0
    closed = _TITLE_END.search(page, begin) if begin else None
    return _GAP.sub(" ", html.unescape(page[begin : closed.start()])).strip() if closed else ""


def count_links(page: str) -> int:
    return sum(_HREF.search(m[1]) is not None for m in _LINK.finditer(page))


def _digest(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def _identifier(*parts: str) -> str:
    h = hashlib.md5("\n".join(parts).encode()).hexdigest()
    return f"<urn:uuid:{h[:8]}-{h[8:12]}-{h[12:16]}-{h[16:20]}-{h[20:]}>"


def _record(headers: list[tuple[str, str | None]], block: bytes) -> bytes:
    clean = lambda v: re.sub(r"[\r\n]+", " ", v)
    head = "".join(f"{k}: {clean(v)}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))] if v)
    return b"WARC/1.1\r\n" + head.encode("utf-8") + b"\r\n" + block + b"\r\n\r\n"


def responses(pages: DataFrame) -> DataFrame:
    """Response records of ``pages(page_id, url, html)``: identifier, date and HTTP headers follow from the row."""
    key = F.md5(F.concat_ws("\n", F.col("page_id").cast("string"), F.coalesce("url", F.lit(""))))
    cut = [F.substring(key, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]
    return pages.select(
        F.col("page_id").cast("long"),
        F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *cut), F.lit(">")).alias("record_id"),
        F.col("url").cast("string"),
        F.date_format(F.timestamp_seconds(F.lit(1704067200) + F.coalesce("page_id", F.lit(0))), "yyyy-MM-dd'T'HH:mm:ss'Z'").alias("date"),
        F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n").alias("http"),
        F.col("html").cast("string").alias("payload"),
    )


def _headers(block: str | None) -> list[str]:
    """Header lines in order; folded lines are joined to the one before, a first line without a name is left out."""
    out: list[str] = []
    for line in re.split(r"\r\n|\n|\r", block or ""):
        if line[:1] in (" ", "\t") and out:
            out[-1] += " " + line.strip()
        elif re.match(r"[^\s:]+[ \t]*:", line):
            out.append(line)
    return out


def _derive(record_id: str, url: str | None, date: str | None, http: str | None, payload: str | None, warc: str | None = None) -> list[tuple]:
    body = (payload or "").encode("utf-8")
    source = _digest(body)
    page = payload or ""
    text = visible_text(page).encode("utf-8")
    conv, meta = _identifier("conversion", record_id), _identifier("metadata", record_id)
    common = [("WARC-Target-URI", url), ("WARC-Date", date), ("WARC-Refers-To", record_id), ("WARC-Payload-Digest", source)]
    kind = next((h.partition(":")[2].strip() for h in (http or "").split("\r\n") if h.lower().startswith("content-type:")), None)
    fields = [
        ("http-status", (http or "").split("\r\n")[0].partition(" ")[2]), ("http-content-type", kind), ("title", title_of(page)),
        ("outlinks", str(count_links(page))), ("text-chars", str(len(text.decode()))), ("conversion", conv), ("conversion-digest", _digest(text)),
        *(("http-header", h) for h in _headers(http)), *(("source-header", h) for h in _headers(warc)),
    ]
    about = "".join(f"{k}: {re.sub(r'[\r\n]+', ' ', v)}\r\n" for k, v in fields if v).encode("utf-8")
    out = []
    for what, own, block, media in (("conversion", conv, text, "text/plain; charset=utf-8"), ("metadata", meta, about, "application/warc-fields")):
        headers = [("WARC-Type", what), ("WARC-Record-ID", own), *common, ("WARC-Block-Digest", _digest(block)), ("Content-Type", media)]
        if what == "metadata":
            headers.insert(2, ("WARC-Concurrent-To", conv))
        out.append((what, own, record_id, source, _digest(block), len(block), _record(headers, block)))
    return out


def derive(source: DataFrame) -> DataFrame:
    """Two rows per response, with the bytes of each record in ``record``."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = ["page_id", "kind", "record_id", "refers_to", "source_digest", "block_digest", "block_bytes", "record"]
        for b in batches:
            for at in range(0, len(b), 256):
                part = b.iloc[at : at + 256]
                rows = [
                    (page, *row)
                    for page, *response in zip(part["page_id"], part["record_id"], part["url"], part["date"], part["http"], part["payload"], part["warc"], strict=True)
                    for row in _derive(*response)
                ]
                yield pd.DataFrame(rows, columns=names)

    warc = F.col("warc").cast("string") if "warc" in source.columns else F.lit(None).cast("string").alias("warc")
    return source.select("page_id", "record_id", "url", "date", "http", "payload", warc).mapInPandas(
        run, "page_id long, kind string, record_id string, refers_to string, source_digest string, block_digest string, block_bytes long, record binary"
    )


def gzip_members(records: DataFrame) -> DataFrame:
    """The same rows with each record compressed to one gzip member; members joined in any order are a file."""
    pack = F.pandas_udf(lambda s: s.map(lambda r: gzip.compress(r, 6, mtime=0)), "binary")
    return records.withColumn("record", pack("record"))


def parse_records(data: bytes) -> list[tuple[dict[str, str], bytes]]:
    """Headers and blocks of concatenated records, compressed or plain."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    out, at = [], 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8").split("\r\n")
        headers = dict(x.split(": ", 1) for x in lines[1:])
        begin = end + 4
        stop = begin + int(headers["Content-Length"])
        out.append((headers, data[begin:stop]))
        at = stop + 4
    return out
