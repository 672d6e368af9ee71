"""WARC derivatives: metadata and plain-text conversion records linked to their responses.

A page becomes a response record; each response yields a metadata record (links, title and header
facts as JSON) and a conversion record (plain text). Both keep the response's target URI and date,
its id as WARC-Refers-To, and its payload digest. Record ids are name-based, so a rerun after a lost
executor writes the same records. All work is one narrow pass over Arrow batches.
"""

from __future__ import annotations

import base64
import hashlib
import html as entities
import json
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idfold.llm.common import table

#: The record version, the namespace of record ids and the date of undated pages.
VERSION = "WARC/1.1"
NAMESPACE = uuid.UUID("6f1cf8a4-6d0b-5c11-9a58-3c1f6d2b7a10")
DEFAULT_DATE = "2024-01-01T00:00:00Z"

SCHEMA = (
    "page_id long, warc_type string, record_id string, refers_to string, target_uri string, warc_date string, "
    "content_type string, content_length long, block_digest string, payload_digest string, source_headers string, block string"
)

_DROPPED = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|template|noscript)\b.*?(?:</\1\s*>|\Z)", re.S | re.I)
_BLOCKS = re.compile(r"</?(?:p|div|br|h[1-6]|li|ul|ol|tr|table|section|article|header|footer|nav|main|pre|blockquote|title|head|body|html|hr|td|th|dd|dt)\b[^>]*>", re.I)
_TAGS = re.compile(r"<[a-zA-Z/!?][^>]*>")
_TITLE = re.compile(r"<title[^>]*>(.*?)</title>", re.S | re.I)
_LINKS = re.compile(r"""<a\s[^>]*?href\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_SPACES = re.compile(r"[ \t\r\f\v]+")
_BREAKS = re.compile(r" *\n\s*")


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(NAMESPACE, chr(31).join(map(str, parts)))}>"


def plain_text(page: str) -> str:
    """Text of a page: scripts, styles and comments dropped, block tags as line breaks, entities resolved."""
    text = _TAGS.sub("", _BLOCKS.sub("\n", _DROPPED.sub(" ", page)))
    text = entities.unescape(text).replace("\xa0", " ")
    return _BREAKS.sub("\n", _SPACES.sub(" ", text)).strip()


def page_facts(page: str) -> dict:
    """Title and links of a page."""
    body = _DROPPED.sub(" ", page)
    title = _TITLE.search(body)
    return {
        "title": _SPACES.sub(" ", entities.unescape(_TAGS.sub("", title[1]))).strip() if title else None,
        "links": [entities.unescape("".join(m)) for m in _LINKS.findall(body)],
    }


def response_record(page_id: int | None, url: str | None, page: str | None, date: str = DEFAULT_DATE) -> dict:
    """The response record of a page; null html is an empty payload, a null url an empty target."""
    payload = (page or "").encode("utf-8", "surrogatepass")
    headers = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n"
    return {
        "page_id": page_id,
        "warc_type": "response",
        "record_id": record_id("response", page_id, url, digest(payload)),
        "refers_to": None,
        "target_uri": url or "",
        "warc_date": date,
        "content_type": "application/http; msgtype=response",
        "content_length": len(headers) + len(payload),
        "block_digest": digest(headers.encode() + payload),
        "payload_digest": digest(payload),
        "source_headers": headers,
        "block": headers + (page or ""),
    }


def derive(response: dict) -> list[dict]:
    """The metadata and the conversion record of a response record."""
    page = response["block"][len(response["source_headers"]) :]
    facts = page_facts(page)
    about = {
        "Container": {"WARC-Record-ID": response["record_id"], "WARC-Target-URI": response["target_uri"]},
        "Payload-Digest": response["payload_digest"],
        "HTTP-Headers": dict(x.split(": ", 1) for x in response["source_headers"].strip().split("\r\n")[1:]),
        "Title": facts["title"],
        "Links": facts["links"],
    }
    out = []
    for kind, content_type, block in (
        ("metadata", "application/json", json.dumps(about, ensure_ascii=False, sort_keys=True)),
        ("conversion", "text/plain; charset=utf-8", plain_text(page)),
    ):
        data = block.encode("utf-8", "surrogatepass")
        out.append(
            {
                "page_id": response["page_id"],
                "warc_type": kind,
                "record_id": record_id(kind, response["record_id"]),
                "refers_to": response["record_id"],
                "target_uri": response["target_uri"],
                "warc_date": response["warc_date"],
                "content_type": content_type,
                "content_length": len(data),
                "block_digest": digest(data),
                "payload_digest": response["payload_digest"],
                "source_headers": response["source_headers"],
                "block": block,
            }
        )
    return out


def _records(pages: DataFrame, make, id_col: str, url_col: str, html_col: str, date_col: str | None) -> DataFrame:
    date = F.coalesce(F.col(date_col).cast("string"), F.lit(DEFAULT_DATE)) if date_col else F.lit(DEFAULT_DATE)
    chosen = pages.select(F.col(id_col).cast("long").alias("i"), F.col(url_col).alias("u"), F.col(html_col).alias("h"), date.alias("d"))
    fields = [p.split()[0] for p in SCHEMA.split(", ")]
    kinds = {"page_id": pa.int64(), "content_length": pa.int64()}
    schema = pa.schema([(f, kinds.get(f, pa.string())) for f in fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):  # few pages at a time: records hold whole texts
                rows = [r for page in zip(*batch.slice(start, 256).to_pydict().values(), strict=True) for r in make(response_record(*page))]
                yield pa.RecordBatch.from_pylist(rows, schema)

    return chosen.mapInArrow(run, SCHEMA)


def response_records(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date_col: str | None = None) -> DataFrame:
    """One response record per page."""
    return _records(pages, lambda r: [r], id_col, url_col, html_col, date_col)


def derivatives(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date_col: str | None = None) -> DataFrame:
    """Two records per page, metadata and conversion, linked to the page's response record.

    Null html and null urls count as empty; repeated pages give repeated records with the same ids;
    an empty table gives no records; extra columns are ignored.
    """
    return _records(pages, derive, id_col, url_col, html_col, date_col)


def serialised(row: dict) -> bytes:
    """A record in WARC form."""
    block = row["block"].encode("utf-8", "surrogatepass")
    headers = [
        ("WARC-Type", row["warc_type"]),
        ("WARC-Record-ID", row["record_id"]),
        ("WARC-Refers-To", row["refers_to"]),
        ("WARC-Target-URI", row["target_uri"]),
        ("WARC-Date", row["warc_date"]),
        ("WARC-Block-Digest", row["block_digest"]),
        ("WARC-Payload-Digest", row["payload_digest"]),
        ("Content-Type", row["content_type"]),
        ("Content-Length", len(block)),
    ]
    head = VERSION + "\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers if v is not None)
    return head.encode() + b"\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> list[dict]:
    """Headers and block of every record in WARC bytes."""
    out, at = [], 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        head = data[at:end].decode().split("\r\n")
        fields = dict(x.split(": ", 1) for x in head[1:])
        size = int(fields["Content-Length"])
        out.append(fields | {"version": head[0], "block": data[end + 4 : end + 4 + size]})
        at = end + 4 + size + 4
    return out


def write_warc(records: DataFrame, path: str, *, compression: str = "gzip") -> None:
    """Write records as WARC text files through Spark's own writer, so any store that Spark knows works."""
    header = lambda name, col: F.when(F.col(col).isNotNull(), F.concat(F.lit(f"{name}: "), F.col(col).cast("string"), F.lit("\r\n"))).otherwise("")
    text = F.concat(
        F.lit(VERSION + "\r\n"), header("WARC-Type", "warc_type"), header("WARC-Record-ID", "record_id"), header("WARC-Refers-To", "refers_to"),
        header("WARC-Target-URI", "target_uri"), header("WARC-Date", "warc_date"), header("WARC-Block-Digest", "block_digest"),
        header("WARC-Payload-Digest", "payload_digest"), header("Content-Type", "content_type"), header("Content-Length", "content_length"),
        F.lit("\r\n"), F.col("block"),
    )
    records.select(text.alias("value")).write.option("lineSep", "\r\n\r\n").option("compression", compression).text(path)


def op8_warc_derivatives(spark, sf_dir: str) -> DataFrame:
    return derivatives(table(spark, sf_dir, "pages"))
