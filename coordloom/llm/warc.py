"""WARC derivatives: from response records to linked metadata and plain-text conversion records.

Each response gives one ``metadata`` record (JSON: title, headers, links, digests) and one ``conversion`` record
(the page's visible text, one block a line). Both name the response in WARC-Refers-To, keep its target and date,
its payload digest, and its HTTP headers: the metadata all of them in its envelope, both the content type, status and date in a header
WARC-Source-Headers of their own; ids are version-5 UUIDs of the response's
id and the kind of record, so that reruns and retried tasks give the same records. Payloads sent in chunks or compressed (gzip, deflate) are
decoded before they are read; the digest is that of the payload as it was sent.

Defined cases: null or empty payload: a conversion with empty text and a metadata record without links; a null URL stays
null and has no header line; text that isn't UTF-8 is decoded with replacement; repeated responses give repeated
records; an empty table gives an empty result; other columns aren't read. Records of other types than ``response``
give nothing. In files: a record whose length is missing, broken or beyond the file's end ends where the next record begins, or with the file;
a compressed file that breaks off gives the records before the break. A payload whose encoding is broken is read as it is. A file is one
task's: Spark hands files of up to 2 GB to it whole (WARC files are cut at about 1 GB by custom), larger ones are refused by Spark.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import json
import re
import uuid
import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.llm.html_blocks import blocks_of

#: Fixed date of records whose source has none.
DATE = "2024-01-01T00:00:00Z"
RESPONSES = "record_id string, target_uri string, warc_date string, http_header binary, payload binary, payload_digest string"
DERIVED = (
    "source_key long, record_type string, record_id string, refers_to string, target_uri string, warc_date string, content_type string, "
    "payload_digest string, block_digest string, content_length long, source_headers string, content string"
)
_LINK = re.compile(r"<(a|img|link|script|iframe)\b[^>]*?\b(?:href|src)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_CHARSET = re.compile(rb"charset\s*=\s*[\"']?([\w-]+)", re.I)


def sha1_digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_uuid(*parts: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(10).join(parts))}>"


def headers_of(block: bytes) -> list[tuple[str, str]]:
    """Header fields in order; the first line is kept under an empty name, folded lines are joined."""
    out: list[tuple[str, str]] = []
    for k, line in enumerate(block.decode("utf-8", "replace").splitlines()):
        if k == 0 and ":" not in line.split(" ")[0]:
            out.append(("", line))
        elif line[:1] in " \t" and out:
            out[-1] = (out[-1][0], f"{out[-1][1]} {line.strip()}")
        elif ":" in line:
            name, _, value = line.partition(":")
            out.append((name.strip(), value.strip()))
    return out


def decode(payload: bytes, header: bytes) -> str:
    found = _CHARSET.search(header or b"") or _CHARSET.search(payload[:1024])
    try:
        return payload.decode(found[1].decode() if found else "utf-8", "replace")
    except LookupError:
        return payload.decode("utf-8", "replace")


def unchunked(data: bytes) -> bytes:
    """The body of a chunked transfer; broken chunks leave it as it is."""
    out, at = [], 0
    while True:
        end = data.find(b"\r\n", at)
        try:
            size = int(data[at:end].split(b";")[0], 16) if end >= 0 else -1
        except ValueError:
            return data
        if size < 0 or end + 2 + size > len(data):
            return data
        if size == 0:
            return b"".join(out)
        out.append(data[end + 2 : end + 2 + size])
        at = end + 2 + size + 2


def body_of(payload: bytes, header: bytes) -> bytes:
    """The payload without its transfer and content encodings."""
    fields = {k.lower(): v.lower() for k, v in headers_of(header)}
    if "chunked" in fields.get("transfer-encoding", ""):
        payload = unchunked(payload)
    encoding = fields.get("content-encoding", "")
    try:
        if "gzip" in encoding and payload[:2] == b"\x1f\x8b":
            return gzip.decompress(payload)
        if "deflate" in encoding:
            try:
                return zlib.decompress(payload)
            except zlib.error:
                return zlib.decompress(payload, -zlib.MAX_WBITS)
    except (OSError, EOFError, zlib.error):
        pass
    return payload


#: Response headers that both derived records repeat.
KEPT_HEADERS = ("content-type", "date", "last-modified", "server")


def source_headers(header: bytes) -> str | None:
    """The status line and the kept headers, on one line."""
    fields = [v if not k else f"{k}: {v}" for k, v in headers_of(header) if not k or k.lower() in KEPT_HEADERS]
    return "; ".join(fields) or None


def derive(record_id: str, uri: str | None, date: str | None, header: bytes, payload: bytes, digest: str | None) -> list[tuple]:
    """The metadata and the conversion record of one response."""
    source = decode(body_of(payload, header), header)
    blocks = blocks_of(source)
    digest = digest or sha1_digest(payload)
    links = [{"tag": m[1].lower(), "url": m[2] or m[3] or m[4] or ""} for m in _LINK.finditer(source)]
    title = next((b.text for b in blocks if b.tags[-1:] == ("title",)), None)
    text = "\n".join(b.text for b in blocks if "title" not in b.tags)
    envelope = {
        "WARC-Header-Metadata": {"WARC-Record-ID": record_id, "WARC-Target-URI": uri, "WARC-Date": date or DATE, "WARC-Payload-Digest": digest},
        "HTTP-Response-Metadata": {"Headers": [list(h) for h in headers_of(header)], "Entity-Length": len(payload), "HTML-Metadata": {"Title": title, "Links": links}},
    }
    out = []
    for kind, content_type, content in (("metadata", "application/json", json.dumps({"Envelope": envelope}, ensure_ascii=False, sort_keys=True)), ("conversion", "text/plain", text)):
        block = content.encode("utf-8", "replace")
        out.append((kind, record_uuid(record_id, kind), record_id, uri, date or DATE, content_type, digest, sha1_digest(block), len(block), source_headers(header), content))
    return out


def derivatives(responses: DataFrame, key: str | None = None) -> DataFrame:
    """Two records per response. ``responses`` has the columns of ``RESPONSES``; ``key`` is carried as source_key."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = (pa.int64(), *[pa.string()] * 8, pa.int64(), pa.string(), pa.string())
        names = [c.split()[0] for c in DERIVED.split(", ")]
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                rows = []
                for r in batch.slice(lo, 256).to_pylist():
                    rows += [(r["source_key"], *d) for d in derive(r["record_id"] or "", r["target_uri"], r["warc_date"], r["http_header"] or b"", r["payload"] or b"", r["payload_digest"])]
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in rows], t) for k, t in enumerate(kinds)], names=names)

    columns = [c.split()[0] for c in RESPONSES.split(", ")]
    source = responses.select((F.col(f"`{key}`").cast("long") if key else F.lit(None).cast("long")).alias("source_key"), *columns)
    return source.mapInArrow(run, DERIVED)


def responses_from_pages(pages: DataFrame) -> DataFrame:
    """A table (page_id, url, html) as response records with made-up HTTP headers."""
    body = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    size = F.octet_length(body)
    header = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), size.cast("string"), F.lit("\r\n\r\n")).cast("binary")
    hexed = F.md5(F.concat_ws("\n", F.lit("response"), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.coalesce("url", F.lit(""))))
    parts = [F.substring(hexed, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]
    return pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *parts), F.lit(">")).alias("record_id"), F.col("url").alias("target_uri"), F.lit(DATE).alias("warc_date"), header.alias("http_header"), body.alias("payload"), F.lit(None).cast("string").alias("payload_digest"),
    )


# Files


def _length(fields: dict[str, str]) -> int | None:
    value = fields.get("content-length", "").strip()
    return int(value) if value.isascii() and value.isdigit() else None


def records(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of an uncompressed WARC stream; names of headers in lower case. What can't be read ends the stream."""
    pending = b""
    try:
        while True:
            line = pending or stream.readline()
            while line and not line.startswith(b"WARC/"):  # blank lines, and what is left of a record of a wrong length
                line = stream.readline()
            pending = b""
            if not line:
                return
            lines = [line]
            while (more := stream.readline()) not in (b"\r\n", b"\n", b""):
                lines.append(more)
            fields = {k.lower(): v for k, v in headers_of(b"".join(lines)) if k}
            size = _length(fields)
            if size is not None:
                yield fields, stream.read(size)
                continue
            block = []
            while (more := stream.readline()) and not more.startswith(b"WARC/"):
                block.append(more)
            pending = more
            yield fields, b"".join(block).rstrip(b"\r\n")
    except (OSError, EOFError, zlib.error):
        return


def read_responses(spark: SparkSession, path: str) -> DataFrame:
    """Response records of .warc and .warc.gz files, one file a task; compressed files are decompressed record by record."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        names = [c.split()[0] for c in RESPONSES.split(", ")]
        kinds = (pa.string(), pa.string(), pa.string(), pa.binary(), pa.binary(), pa.string())

        def pack(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=names)

        for batch in batches:
            for content in batch.column(0):
                raw = content.as_buffer()
                stream = io.BufferedReader(pa.input_stream(raw)) if raw.size else io.BytesIO()
                if raw[:2].to_pybytes() == b"\x1f\x8b":
                    stream = gzip.GzipFile(fileobj=stream)
                rows, held = [], 0
                for fields, block in records(stream):
                    if fields.get("warc-type", "").lower() == "response":
                        head, mark, payload = block.partition(b"\r\n\r\n")
                        rows.append((fields.get("warc-record-id"), fields.get("warc-target-uri"), fields.get("warc-date"), head + mark, payload, fields.get("warc-payload-digest")))
                        held += len(block)
                    if held >= 1 << 22:
                        yield pack(rows)
                        rows, held = [], 0
                if rows:
                    yield pack(rows)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, RESPONSES)


def serialise(row: dict) -> bytes:
    """A derived record as WARC bytes."""
    block = row["content"].encode("utf-8", "replace")
    fields = [("WARC-Type", row["record_type"]), ("WARC-Record-ID", row["record_id"]), ("WARC-Refers-To", row["refers_to"]), ("WARC-Target-URI", row["target_uri"]), ("WARC-Date", row["warc_date"]), ("WARC-Payload-Digest", row["payload_digest"]), ("WARC-Block-Digest", row["block_digest"]), ("WARC-Source-Headers", row["source_headers"]), ("Content-Type", row["content_type"]), ("Content-Length", str(len(block)))]
    return ("WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields if v is not None) + "\r\n").encode() + block + b"\r\n\r\n"


def as_warc_members(derived: DataFrame) -> DataFrame:
    """(record_type, record_id, member): each record as a gzip member of its own; members of one type joined end to end are a .warc.gz file."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            rows = batch.to_pylist()
            yield pa.RecordBatch.from_arrays([batch.column("record_type"), batch.column("record_id"), pa.array([gzip.compress(serialise(r), mtime=0) for r in rows], pa.binary())], names=["record_type", "record_id", "member"])

    return derived.mapInArrow(run, "record_type string, record_id string, member binary")
