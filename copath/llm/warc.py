"""WARC derivatives: linked metadata and plain-text conversion records for responses.

A response is a record id, a target URI, a date, HTTP header text and a payload, and may have its WARC digests. Each gives one
metadata record (title, language, out-links and the source's headers as JSON) and one conversion record (visible
plain text). Both refer to the response by WARC-Refers-To, keep its target, date, HTTP
headers and digests (the payload's SHA-1 in base 32 where the source names none), and carry the digest of their own block.
Record ids are name-based, so that a lost task makes the same records again. For reading text, chunked and compressed payloads are unpacked and
decoded by their charset; digests are of the bytes as they came.

Null payloads are empty; empty responses give empty text and no links. Responses without a record id get
one from target and payload digest. Repeated responses give repeated records. A payload that can't be unpacked is read as it is, bytes that aren't of the
charset become U+FFFD.

Files are WARC 1.1, one record after another, whole files gzipped on demand. Reading streams records; a file that ends inside a record gives what
there is of it, as truncated.
"""

from __future__ import annotations

import base64
import hashlib
import html as entities
import json
import re
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

HIDE = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|head)\b[^>]*>.*?(?:</\1\s*>|\Z)", re.S | re.I)
BLOCK = re.compile(r"</?(?:p|div|li|ul|ol|h[1-6]|br|tr|td|th|table|article|section|nav|header|footer|aside|main|form|blockquote|pre|body|hr|dd|dt|dl)\b[^>]*>", re.I)
ANY = re.compile(r"<[a-zA-Z/!?][^>]*>")
TITLE = re.compile(r"<title[^>]*>(.*?)</title", re.S | re.I)
LANG = re.compile(r"<html[^>]*\blang\s*=\s*[\"']?([\w-]+)", re.I)
HREF = re.compile(r"<a\b[^>]*?\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
EDGES = re.compile(r"[^\S\n]*\n\s*")
RUNS = re.compile(r"[^\S\n]+")


def digest(block: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()


def record_id(*names: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, chr(10).join(names))}>"


def plain_text(page: str) -> str:
    """Visible text: one line a block, one space between words."""
    text = BLOCK.sub("\n", HIDE.sub(" ", page))
    text = entities.unescape(ANY.sub("", text))
    return EDGES.sub("\n", RUNS.sub(" ", text)).strip()


def facts(page: str, headers: str) -> str:
    title, lang = TITLE.search(page), LANG.search(page)
    links = [entities.unescape(a or b or c) for a, b, c in HREF.findall(page)]
    return json.dumps({"title": entities.unescape(title[1]).strip() if title else None, "language": lang[1] if lang else None, "links": links, "source_headers": headers}, ensure_ascii=False)


CHARSET = re.compile(r"charset\s*=\s*[\"']?([\w.:-]+)", re.I)


def header(headers: str, name: str) -> str:
    """Value of an HTTP header (empty: none)."""
    found = re.search(rf"^{name}\s*:(.*)$", headers, re.I | re.M)
    return found[1].strip() if found else ""


def unchunked(raw: bytes) -> bytes:
    """A chunked body without its chunk sizes; what isn't chunked stays."""
    out, at = [], 0
    while True:
        end = raw.find(b"\r\n", at)
        try:
            size = int(raw[at:end].split(b";")[0], 16) if end > 0 else -1
        except ValueError:
            size = -1
        if size < 0:
            return raw if not out else b"".join(out)
        if not size:
            return b"".join(out)
        out.append(raw[end + 2 : end + 2 + size])
        at = end + 2 + size + 2


def readable(raw: bytes, headers: str) -> str:
    """A payload's text."""
    if "chunked" in header(headers, "transfer-encoding").lower():
        raw = unchunked(raw)
    packed = header(headers, "content-encoding").lower()
    if "gzip" in packed or "deflate" in packed:
        for bits in (47, -15):
            try:
                raw = zlib.decompressobj(bits).decompress(raw)
                break
            except zlib.error:
                continue
    found = CHARSET.search(header(headers, "content-type")) or CHARSET.search(raw[:2048].decode("latin-1"))
    try:
        return raw.decode(found[1] if found else "utf-8", errors="replace")
    except LookupError:
        return raw.decode(errors="replace")


RECORD = (
    "source_id string, warc_type string, record_id string, refers_to string, target_uri string, warc_date string, content_type string, "
    "content_length long, block_digest string, source_payload_digest string, source_block_digest string, source_headers string, block string"
)
SOURCE = ("record_id", "target_uri", "warc_date", "http_headers", "payload", "payload_digest", "block_digest")


def derive(responses: DataFrame) -> DataFrame:
    """Two records for each row of record_id, target_uri, warc_date, http_headers, payload (text or bytes), and payload_digest and block_digest if there are such columns."""
    have = set(responses.columns)
    cast = lambda c: F.col(c).cast("binary" if c == "payload" else "string")
    rows = responses.select(*[(cast(c) if c in have else F.lit(None).cast("string")).alias(c) for c in SOURCE])

    def one(batches):
        names = [f.split()[0] for f in RECORD.split(", ")]
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                made = []
                for rid, uri, date, headers, raw, known, block_known in zip(*[c.to_pylist() for c in b.slice(lo, 256).columns]):
                    raw, headers, uri = raw or b"", headers or "", uri or ""
                    page, source = readable(raw, headers), known or digest(raw)
                    rid = rid or record_id(uri, source)
                    for kind, mime, block in (("metadata", "application/json", facts(page, headers)), ("conversion", "text/plain", plain_text(page))):
                        own = block.encode(errors="replace")
                        made.append((rid, kind, record_id(rid, kind), rid, uri, date, mime, len(own), digest(own), source, block_known, headers, own.decode()))
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if n == "content_length" else pa.string()) for n, c in zip(names, zip(*made))], names)

    return rows.mapInArrow(one, RECORD)


def responses_from_pages(pages: DataFrame, date: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Responses of a table of raw pages (page_id, url, html), with a minimal HTTP header."""
    length = F.octet_length(F.coalesce("html", F.lit(""))).cast("string")
    name = F.sha1(F.concat_ws("\n", F.col("page_id").cast("string"), "url"))
    urn = F.concat(F.lit("<urn:uuid:"), F.substring(name, 1, 8), F.lit("-"), F.substring(name, 9, 4), F.lit("-5"), F.substring(name, 14, 3), F.lit("-8"), F.substring(name, 18, 3), F.lit("-"), F.substring(name, 21, 12), F.lit(">"))
    return pages.select(urn.alias("record_id"), F.col("url").alias("target_uri"), F.lit(date).alias("warc_date"), F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), length, F.lit("\r\n")).alias("http_headers"), F.col("html").alias("payload"))


#: What stands between records; the text sink writes it behind each.
GAP = "\r\n\r\n"


def _record(kind: str, fields: dict[str, str | None], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in {"WARC-Type": kind, **fields, "Content-Length": str(len(block))}.items() if v is not None)
    return f"WARC/1.1\r\n{head}\r\n".encode() + block


def _write(rows: DataFrame, path: str, compression: str | None) -> None:
    """Writes rows (raw binary) as WARC files part-*.warc or part-*.warc.gz into a folder."""
    spark = rows.sparkSession
    rows.select(F.col("raw").cast("string")).write.option("lineSep", GAP).option("compression", compression or "none").text(path)
    # The sink names its files .txt; only names change here, no data moves.
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    for f in files.listStatus(where):
        name = f.getPath().getName()
        if ".txt" in name:
            files.rename(f.getPath(), spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where, name.replace(".txt", ".warc")))


def write_warc(records: DataFrame, path: str, compression: str | None = None) -> None:
    """Records of ``derive`` as WARC files in a folder; compression: None or gzip."""

    def one(batches):
        for b in batches:
            made = []
            for r in b.to_pylist():
                fields = {"WARC-Record-ID": r["record_id"], "WARC-Refers-To": r["refers_to"], "WARC-Target-URI": r["target_uri"], "WARC-Date": r["warc_date"], "WARC-Block-Digest": r["block_digest"], "WARC-Source-Payload-Digest": r["source_payload_digest"], "WARC-Source-Block-Digest": r["source_block_digest"], "Content-Type": r["content_type"]}
                made.append(_record(r["warc_type"], fields, r["block"].encode(errors="replace")))
            yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], ["raw"])

    _write(records.mapInArrow(one, "raw binary"), path, compression)


def write_responses(responses: DataFrame, path: str, compression: str | None = None) -> None:
    """Responses (as ``derive`` takes them) as WARC files in a folder."""

    def one(batches):
        for b in batches:
            made = []
            for r in b.to_pylist():
                payload = r["payload"] or b""
                block = (r["http_headers"] or "").encode() + b"\r\n" + payload
                fields = {"WARC-Record-ID": r["record_id"], "WARC-Target-URI": r["target_uri"], "WARC-Date": r["warc_date"], "WARC-Payload-Digest": digest(payload), "WARC-Block-Digest": digest(block), "Content-Type": "application/http; msgtype=response"}
                made.append(_record("response", fields, block))
            yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], ["raw"])

    rows = responses.select("record_id", "target_uri", "warc_date", "http_headers", F.col("payload").cast("binary").alias("payload"))
    _write(rows.mapInArrow(one, "raw binary"), path, compression)


#: Every record begins so; the rest of the version and the fields follow.
MARK = b"WARC/1."


def records_of(pieces):
    """(fields, block, whether the record is whole) of what stands between marks, in order; pieces: (file, bytes). A mark inside a block is put back."""
    held = None  # file, fields, size, block
    for name, x in pieces:
        if held is not None and held[0] == name and len(held[3]) < held[2]:
            held = (*held[:3], held[3] + MARK + x)
        else:
            if held is not None:
                yield held[1], held[3][: held[2]], False
                held = None
            end = x.find(b"\r\n\r\n")
            if end < 0:
                continue
            fields = {}
            for line in x[:end].decode(errors="replace").split("\r\n")[1:]:
                k, _, v = line.partition(":")
                fields[k.strip().lower()] = v.strip()
            length = fields.get("content-length", "")
            held = name, fields, int(length) if length.isdigit() else 0, x[end + 4 :]
        if len(held[3]) >= held[2]:
            yield held[1], held[3][: held[2]], True
            held = None
    if held is not None:
        yield held[1], held[3][: held[2]], False


RESPONSE = "record_id string, target_uri string, warc_date string, http_headers string, payload binary, payload_digest string, block_digest string, truncated boolean"
PLAIN = "warc_type string, record_id string, refers_to string, target_uri string, warc_date string, content_type string, block_digest string, source_payload_digest string, source_block_digest string, block binary, truncated boolean"


def _read(spark: SparkSession, path: str, wanted, make, schema: str) -> DataFrame:
    names = [f.split()[0] for f in schema.split(", ")]
    types = {"binary": pa.binary(), "boolean": pa.bool_(), "string": pa.string()}
    kinds = [types[f.split()[1]] for f in schema.split(", ")]

    def one(batches):
        pieces = ((f, x) for b in batches for f, x in zip(b.column("file").to_pylist(), b.column("raw").to_pylist()))
        made, held = [], 0
        for fields, block, whole in records_of(pieces):
            if wanted(fields):
                made.append((*make(fields, block), not whole))
                held += len(block)
            if held > 4 << 20:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*made), kinds)], names)
                made, held = [], 0
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*made), kinds)], names)

    lines = spark.read.option("lineSep", MARK.decode()).text(path)
    return lines.select(F.input_file_name().alias("file"), F.col("value").cast("binary").alias("raw")).mapInArrow(one, schema)


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """The response records of WARC files, gzipped or not: record_id, target_uri, warc_date, http_headers, payload (bytes), payload_digest, block_digest, truncated."""

    def make(f, block):
        head, _, payload = block.partition(b"\r\n\r\n")
        return f.get("warc-record-id"), f.get("warc-target-uri"), f.get("warc-date"), head.decode(errors="replace") + "\r\n", payload, f.get("warc-payload-digest"), f.get("warc-block-digest")

    return _read(spark, path, lambda f: f.get("warc-type") == "response", make, RESPONSE)


def read_derivatives(spark: SparkSession, path: str) -> DataFrame:
    """The metadata and conversion records of WARC files."""
    fields = ("warc-type", "warc-record-id", "warc-refers-to", "warc-target-uri", "warc-date", "content-type", "warc-block-digest", "warc-source-payload-digest", "warc-source-block-digest")
    return _read(spark, path, lambda f: f.get("warc-type") in ("metadata", "conversion"), lambda f, block: (*(f.get(k) for k in fields), block), PLAIN)


def report(pages: DataFrame) -> DataFrame:
    """Both records of every page, with their blocks and the blocks' SHA-256."""
    return derive(responses_from_pages(pages)).withColumn("block_sha256", F.sha2("block", 256)).drop("source_id")
