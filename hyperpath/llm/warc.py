"""Web archives: a converter from the legacy ARC format, and WARC files written and read through Spark.

ARC: a file starts with a version block whose second line names the version. Version 1 gives each record one header
line of five fields (URL, IP address, date, type, length), version 2 of ten (URL, IP address, date, type, result code,
checksum, location, offset, file name, length); the declared length says how many bytes follow. The converter reads
by declared lengths only and synthesises what WARC needs besides: a record id (a UUID from URL, date and digest, or from the row's key
and digest, so that a retried task writes the same id and a revisit can name the response's), an ISO timestamp, the record type, and
SHA-1 digests.

Archives are written by Spark's text writer from byte strings, so they commit like any Spark output and go to any
store that Spark reaches. Records are joined to chunks of bounded bytes and files have a bounded number of chunks; files are read whole.

Defined results: null payloads are empty payloads; a null URL is written as urn:none and read back as null; payloads
may hold any bytes, line breaks and archive headers too; tables without rows give no record; rows of equal id and payload are one
record twice. A payload larger than a chunk is a chunk of its own.
"""

from __future__ import annotations

import gzip
import hashlib
import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

CRLF = b"\r\n"
NO_URL = "urn:none"
#: Equal payloads of at least so many bytes are revisits of one response.
REVISIT_BYTES = 1000
#: Unpacked bytes of a file of archives, about, and the chunks that it has.
FILE_BYTES, FILE_CHUNKS = 64 << 20, 16
#: Field names of an ARC header line, by version.
ARC_FIELDS = {
    1: ("url", "ip", "date", "type", "length"),
    2: ("url", "ip", "date", "type", "result", "checksum", "location", "offset", "filename", "length"),
}
#: Fixed value: the profile of a revisit by digest.
SAME_PAYLOAD = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


@dataclass
class ArcRecord:
    fields: dict[str, str]
    content: bytes


@dataclass
class WarcRecord:
    kind: str
    headers: dict[str, str] = field(default_factory=dict)
    content: bytes = b""

    @property
    def payload(self) -> bytes:
        """The content, or the body of an HTTP message."""
        http = self.headers.get("Content-Type", "").startswith("application/http") and CRLF * 2 in self.content
        return self.content.split(CRLF * 2, 1)[1] if http else self.content

    def to_bytes(self) -> bytes:
        head = [b"WARC/1.1", b"WARC-Type: " + self.kind.encode()]
        head += [f"{k}: {v}".encode() for k, v in self.headers.items()]
        head.append(b"Content-Length: %d" % len(self.content))
        return CRLF.join(head) + CRLF * 2 + self.content + CRLF * 2


# ---------------------------------------------------------------- ARC


def arc_version_block(version: int = 1, name: str = "records.arc", origin: str = "engine") -> bytes:
    """The block at the start of an ARC file."""
    body = f"{version} 0 {origin}\n{' '.join(_ARC_LABELS[version])}\n".encode()
    line = ["filedesc://" + name, "0.0.0.0", "20000101000000", "text/plain"]
    line += ["200", "-", "-", "0", name] if version == 2 else []
    return f"{' '.join(line)} {len(body)}\n".encode() + body + b"\n"


#: The labels in the third line of a version block.
_ARC_LABELS = {
    1: ("URL", "IP-address", "Archive-date", "Content-type", "Archive-length"),
    2: ("URL", "IP-address", "Archive-date", "Content-type", "Result-code", "Checksum", "Location", "Offset", "Filename", "Archive-length"),
}


def arc_record(url: str, content: bytes, *, date: str, mime: str = "text/html", version: int = 1, ip: str = "0.0.0.0") -> bytes:
    """One ARC record; blanks in the URL are escaped, as the header line is split at blanks."""
    line = [re.sub(r"\s", lambda m: quote(m[0]), url), ip, date, mime]
    line += ["200", hashlib.md5(content).hexdigest(), "-", "0", "-"] if version == 2 else []
    return f"{' '.join(line)} {len(content)}\n".encode() + content + b"\n"


def parse_arc(data: bytes, *, version: int | None = None) -> Iterator[ArcRecord]:
    """Records of an ARC file, its version block first if it has one. version: needed only without such a block."""
    at = 0
    while at < len(data):
        if data[at : at + 1] in b"\r\n":
            at += 1
            continue
        stop = data.find(b"\n", at)
        if stop < 0:
            raise ValueError(f"ARC header line at byte {at} has no end")
        parts = data[at:stop].rstrip(b"\r").decode("utf-8", "replace").split(" ")
        block = parts[0].startswith("filedesc://")
        if not parts[-1].isdigit():
            raise ValueError(f"ARC header line at byte {at} declares no length: {parts}")
        size = int(parts[-1])
        content = data[stop + 1 : stop + 1 + size]
        if len(content) < size:
            raise ValueError(f"ARC record at byte {at} is cut: {len(content)} of {size} bytes")
        if block:
            version = int(content.split(b" ", 1)[0])
        names = ARC_FIELDS.get(version or 0)
        if names is None or not block and len(parts) != len(names):
            raise ValueError(f"ARC header line at byte {at} doesn't fit version {version}: {parts}")
        yield ArcRecord(dict(zip(names, parts, strict=False)) | {"length": parts[-1]}, content)
        at = stop + 1 + size


def digest(payload: bytes) -> str:
    return hashlib.sha1(payload).hexdigest()


def warc_date(date: str) -> str:
    """An ARC date of 14 digits (or fewer: the rest is the earliest) as ISO 8601 in UTC."""
    d = (re.sub(r"\D", "", date) + "00000101000000"[len(re.sub(r"\D", "", date)) :])[:14]
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def arc_to_warc(record: ArcRecord, *, own_id: str | None = None, refers_to: str | None = None, extra: dict[str, str] | None = None, http: bool | None = None) -> WarcRecord:
    """The equivalent WARC record: warcinfo for a version block, revisit if refers_to is given, else response;
    ids (unless own_id is given), timestamps and digests are synthesised. http: whether the content is an HTTP message (None: if it begins like one)."""
    f, url = record.fields, record.fields["url"]
    if url.startswith("filedesc://"):
        return WarcRecord("warcinfo", {"WARC-Record-ID": record_id(url, f["date"], record.content), "WARC-Date": warc_date(f["date"]), "WARC-Filename": url[11:], "Content-Type": "text/plain"}, record.content)
    http = record.content.startswith(b"HTTP/") if http is None else http
    payload = record.content.split(CRLF * 2, 1)[1] if http and CRLF * 2 in record.content else record.content
    headers = {
        "WARC-Record-ID": own_id or record_id(url, f["date"], record.content), "WARC-Target-URI": url, "WARC-Date": warc_date(f["date"]),
        "WARC-IP-Address": f["ip"], "WARC-Payload-Digest": f"sha1:{digest(payload)}", "WARC-Block-Digest": f"sha1:{digest(record.content)}",
        "Content-Type": "application/http; msgtype=response" if http else f["type"],
    }
    headers |= extra or {}
    if refers_to is None:
        return WarcRecord("response", headers, record.content)
    headers |= {"WARC-Profile": SAME_PAYLOAD, "WARC-Refers-To": refers_to, "WARC-Truncated": "length", "WARC-Block-Digest": f"sha1:{digest(b'')}"}
    return WarcRecord("revisit", headers, b"")


def record_id(url: str, date: str, content: bytes) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{url} {date} {digest(content)}')}>"


def keyed_id(key: object, payload_digest: str) -> str:
    """The record id of a row with a key of its own."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'{key} {payload_digest}')}>"


# ---------------------------------------------------------------- WARC


def parse_warc(data: bytes) -> Iterator[WarcRecord]:
    """Records of a WARC file, by their declared lengths."""
    at = 0
    while at < len(data):
        if data[at : at + 1] in b"\r\n":
            at += 1
            continue
        stop = data.find(CRLF * 2, at)
        if stop < 0 or not data.startswith(b"WARC/", at):
            raise ValueError(f"no WARC record at byte {at}")
        lines = data[at:stop].decode("utf-8", "replace").split("\r\n")[1:]
        headers = {k: v.strip() for k, _, v in (x.partition(":") for x in lines)}
        size = int(headers.pop("Content-Length"))
        content = data[stop + 4 : stop + 4 + size]
        if len(content) < size:
            raise ValueError(f"WARC record at byte {at} is cut: {len(content)} of {size} bytes")
        yield WarcRecord(headers.pop("WARC-Type"), headers, content)
        at = stop + 4 + size


def revisit_plan(pages: DataFrame, payload: Column, *, id_col: str = "page_id", least_bytes: int = REVISIT_BYTES) -> DataFrame:
    """pages with _digest, and _first: the largest id of those with this payload, where this row isn't it.

    Only digests with two rows or more reach the join; a payload that a third of the rows share is one row of the
    right side, and the skew join splits the left.
    """
    dealt = pages.withColumn("_size", F.coalesce(F.octet_length(payload), F.lit(0)))
    dealt = dealt.withColumn("_digest", F.when(F.col("_size") >= least_bytes, F.sha1(payload.cast("binary"))))
    groups = (
        dealt.where("_digest is not null").groupBy("_digest").agg(F.max(id_col).alias("_last"), F.count("*").alias("_n"))
        .where("_n > 1").select(F.col("_digest").alias("_same"), "_last")
    )
    # Rows without a digest get a key of their own, so that they don't meet in one task.
    key = F.coalesce("_digest", F.concat(F.lit("-"), F.monotonically_increasing_id().cast("string")))
    joined = dealt.withColumn("_key", key).join(groups, F.col("_key") == F.col("_same"), "left")
    return joined.withColumn("_first", F.when(F.col(id_col) != F.col("_last"), F.col("_last"))).drop("_size", "_key", "_same", "_last")


def write_warc(
    pages: DataFrame, path: str, *, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", date: str = "20240101000000",
    arc_version: int = 1, file_bytes: int = FILE_BYTES,
) -> None:
    """Each row as an ARC record, converted to WARC, in files of about file_bytes at most under path.

    revisit records carry no payload; their WARC-Payload-Length says how long it is.
    """
    rows = revisit_plan(pages.select(id_col, url_col, payload_col), F.col(payload_col), id_col=id_col)
    rows = rows.select(id_col, url_col, F.col(payload_col).cast("binary").alias("_payload"), "_first")

    def convert(rows: Iterator[tuple]) -> Iterator[bytes]:
        for key, url, payload, first in rows:
            payload = payload or b""
            legacy = arc_record(NO_URL if url is None else quote(url, safe=_URL_SAFE), payload, date=date, version=arc_version)
            for record in parse_arc(legacy, version=arc_version):
                extra = {"Record-Key": "" if key is None else str(key), "WARC-Payload-Length": str(len(payload))}
                own = digest(payload)
                if first is not None:
                    extra["Refers-To-Key"] = str(first)
                yield arc_to_warc(record, own_id=keyed_id(key, own), refers_to=None if first is None else keyed_id(first, own), extra=extra, http=False).to_bytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _chunks(convert(row for batch in batches for row in zip(*(c.to_pylist() for c in batch.columns), strict=True)), file_bytes)

    _save(rows.mapInArrow(run, "value binary"), path)


def _chunks(records: Iterator[bytes], file_bytes: int) -> Iterator[pa.RecordBatch]:
    """Records joined to rows of a part of a file each."""
    held, size = [], 0
    for record in records:
        if held and size + len(record) > file_bytes // FILE_CHUNKS:
            yield _row(held)
            held, size = [], 0
        held.append(record)
        size += len(record)
    if held:
        yield _row(held)


def _row(records: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([b"".join(records)[:-1]], pa.binary())], names=["value"])  # the writer adds the last line feed


#: Characters of a URL that stay as they are; all others, blanks, % and non-ASCII too, are escaped and restored.
_URL_SAFE = "!#$&'()*+,/:;=?@[]~"


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """All records under path: record_key, url, record_type, payload_bytes, payload_digest, refers_to (a key), warc_date, content, record_id, refers_to_id."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0):
                rows, size = [], 0
                for r in parse_warc(_plain(data.as_py())):
                    h = r.headers
                    url = unquote(h.get("WARC-Target-URI", ""))
                    # Length and digest are those of the bytes read; only a revisit, which has none, is taken at its word.
                    length, own = len(r.payload), digest(r.payload)
                    if r.kind == "revisit":
                        length, own = int(h.get("WARC-Payload-Length", 0)), h.get("WARC-Payload-Digest", "").removeprefix("sha1:")
                    elif h.get("WARC-Payload-Digest", f"sha1:{own}") != f"sha1:{own}":
                        raise ValueError(f"payload of {h.get('WARC-Record-ID')} doesn't have its digest")
                    rows.append((
                        h.get("Record-Key") or None, None if url == NO_URL else url, r.kind, length, own, h.get("Refers-To-Key"),
                        h.get("WARC-Date"), r.content, h.get("WARC-Record-ID"), h.get("WARC-Refers-To"),
                    ))
                    size += len(r.content)
                    if size > 8 << 20:
                        yield _batch(rows)
                        rows, size = [], 0
                if rows:
                    yield _batch(rows)

    return files.mapInArrow(parse, "record_key string, url string, record_type string, payload_bytes long, payload_digest string, refers_to string, warc_date string, content binary, record_id string, refers_to_id string")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.string()] * 3 + [pa.int64()] + [pa.string()] * 3 + [pa.binary()] + [pa.string()] * 2
    names = ["record_key", "url", "record_type", "payload_bytes", "payload_digest", "refers_to", "warc_date", "content", "record_id", "refers_to_id"]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def convert_arc_files(spark: SparkSession, source: str, path: str, *, file_bytes: int = FILE_BYTES) -> None:
    """Convert whole ARC files under source to WARC files under path. A file is read by one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _chunks((arc_to_warc(r).to_bytes() for batch in batches for data in batch.column(0) for r in parse_arc(_plain(data.as_py()))), file_bytes)

    files = spark.read.format("binaryFile").load(source).select("content")
    _save(files.mapInArrow(run, "value binary"), path)


def _save(chunks: DataFrame, path: str) -> None:
    writer = chunks.select(F.col("value").cast("string")).write.option("lineSep", "\n").option("compression", "gzip")
    writer.option("maxRecordsPerFile", FILE_CHUNKS).text(path)


def _plain(data: bytes) -> bytes:
    return gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
