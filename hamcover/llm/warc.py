"""WARC archives: a writer, and a reader that splits compressed files by byte ranges.

Each record is a gzip member of its own. A reading task gets a range of bytes, looks for the magic bytes of gzip,
and takes a place for a record only if the member there decodes to a WARC header of this very archive (records name their archive's id, so members inside of payloads don't count).
It owns the records that start in its range, and reads the last of them to its end, wherever that is; from a record on it follows
the members one by one, and looks for magic bytes again where one is damaged.

Archives go to the store that driver and executors share, through pyarrow's file systems. A task that is run again writes
files of new names; only files of tasks that ended are in the manifest, so lost executors leave no record twice.

Records of equal payload (SHA-1 and length): the one with the largest page_id is a response, the others are revisits that
refer to it and hold its HTTP header without the payload. Which digests repeat is found by a partial aggregation; only they are joined
back, so a payload that a third of all pages share costs one row of the small side, and Spark can split the large side.

Defined results: a null html is an empty payload; a null url has no target header; line breaks and other control characters in a url are
percent-encoded; a null page_id gives a record with no number, which is never the one referred to while a page with a number has
that payload; repeated rows of the largest page_id are all responses; no pages give no archives; other columns are not looked at.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.common import shared_dir, written

ARCHIVE_BYTES = 256 << 20
RANGE_BYTES = 16 << 20
#: Payloads of so many bytes at least are compared.
MIN_REVISIT = 0
MAGIC = b"\x1f\x8b\x08"
_DATE = "2000-01-01T00:00:00Z"
#: The profile of revisits with an identical payload: a fixed value of the format.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORDS = "archive string, offset bigint, record_type string, page_id bigint, refers_to bigint, target_uri string, payload_digest string, payload_bytes bigint, digest_ok boolean, payload binary"


def base32_sha1(data: Column) -> Column:
    """Upper-case base32 of the SHA-1 of binary data, by Spark expressions: ten hex digits make eight base32 digits."""
    digits = F.concat(*(F.lpad(F.conv(F.substring(F.sha1(data), 10 * k + 1, 10), 16, 32), 8, "0") for k in range(4)))
    return F.translate(digits, "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def with_revisits(pages: DataFrame, min_revisit: int = MIN_REVISIT) -> DataFrame:
    """page_id, url, payload, digest, refers_to: null for responses."""
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("digest", base32_sha1(F.col("payload")))
    large = rows.where(F.length("payload") >= min_revisit)
    repeated = written(large.groupBy("digest").agg(F.max("page_id").alias("largest"), F.count("*").alias("n")).where("n > 1").select("digest", "largest"), "warc-repeated")
    joined = rows.join(repeated, "digest", "left")
    refers = F.when(F.col("largest").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("largest")), F.col("largest"))
    return joined.select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def _urn(page_id: int | None) -> str:
    return f"<urn:x-page:{'' if page_id is None else page_id}>"


def _record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", str(len(block)))])
    squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
    return squeeze.compress(b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n") + squeeze.flush()


def _page_record(archive: str, page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    kind = "response" if refers_to is None else "revisit"
    fields = [("WARC-Type", kind), ("WARC-Record-ID", _urn(page_id)), ("WARC-Date", _DATE), ("WARC-Warcinfo-ID", f"<urn:uuid:{archive}>")]
    if url is not None:
        fields.append(("WARC-Target-URI", re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)))
    if refers_to is not None:
        fields += [("WARC-Refers-To", _urn(refers_to)), ("WARC-Profile", PROFILE)]
    fields += [("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    return _record(fields, http + (payload if refers_to is None else b""))


def write_archives(rows: DataFrame, folder: str, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Writes the rows of with_revisits() and returns the manifest: archive, bytes, records."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, base = fs.FileSystem.from_uri(folder)
        system.create_dir(base, recursive=True)
        out, name, size, n, made = None, "", 0, 0, []
        for whole in it:
            for row in (r for i in range(0, whole.num_rows, 256) for r in whole.slice(i, 256).to_pylist()):
                if out is None:
                    archive = str(uuid.uuid4())
                    name, n = f"pages-{archive}.warc.gz", 0
                    out = system.open_output_stream(f"{base}/{name}", compression=None)
                    head = _record([("WARC-Type", "warcinfo"), ("WARC-Record-ID", f"<urn:uuid:{archive}>"), ("WARC-Date", _DATE), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n")
                    out.write(head)
                    size = len(head)
                data = _page_record(archive, row["page_id"], row["url"], row["payload"], row["digest"], row["refers_to"])
                out.write(data)
                size, n = size + len(data), n + 1
                if size >= archive_bytes:
                    out.close()
                    made.append((f"{folder}/{name}", size, n))
                    out = None
        if out is not None:
            out.close()
            made.append((f"{folder}/{name}", size, n))
        if made:
            yield pa.RecordBatch.from_arrays([pa.array([m[k] for m in made], t) for k, t in enumerate((pa.string(), pa.int64(), pa.int64()))], names=["archive", "bytes", "records"])

    return written(rows.mapInArrow(run, "archive string, bytes bigint, records bigint"), "warc-manifest")


class _File:
    """Bytes of a file by place, read ahead in blocks."""

    def __init__(self, path: str, ahead: int = 1 << 20):
        system, name = fs.FileSystem.from_uri(path)
        self.file, self.ahead = system.open_input_file(name), ahead
        self.at, self.data = 0, b""

    def read(self, at: int) -> bytes:
        """Some bytes from `at` on; none at the end."""
        if not self.at <= at < self.at + len(self.data):
            self.file.seek(at)
            self.at, self.data = at, self.file.read(self.ahead)
        return self.data[at - self.at :]

    def close(self) -> None:
        self.file.close()


def _find(file: _File, at: int, end: int) -> int | None:
    """The first place in [at, end) with the magic bytes."""
    while at < end:
        data = file.read(at)
        if not data:
            return None
        if len(data) < len(MAGIC):  # they may go on in the next block
            file.file.seek(at)
            file.at, file.data = at, file.file.read(file.ahead)
            data = file.data
            if len(data) < len(MAGIC):
                return None
        k = data.find(MAGIC)
        if k >= 0:
            return at + k if at + k < end else None
        at += len(data) - len(MAGIC) + 1
    return None


def _member(file: _File, at: int) -> tuple[bytes, int] | None:
    """Contents and end of the gzip member at a place, if it is whole and begins as a WARC record does."""
    d, parts, seen = zlib.decompressobj(31), [], 0
    step = 4096
    while not d.eof:
        data = file.read(at)[:step]
        if not data:
            return None
        try:
            out = d.decompress(data)
        except zlib.error:
            return None
        parts.append(out)
        if seen < 7:
            seen += len(out)
            if seen >= 7 and not b"".join(parts).startswith(b"WARC/1."):
                return None
        at += len(data) - len(d.unused_data)
        step = 1 << 18
    return b"".join(parts), at


def _parse(data: bytes, archive: str) -> dict | None:
    head, gap, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in lines[1:])}
    if not gap or not lines[0].startswith("WARC/1.") or "warc-type" not in fields or not fields.get("content-length", "").isdigit():
        return None
    own = re.search(r"([0-9a-f]{8}(?:-[0-9a-f]{4}){3}-[0-9a-f]{12})\.warc\.gz$", archive)
    if own and own[1] not in (fields.get("warc-warcinfo-id", "") or fields.get("warc-record-id", "")):
        return None
    n = int(fields["content-length"])
    if len(rest) < n:
        return None
    return fields | {"block": rest[:n]}


def _number(urn: str | None) -> int | None:
    m = re.fullmatch(r"<urn:x-page:(-?\d+)>", urn or "")
    return int(m[1]) if m else None


def range_records(archive: str, start: int, end: int) -> Iterator[dict]:
    """The page records that start in [start, end) of an archive, in order."""
    file = _File(archive)
    try:
        at = _find(file, start, end)
        while at is not None:
            member = _member(file, at)
            fields = _parse(member[0], archive) if member else None
            if fields is None:
                at = _find(file, at + 1, end)
                continue
            if fields["warc-type"] in ("response", "revisit"):
                yield _as_row(archive, at, fields)
            at = _find(file, member[1], end)
    finally:
        file.close()


def _as_row(archive: str, at: int, fields: dict) -> dict:
    http, _, payload = fields["block"].partition(b"\r\n\r\n")
    digest = fields.get("warc-payload-digest", "").removeprefix("sha1:")
    full = fields["warc-type"] == "response"
    length = re.search(rb"(?im)^content-length:\s*(\d+)", http)
    return {
        "archive": archive,
        "offset": at,
        "record_type": fields["warc-type"],
        "page_id": _number(fields.get("warc-record-id")),
        "refers_to": _number(fields.get("warc-refers-to")),
        "target_uri": fields.get("warc-target-uri"),
        "payload_digest": base64.b32encode(hashlib.sha1(payload).digest()).decode() if full else digest,
        "payload_bytes": len(payload) if full else int(length[1]) if length else None,
        "digest_ok": base64.b32encode(hashlib.sha1(payload).digest()).decode() == digest if full else None,
        "payload": payload,
    }


def read_archives(manifest: DataFrame, payloads: bool = True, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Page records of all archives of a manifest (archive, bytes), read in ranges of bytes. Payloads of revisits are empty."""
    ranges = manifest.select("archive", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("bytes") - 1, F.lit(0)), F.lit(range_bytes).cast("long"))).alias("start"))
    n = max(1, min(ranges.count(), 100_000))
    columns = RECORDS if payloads else RECORDS.removesuffix(", payload binary")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for row in batch.to_pylist():
                rows, size = [], 0
                for record in range_records(row["archive"], row["start"], row["start"] + range_bytes):
                    if not payloads:
                        del record["payload"]
                    rows.append(record)
                    size += len(record.get("payload", b""))
                    if len(rows) >= 1000 or size >= 8 << 20:
                        yield pa.RecordBatch.from_pylist(rows, schema=arrow)
                        rows, size = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    arrow = _arrow_schema(columns)
    return ranges.repartition(n).mapInArrow(run, columns)


def _arrow_schema(ddl: str) -> pa.Schema:
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(T._parse_datatype_string(ddl))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    manifest = write_archives(with_revisits(pages), shared_dir(spark, "warc"))
    return read_archives(manifest, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "digest_ok")


QUERIES = {"op3_warc": op3_warc}
ORACLES = {
    "op3_warc": r"""
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(encode(coalesce(html, ''))) AS h FROM pages
), q AS (
  SELECT *, max(page_id) OVER (PARTITION BY h, payload_bytes) AS largest FROM p
)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes,
  (SELECT string_agg(substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(h, 1 + 10 * (i // 8), 10) AS BIGINT) >> (35 - 5 * (i % 8))) & 31 AS INT) + 1, 1), '' ORDER BY i) FROM range(32) t(i)) AS payload_digest,
  CASE WHEN page_id = largest THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> largest THEN largest END AS refers_to,
  CASE WHEN page_id = largest THEN true END AS digest_ok
FROM q
"""
}
