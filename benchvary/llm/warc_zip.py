"""WARC records in ZIP archives: writing, and reading by range without extraction.

Each archive holds stored (uncompressed) members: segments of WARC records, gzip-compressed one by one, and an index
of their offsets. The reader parses the end records (ZIP64 ones too), the central directory and local headers, finds
the index, and fetches each record by one range of the archive.

Archives are written by tasks into a folder that all executors share, under names that no other attempt uses; only
archives listed in the written manifest count, so a repeated task leaves at worst an unlisted file.

Defined results: a null payload counts as empty; of records with equal payloads that have at least least_bytes the one
with the largest id is a response and the others revisit it, smaller ones are all responses; of rows with equal id and
payload one is the response and the rest revisit it; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import json
import struct
import uuid
import zipfile
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.session import materialize, scratch_path

#: Bytes of compressed records in an archive, about, and in a segment inside it.
ARCHIVE_BYTES = 32 << 20
SEGMENT_BYTES = 8 << 20
INDEX_NAME = "index.jsonl"
_CRLF = b"\r\n"


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def warc_record(kind: str, uri: str, record_id: str, digest: str, payload: bytes, size: int, refers_to: str | None = None) -> bytes:
    """One WARC/1.1 record; a revisit has no block. size: bytes of the whole payload."""
    body = payload if kind == "response" else b""
    head = [
        b"WARC/1.1",
        b"WARC-Type: " + kind.encode(),
        b"WARC-Record-ID: <" + record_id.encode() + b">",
        b"WARC-Target-URI: " + uri.encode().replace(b"\r", b"%0D").replace(b"\n", b"%0A"),
        b"WARC-Date: 1970-01-01T00:00:00Z",
        b"WARC-Payload-Digest: sha1:" + digest.encode(),
        b"X-Payload-Length: %d" % size,
    ]
    if refers_to is not None:
        head += [b"WARC-Refers-To: <" + refers_to.encode() + b">", b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head.append(b"Content-Length: %d" % len(body))
    return _CRLF.join(head) + _CRLF * 2 + body + _CRLF * 2


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers (lower-case names) and block of one record."""
    head, _, rest = raw.partition(_CRLF * 2)
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    return fields, rest[: int(fields["content-length"])]


class ZipDirectory:
    """Names, offsets and sizes of the members of a ZIP archive, read through fetch(offset, length)."""

    def __init__(self, fetch, size: int):
        self.fetch, self.members = fetch, {}
        tail_at = max(0, size - (1 << 16) - 22)
        tail = fetch(tail_at, size - tail_at)
        at = tail.rfind(b"PK\x05\x06")
        if at < 0:
            raise ValueError("no end of central directory")
        count, length, start = struct.unpack("<H2I", tail[at + 10 : at + 20])
        mark, _, where, _ = struct.unpack("<4sIQI", fetch(tail_at + at - 20, 20)) if tail_at + at >= 20 else (b"", 0, 0, 0)
        if mark != b"PK\x06\x07" and 0xFFFFFFFF in (length, start):
            raise ValueError("no ZIP64 locator")
        if mark == b"PK\x06\x07" and (count == 0xFFFF or 0xFFFFFFFF in (length, start)):
            end = fetch(where, 56)
            if end[:4] != b"PK\x06\x06":
                raise ValueError("no ZIP64 end record")
            count, length, start = struct.unpack("<3Q", end[32:56])
        directory = fetch(start, length)
        at = 0
        for _ in range(count):
            mark, _, _, flags, method, _, _, crc, packed, full, n_name, n_extra, n_note, _, _, _, offset = struct.unpack("<4s6H3I5H2I", directory[at : at + 46])
            if mark != b"PK\x01\x02":
                raise ValueError("broken central directory")
            name = directory[at + 46 : at + 46 + n_name].decode("utf-8")
            extra = directory[at + 46 + n_name : at + 46 + n_name + n_extra]
            k = 0
            while k + 4 <= len(extra):
                tag, n = struct.unpack("<2H", extra[k : k + 4])
                if tag == 1:
                    wide = [v for (v,) in struct.iter_unpack("<Q", extra[k + 4 : k + 4 + n - n % 8])]
                    if full == 0xFFFFFFFF:
                        full = wide.pop(0)
                    if packed == 0xFFFFFFFF:
                        packed = wide.pop(0)
                    if offset == 0xFFFFFFFF:
                        offset = wide.pop(0)
                k += 4 + n
            if method == 0 and not flags & 1:  # stored and not encrypted: ranges of the archive are ranges of the member
                self.members[name] = (offset, full, crc)
            at += 46 + n_name + n_extra + n_note

    def start(self, name: str) -> int:
        """Where a member's bytes begin, behind its local header."""
        offset, _, _ = self.members[name]
        head = self.fetch(offset, 30)
        if head[:4] != b"PK\x03\x04":
            raise ValueError("broken local header")
        n_name, n_extra = struct.unpack("<2H", head[26:30])
        return offset + 30 + n_name + n_extra

    def read(self, name: str) -> bytes:
        _, size, crc = self.members[name]
        body = self.fetch(self.start(name), size)
        if zlib.crc32(body) != crc:
            raise ValueError(f"{name} is damaged")
        return body


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def zip_bytes(segments: list[tuple[str, bytes]], force_zip64: bool = False) -> bytes:
    """An archive of stored members."""
    out = io.BytesIO()
    with zipfile.ZipFile(out, "w", zipfile.ZIP_STORED, allowZip64=True) as z:
        for name, body in segments:
            with z.open(zipfile.ZipInfo(name), "w", force_zip64=force_zip64) as f:
                f.write(body)
    return out.getvalue()


def write_archives(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", least_bytes: int = 0) -> DataFrame:
    """Write one record for each row into archives under folder; the manifest (archive, bytes, records)."""
    body = F.coalesce(F.col(payload_col), F.lit(""))
    slim = pages.select(
        F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col(url_col), F.lit("")).alias("url"), body.alias("html"), F.sha1(body.cast("binary")).alias("digest"), F.octet_length(body).cast("long").alias("size")
    ).withColumn("row_key", F.monotonically_increasing_id())
    # Of each payload the largest id leads; among rows of that id one row does.
    slim = slim.withColumn("lead_key", F.struct(F.coalesce("page_id", F.lit(-(1 << 62))).alias("i"), F.col("row_key").alias("r")))
    lead = slim.where(F.col("size") >= least_bytes).groupBy("digest", "size").agg(F.max("lead_key").alias("lead"))
    rows = slim.join(lead, ["digest", "size"], "left").select(
        "page_id", "url", "html", "size", (F.col("lead").isNotNull() & (F.col("lead") != F.col("lead_key"))).alias("revisit"), F.when(F.col("lead.i") != -(1 << 62), F.col("lead.i")).alias("lead_id")
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filesystem, base = _filesystem(folder)
        segments: list[tuple[str, bytes]] = []
        index: list[str] = []
        segment, total, records = io.BytesIO(), 0, 0

        def close_segment() -> None:
            nonlocal segment
            if segment.tell():
                segments.append((f"records-{len(segments):05d}.warc.gz", segment.getvalue()))
                segment = io.BytesIO()

        def close_archive() -> pa.RecordBatch:
            nonlocal segments, index, total, records
            close_segment()
            raw = zip_bytes([*segments, (INDEX_NAME, "\n".join(index).encode())])
            name = f"{uuid.uuid4().hex}.zip"
            with filesystem.open_output_stream(f"{base}/{name}") as f:
                f.write(raw)
            out = pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"]), pa.array([len(raw)]), pa.array([records])], names=["archive", "bytes", "records"])
            segments, index, total, records = [], [], 0, 0
            return out

        for batch in batches:
            for part in (batch.slice(i, 200) for i in range(0, batch.num_rows, 200)):
                for page, url, html, size, revisit, lead_id in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    payload = html.encode()
                    record_id, refers = (f"urn:page:{x}" for x in (page, lead_id))
                    record = warc_record("revisit" if revisit else "response", url, record_id, payload_digest(payload), payload, size, refers if revisit else None)
                    packed = gzip.compress(record, 1, mtime=0)
                    index.append(json.dumps({"member": f"records-{len(segments):05d}.warc.gz", "offset": segment.tell(), "length": len(packed)}))
                    segment.write(packed)
                    total += len(packed)
                    records += 1
                    if segment.tell() >= SEGMENT_BYTES:
                        close_segment()
                    if total >= ARCHIVE_BYTES:
                        yield close_archive()
        if records:
            yield close_archive()

    spark = pages.sparkSession
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).mkdirs(path)
    return materialize(rows.mapInArrow(run, "archive string, bytes long, records long"), "manifest")


def read_archives(manifest: DataFrame) -> DataFrame:
    """(page_id, url, payload_bytes, payload_digest, record_type, refers_to, payload) of every record, by ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
        to_id = lambda x: None if x is None or x.endswith("None>") else int(x.rpartition(":")[2].rstrip(">"))
        for batch in batches:
            for archive, size in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                filesystem, path = _filesystem(archive)
                with filesystem.open_input_file(path) as f:

                    def fetch(offset: int, length: int, f=f) -> bytes:
                        f.seek(offset)
                        return f.read(length)

                    directory = ZipDirectory(fetch, size)
                    starts = {n: directory.start(n) for n in directory.members}
                    rows: list[tuple] = []
                    for line in directory.read(INDEX_NAME).decode().splitlines():
                        entry = json.loads(line)
                        fields, block = parse_record(gzip.decompress(fetch(starts[entry["member"]] + entry["offset"], entry["length"])))
                        digest = fields["warc-payload-digest"].removeprefix("sha1:")
                        kind = fields["warc-type"]
                        if kind == "response" and payload_digest(block) != digest:
                            raise ValueError(f"{fields['warc-record-id']} is damaged")
                        rows.append((to_id(fields["warc-record-id"]), fields["warc-target-uri"], int(fields["x-payload-length"]), digest, kind, to_id(fields.get("warc-refers-to")), block if kind == "response" else None))
                        if len(rows) >= 200:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)
                            rows = []
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    n = max(1, min(manifest.count(), 10_000))
    return manifest.select("archive", "bytes").repartition(n).mapInArrow(
        run, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    )


def archive_folder(pages: DataFrame) -> str:
    return scratch_path(pages.sparkSession, "archives")
