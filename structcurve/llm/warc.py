"""WARC archives: written by the executors to shared storage, read back as rows of payload chunks."""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, shared_dir, text_of, written

CHUNK_SCHEMA = "page_id bigint, record_id string, url string, record_type string, refers_to bigint, chunk_no int, chunk_bytes int, bytes_so_far bigint, digest_so_far string, last boolean, declared_bytes bigint, declared_digest string, chunk binary"
#: High halves of the record ids (an id of the page follows) and the profile of a revisit: fixed values.
_PAGE, _NO_PAGE = 0x5C17E000_0000_4000, 0x5C17E001_0000_4000
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def base32(hex_digest: str) -> str:
    return base64.b32encode(bytes.fromhex(hex_digest)).decode()


def record_id(page_id: int | None) -> str:
    return f"<{uuid.UUID(int=(_NO_PAGE if page_id is None else _PAGE) << 64 | ((page_id or 0) & (1 << 64) - 1)).urn}>"


def page_of(text: str) -> int | None:
    value = uuid.UUID(text.strip("<>")).int
    low = value & (1 << 64) - 1
    return None if value >> 64 == _NO_PAGE else low - (1 << 64 if low >> 63 else 0)


def _header_text(url: str) -> str:
    return "".join(c if c > " " and c != "\x7f" else "".join(f"%{b:02X}" for b in c.encode()) for c in url)


def record_head(page_id: int | None, url: str, first: int | None, size: int, digest: str) -> bytes:
    """All of a record that comes before the payload; a revisit keeps the HTTP header and no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    lines = ["WARC/1.1", f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Target-URI: {_header_text(url)}", f"WARC-Payload-Digest: sha1:{digest}"]
    if first is not None:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(first)}"]
    lines += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(http) + (size if first is None else 0)}"]
    return "\r\n".join([*lines, "", ""]).encode() + http


class ArchiveWriter:
    """Records as gzip members, written piece by piece; a new archive starts beyond ``limit`` bytes."""

    def __init__(self, where: str, limit: int, chunk: int):
        self.files, self.root = fs.FileSystem.from_uri(where)
        self.limit, self.chunk = limit, chunk
        self.out = self.path = None
        self.records = self.size = 0
        self.done: list[tuple[str, int, int]] = []

    def add(self, head: bytes, payload: memoryview) -> None:
        if self.out is None:
            self.path = f"{self.root}/{uuid.uuid4().hex}.warc.gz"
            self.out = self.files.open_output_stream(self.path)
        packer = zlib.compressobj(1, zlib.DEFLATED, 31)
        pieces = [head, *(payload[i : i + self.chunk] for i in range(0, len(payload), self.chunk)), b"\r\n\r\n"]
        for piece in pieces:
            self._put(packer.compress(piece))
        self._put(packer.flush())
        self.records += 1
        if self.size >= self.limit:
            self.close()

    def _put(self, data: bytes) -> None:
        self.out.write(data)
        self.size += len(data)

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            self.done.append((self.path, self.records, self.size))
        self.out, self.records, self.size = None, 0, 0


def read_chunks(stream: io.BufferedIOBase, chunk: int, keep: bool) -> Iterator[tuple]:
    """Rows of one archive in CHUNK_SCHEMA's order; only one chunk of a payload is in memory at a time."""
    data = io.BufferedReader(gzip.GzipFile(fileobj=stream), 1 << 17)
    while True:
        version = data.readline()
        if not version:
            return
        if not version.startswith(b"WARC/"):
            raise ValueError("not a WARC record")
        head = _headers(data)
        left = int(head["content-length"])
        before = left
        status = data.readline()
        http: dict[str, str] = {}
        left -= len(status)
        while left > 0:
            line = data.readline()
            left -= len(line)
            if line in (b"\r\n", b"\n", b""):
                break
            name, _, value = line.partition(b":")
            http[name.decode().strip().lower()] = value.decode().strip()
        assert 0 <= left <= before
        kind = head["warc-type"]
        refers = page_of(head["warc-refers-to"]) if "warc-refers-to" in head else None
        fixed = (page_of(head["warc-record-id"]), head["warc-record-id"], head.get("warc-target-uri"), kind, refers)
        declared = int(http.get("content-length", left)), head.get("warc-payload-digest", "").rpartition(":")[2]
        sha, number, seen = hashlib.sha1(), 0, 0
        while True:
            piece = data.read(min(chunk, left))
            if left and not piece:
                raise ValueError("archive ends inside a record")
            left -= len(piece)
            seen += len(piece)
            sha.update(piece)
            yield (*fixed, number, len(piece), seen, base64.b32encode(sha.digest()).decode(), left == 0, *declared, piece if keep else None)
            number += 1
            if not left:
                break
        if data.read(4) != b"\r\n\r\n":
            raise ValueError("record is not closed")


def _headers(data: io.BufferedReader) -> dict[str, str]:
    out: dict[str, str] = {}
    while (line := data.readline()) not in (b"\r\n", b"\n", b""):
        name, _, value = line.decode().partition(":")
        out[name.strip().lower()] = value.strip()
    return out


def write_archives(pages: DataFrame, where: str | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_bytes: int = 0, archive_bytes: int = 64 << 20, chunk_bytes: int = 1 << 20) -> DataFrame:
    """Write one record per page and return the manifest ``(path, records, bytes)``, itself written once.

    Of pages with equal payloads of at least ``min_bytes`` bytes the smallest id is the response, the
    others are revisits of it; rows that repeat that id, and rows without an id, are responses.  Null
    html is an empty payload.  Equal payloads are found by SHA-1 in Catalyst on ids and digests alone;
    the payloads travel once, by page id, so a payload that many pages share makes no large partition.  An archive is
    named at random and counts only if its task's manifest row was kept, so a task that runs again
    leaves at worst an archive that nobody reads.
    """
    spark = pages.sparkSession
    where = where or f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    where = where if "://" in where else f"file://{where}"
    spark._jvm.org.apache.hadoop.fs.Path(where).getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(spark._jvm.org.apache.hadoop.fs.Path(where))
    rows = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), text_of(html_col).alias("html")).withColumn("sha1", F.sha1(F.col("html").cast("binary")))
    light = rows.select("page_id", "sha1", F.octet_length("html").alias("size")).where(F.col("page_id").isNotNull() & (F.col("size") >= min_bytes))
    firsts = light.groupBy("sha1").agg(F.min("page_id").alias("first"), F.max("page_id").alias("_last")).where("_last > first").select("sha1", "first")
    revisits = light.join(firsts, "sha1").where("page_id > first").select("page_id", "sha1", "first").distinct()
    ready = rows.join(revisits, ["page_id", "sha1"], "left").select("page_id", "url", "html", "sha1", "first")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer = ArchiveWriter(where, archive_bytes, chunk_bytes)
        for batch in batches:
            for page_id, url, html, sha1, first in zip(*(batch.column(i) for i in range(5))):
                payload = memoryview(html.as_buffer()) if html.as_buffer() is not None else memoryview(b"")
                first = first.as_py()
                head = record_head(page_id.as_py(), url.as_py(), first, len(payload), base32(sha1.as_py()))
                writer.add(head, payload if first is None else memoryview(b""))
        writer.close()
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in writer.done], pa.string()), pa.array([d[1] for d in writer.done], pa.int64()), pa.array([d[2] for d in writer.done], pa.int64())], ["path", "records", "bytes"])

    scheme = where.split("://")[0]
    manifest = arrow_map(ready, run, "path string, records bigint, bytes bigint")
    return written(manifest.withColumn("path", F.concat(F.lit(f"{scheme}://"), "path")), "warc-manifest")


def read_archives(spark: SparkSession, manifest: DataFrame, chunk_bytes: int = 1 << 20, keep: bool = True) -> DataFrame:
    """The chunked record table of the archives in ``manifest.path``, one archive per task.

    A record of n bytes gives max(1, ceil(n / chunk_bytes)) rows, numbered from 0, each with the SHA-1 of
    the payload up to its end; ``keep`` says whether the chunks' bytes leave the worker.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.bool_(), pa.int64(), pa.string(), pa.binary())
        names = [f.split()[0] for f in CHUNK_SCHEMA.split(", ")]
        batch_of = lambda rows: pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)
        for batch in batches:
            for path in batch.column(0).to_pylist():
                files, name = fs.FileSystem.from_uri(path)
                with files.open_input_stream(name) as stream:
                    rows, size = [], 0
                    for row in read_chunks(stream, chunk_bytes, keep):
                        rows.append(row)
                        size += row[6] if keep else 0
                        if len(rows) >= 2000 or size >= 8 << 20:
                            yield batch_of(rows)
                            rows, size = [], 0
                    yield batch_of(rows)

    return arrow_map(manifest.select("path").repartition(max(1, manifest.count())), run, CHUNK_SCHEMA)


def records_of(chunks: DataFrame) -> DataFrame:
    """One row per record, from its last chunk: a response's size and digest are those read back, and must be
    those declared; a revisit has the declared ones of the payload that it stands for."""
    own = F.col("record_type") == "response"
    return chunks.where("last").select(
        "page_id",
        F.when(own, F.col("bytes_so_far")).otherwise(F.col("declared_bytes")).alias("payload_bytes"),
        F.when(own, F.col("digest_so_far")).otherwise(F.col("declared_digest")).alias("payload_digest"),
        "record_type",
        "refers_to",
        (~own | ((F.col("bytes_so_far") == F.col("declared_bytes")) & (F.col("digest_so_far") == F.col("declared_digest")))).alias("verified"),
    )
