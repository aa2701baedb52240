"""WARC archives: a writer, and a sequential reader.

Each record is a gzip member of its own. The reader inflates the bytes of an archive step by step, takes a record's
block by its Content-Length, asks for the two line ends behind it and for the member's end, and compares the
block and payload digests with the block that it read. Payloads that several records share are stored once, in
the record with the largest page_id; the others become revisit records that name it.

Null html: the empty payload. A null page_id counts as the smallest; a group that has no other id is all responses.
Rows that repeat the response's page_id are responses too. A null url is written as urn:none; control characters
in urls are percent-encoded. An empty table gives no archive and an empty result. Further columns aren't archived.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import goes_at_exit, read, saved, shared_dir, small_batches

ARCHIVE_BYTES, BROADCAST_GROUPS, WINDOW = 8 << 20, 50_000, 1 << 16
LINE, END = b"\r\n", b"\r\n\r\n"


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def member(kind: str, record_id: str, url: str, payload_bytes: int, payload_digest: str, payload: bytes, date: str, refers_to: str | None) -> bytes:
    """One record as a gzip member. A revisit's block is the HTTP header alone."""
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % payload_bytes + (payload if kind == "response" else b"")
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{record_id}>", f"WARC-Date: {date}", f"WARC-Target-URI: {url}", f"WARC-Payload-Digest: sha1:{payload_digest}", f"WARC-Block-Digest: sha1:{base32_sha1(block)}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <{refers_to}>"]
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    squeeze = zlib.compressobj(1, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(head).encode() + END + block + END) + squeeze.flush()


def clean_url(url: str | None) -> str:
    if url is None:
        return "urn:none"
    return "".join(c if c > " " and c != "\x7f" else "".join(f"%{b:02X}" for b in c.encode()) for c in url)


@dataclass
class Record:
    headers: dict[str, str]
    http: dict[str, str]
    payload: bytes
    sound: bool


class FormatError(ValueError):
    pass


def fields(lines: list[bytes]) -> dict[str, str]:
    return {k.strip().decode().lower(): v.strip().decode("utf-8", "replace") for k, _, v in (x.partition(b":") for x in lines)}


def records(windows: Iterator[bytes]) -> Iterator[Record]:
    """Reads an archive front to back. Memory: the record at hand, and one window."""
    rest = b""
    done = False
    while True:
        while not rest and not done:
            rest = next(windows, b"")
            done = not rest
        if done:
            return
        inflate, data, need, body = zlib.decompressobj(31), bytearray(), -1, 0
        while not inflate.eof:
            try:
                data += inflate.decompress(rest)
            except zlib.error as e:
                raise FormatError(f"a gzip member is damaged: {e}") from e
            rest = b""
            if need < 0 and (at := data.find(END)) >= 0:
                lines = bytes(data[:at]).split(LINE)
                headers, body = fields(lines[1:]), at + 4
                if not lines[0].startswith(b"WARC/1.") or not headers.get("content-length", "").isdigit():
                    raise FormatError("a record has no version line or length")
                need = body + int(headers["content-length"]) + 4
            if not inflate.eof:
                rest = next(windows, b"")
                if not rest:
                    raise FormatError("the archive ends inside a record")
        rest = inflate.unused_data
        if need < 0 or len(data) != need or data[-4:] != END:
            raise FormatError("a record's length differs from its Content-Length")
        block = bytes(data[body:-4])
        head, _, payload = block.partition(END)
        sound = headers.get("warc-block-digest") == f"sha1:{base32_sha1(block)}"
        if headers.get("warc-type") == "response":
            sound &= headers.get("warc-payload-digest") == f"sha1:{base32_sha1(payload)}"
        yield Record(headers, fields(head.split(LINE)[1:]), payload, sound)


def with_originals(pages: DataFrame, at_least_bytes: int = 0) -> DataFrame:
    """Adds refers_to: the largest page_id of those with this payload, where that is another one; else null.

    Groups of equal payloads are found by digest with map-side combining; only groups of two and more are joined,
    by broadcast if they are few, else by a shuffle whose hot keys Spark splits.
    """
    payload = F.coalesce(F.col("html").cast("binary"), F.lit(b""))
    keyed = pages.select("page_id", "url", payload.alias("payload")).withColumn("sha", F.unhex(F.sha1("payload")))
    shared = keyed.filter(F.length("payload") >= at_least_bytes).groupBy("sha").agg(F.count(F.lit(1)).alias("n"), F.max("page_id").alias("original")).filter("n > 1").select("sha", "original")
    shared = saved(shared, "shared-payloads")
    few = shared.limit(BROADCAST_GROUPS + 1).count() <= BROADCAST_GROUPS
    out = keyed.join(F.broadcast(shared) if few else shared.hint("merge"), "sha", "left")
    out = out.select("page_id", "url", "payload", F.when(~F.col("page_id").eqNullSafe(F.col("original")), F.col("original")).alias("refers_to"))
    return out if few else out.sortWithinPartitions("page_id", "url")  # equal archives if a task is run again


def write_archives(pages: DataFrame, path: str, archive_bytes: int = ARCHIVE_BYTES, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """Writes a record per row of (page_id, url, payload, refers_to). Gives (archive, records, bytes).

    A task writes each archive under a name of its attempt and renames it when complete, so that a lost or repeated
    task leaves no half archive behind.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = pafs.FileSystem.from_uri(path)
        fs.create_dir(base, recursive=True)
        part, mark = TaskContext.get().partitionId(), uuid.uuid4().hex
        number = row = 0
        made: list[tuple[str, int, int]] = []
        out, n, size = None, 0, 0

        def close() -> None:
            nonlocal out, n, size, number
            out.close()
            name = f"part-{part:06d}-{number:05d}.warc.gz"
            fs.move(f"{base}/.{mark}", f"{base}/{name}")
            made.append((name, n, size))
            out, n, size, number = None, 0, 0, number + 1

        for b in batches:
            for page, url, payload, other in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), b.column(3).to_pylist(), strict=True):
                data = payload.as_buffer().to_pybytes()
                row += 1
                name = f"urn:page:{page}" if page is not None else f"urn:page:none-{part}-{row}"
                bytes_ = member("response" if other is None else "revisit", name, clean_url(url), len(data), base32_sha1(data), data, date, None if other is None else f"urn:page:{other}")
                out = out or fs.open_output_stream(f"{base}/.{mark}")
                out.write(bytes_)
                n, size = n + 1, size + len(bytes_)
                if size >= archive_bytes:
                    close()
        if out:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([m[0] for m in made], pa.string()), pa.array([m[1] for m in made], pa.int64()), pa.array([m[2] for m in made], pa.int64())], ["archive", "records", "bytes"])

    return small_batches(pages).select("page_id", "url", "payload", "refers_to").mapInArrow(run, "archive string, records long, bytes long")


def read_archives(spark: SparkSession, path: str, payloads: bool = False) -> DataFrame:
    """Every record of every archive in path: page_id, url, record_type, payload_bytes, payload_digest, refers_to, sound, and the payload if asked for."""
    schema = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, sound boolean" + ", payload binary" * payloads
    kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.bool_()] + [pa.binary()] * payloads
    names = [x.split()[0] for x in schema.split(", ")]

    def page(uri: str) -> int | None:
        last = uri.strip("<>").rpartition(":")[2]
        return int(last) if last.lstrip("-").isdigit() else None

    def rows(content: memoryview) -> Iterator[tuple]:
        for r in records(bytes(content[i : i + WINDOW]) for i in range(0, len(content), WINDOW)):
            h = r.headers
            other = page(h["warc-refers-to"]) if "warc-refers-to" in h else None
            out = (page(h["warc-record-id"]), h.get("warc-target-uri"), h["warc-type"], int(r.http.get("content-length", len(r.payload))), h["warc-payload-digest"].removeprefix("sha1:"), other, r.sound)
            yield (*out, r.payload) if payloads else out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                held, size = [], 0
                for r in rows(memoryview(content.as_buffer())):
                    held.append(r)
                    size += r[3] if payloads else 0
                    if len(held) >= 4096 or size > 32 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)
                        held, size = [], 0
                if held:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(path)
    return files.select("content").mapInArrow(run, schema)


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    goes_at_exit(spark, path)
    manifest = saved(write_archives(with_originals(read(spark, sf_dir, "pages")), path), "warc-manifest")
    found = manifest.agg(F.sum("records")).first()[0]
    if not found:
        return spark.createDataFrame([], "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, sound boolean")
    return read_archives(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "sound")
