"""WARC normaliser: one gzip stream around a whole file becomes a member for each record, with a sidecar index of offsets.

The file is read and inflated once, in bounded pieces, and never held whole; only the record at hand is, whose header may have HEAD_LIMIT bytes.  Each record is deflated as a member of its own, so that
a reader can seek to `offset` and inflate `length` bytes.  The sidecar lists the same as tab-separated text next to the new file.  A file is one
task; a task writes under a temporary name and renames, so a repeated attempt leaves one whole file.  Paths may be of any file system that
pyarrow opens.

Definitions for odd input.  An empty file gives no record.  A file that ends early, or holds a broken header, gives its whole records, then one index row with
status `broken` and no length.  Input that already has several members is accepted.  Null urls and pages become empty header values and payloads.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from itertools import islice

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import work_path

PIECE = 1 << 20
#: Bytes that a record's header may have; a longer one is broken.
HEAD_LIMIT = 1 << 20
#: Index rows in a batch.
INDEX_ROWS = 10_000
LEVEL = 6
HEAD_END = b"\r\n\r\n"
INDEX = "file string, nth bigint, page_id bigint, url string, offset bigint, length bigint, payload_bytes bigint, payload_md5 string, status string"


def opened(path: str) -> tuple[fs.FileSystem, str]:
    if path.startswith("file:/") and not path.startswith("file://"):
        path = path[5:]
    return fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")


def record(page_id: int | None, url: str | None, html: str | None) -> bytes:
    body = (html or "").encode("utf-8", "replace")
    head = f"WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>\r\nWARC-Target-URI: {(url or '').replace(chr(13), ' ').replace(chr(10), ' ')}\r\nContent-Type: text/html\r\nContent-Length: {len(body)}\r\n\r\n"
    return head.encode() + body + HEAD_END


class Inflater:
    """Reads a gzip file of one or many members as one stream, in pieces of at most PIECE inflated bytes."""

    def __init__(self, source) -> None:
        self.source, self.z, self.buffer, self.over, self.failed, self.started = source, zlib.decompressobj(31), bytearray(), False, False, False
        self.raw = b""

    def more(self) -> bool:
        """Inflates one piece more; False at the end."""
        while not self.over:
            if self.z.eof and self.raw:
                self.z = zlib.decompressobj(31)
            if not self.raw:
                self.raw = self.source.read(PIECE)
                if not self.raw:
                    self.over = True
                    self.failed |= not self.z.eof and self.started
                    return False
                if self.z.eof:
                    continue
            self.started = True
            try:
                got = self.z.decompress(self.raw, PIECE)
            except zlib.error:
                self.over = self.failed = True
                return False
            self.raw = self.z.unused_data if self.z.eof else self.z.unconsumed_tail
            if got:
                self.buffer += got
                return True
        return False

    def until(self, mark: bytes, limit: int) -> bytes | None:
        """All up to the mark; None at the end of the file, or where the mark does not come within the limit."""
        seen = 0
        while (at := self.buffer.find(mark, seen)) < 0:
            seen = max(0, len(self.buffer) - len(mark) + 1)
            if len(self.buffer) > limit:
                self.failed = True
                return None
            if not self.more():
                return None
        return self.take(at + len(mark))

    def take(self, n: int) -> bytes | None:
        while len(self.buffer) < n:
            if not self.more():
                return None
        out = bytes(memoryview(self.buffer)[:n])
        del self.buffer[:n]
        return out


def records(source) -> Iterator[tuple[dict[str, str], bytes, bytes] | None]:
    """(header fields, header bytes, payload) of each record; None, last, where the file is broken."""
    z = Inflater(source)
    while True:
        head = z.until(HEAD_END, HEAD_LIMIT)
        if head is None:
            if z.buffer.strip() or z.failed:
                yield None
            return
        lines = head[:-4].decode("utf-8", "replace").split("\r\n")
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = fields.get("content-length", "")
        body = z.take(int(size)) if lines[0].startswith("WARC/") and size.isdigit() else None
        if body is None or z.take(4) is None:
            yield None
            return
        yield fields, head, body


def member(data: bytes) -> bytes:
    z = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def normalise(path: str, target: str) -> Iterator[tuple]:
    """Rewrites one file as target, and target.idx beside it; gives the rows of INDEX as they are written.  The files have their names once all is read."""
    source_fs, source_path = opened(path)
    target_fs, target_path = opened(target)
    name, temporary, at, nth = target_path.rsplit("/", 1)[-1], f"{target_path}.{uuid.uuid4().hex}", 0, 0
    with source_fs.open_input_stream(source_path, compression=None) as source, target_fs.open_output_stream(temporary, compression=None) as sink, target_fs.open_output_stream(f"{temporary}.idx", compression=None) as index:
        for found in records(source):
            if found is None:
                row = (name, nth, None, None, at, None, None, None, "broken")
            else:
                fields, head, body = found
                data = member(head + body + HEAD_END)
                sink.write(data)
                page = fields.get("warc-record-id", "").removeprefix("<urn:page:").removesuffix(">")
                row = (name, nth, int(page) if re.fullmatch(r"-?[0-9]{1,18}", page) else None, fields.get("warc-target-uri") or None, at, len(data), len(body), hashlib.md5(body).hexdigest(), "whole")
                at += len(data)
                nth += 1
            index.write(("\t".join("" if x is None else str(x).replace("\t", " ") for x in row) + "\n").encode())
            yield row
    target_fs.move(temporary, target_path)
    target_fs.move(f"{temporary}.idx", f"{target_path}.idx")


def write_monolithic(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(path, records): writes each partition of pages as one WARC file inside one gzip stream; lazy."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        path = f"{folder}/part-{part:06d}.warc.gz"
        where, target = opened(path)
        temporary, n, z = f"{target}.{uuid.uuid4().hex}", 0, zlib.compressobj(1, zlib.DEFLATED, 31)
        with where.open_output_stream(temporary, compression=None) as sink:
            for b in batches:
                for i, u, h in zip(*(b.column(c).to_pylist() for c in ("page_id", "url", "html"))):
                    sink.write(z.compress(record(i, u, h)))
                    n += 1
            sink.write(z.flush())
        where.move(temporary, target)
        yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([n], pa.int64())], ["path", "records"])

    slim = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return slim.mapInArrow(run, "path string, records bigint")


def normalise_files(spark: SparkSession, paths: list[str], folder: str) -> DataFrame:
    """The index rows of all files; each file becomes folder/<its name>."""
    where, target = opened(folder)
    where.create_dir(target, recursive=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("file", pa.string()), ("nth", pa.int64()), ("page_id", pa.int64()), ("url", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("payload_bytes", pa.int64()), ("payload_md5", pa.string()), ("status", pa.string())])
        for b in batches:
            for path in b.column(0).to_pylist():
                rows = normalise(path, f"{folder}/{path.rsplit('/', 1)[-1]}")
                while some := list(islice(rows, INDEX_ROWS)):
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*some), schema)], schema=schema)

    files = spark.createDataFrame([(p,) for p in paths], "path string")
    return files.repartition(max(1, len(paths)), "path").mapInArrow(run, INDEX)


def normalised_pages(pages: DataFrame) -> DataFrame:
    """Writes pages as monolithic files in the shared folder, normalises these, and gives the index of all records."""
    spark = pages.sparkSession
    raw, new = work_path(spark, "warc-monolithic"), work_path(spark, "warc-members")
    where, target = opened(raw)
    where.create_dir(target, recursive=True)
    paths = [r["path"] for r in write_monolithic(pages, raw).select("path").collect()]
    return normalise_files(spark, sorted(paths), new)
