"""Crawl archives: gzip members that each hold one record; a Python data source reads them, one partition for each file."""

from __future__ import annotations

import gzip
import io
import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "page_id bigint, url string, html string, crawl_ts timestamp, snapshot_ix int, _corrupt string"


def write_record(url: str, html: str, page_id: int, when: str, snapshot: int, kind: str = "response") -> bytes:
    """One gzip member: a record header, a blank line, the HTTP header, a blank line, the body."""
    body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n\r\n" + html.encode("utf-8", "surrogatepass")
    head = f"WARC/1.0\r\nWARC-Type: {kind}\r\nWARC-Target-URI: {url}\r\nWARC-Date: {when}\r\nX-Page-Id: {page_id}\r\nX-Snapshot: {snapshot}\r\nContent-Length: {len(body)}\r\n\r\n"
    return gzip.compress(head.encode() + body + b"\r\n\r\n", mtime=0)


def members(stream) -> Iterator[bytes | None]:
    """Decompressed members one by one; None for a broken rest. Memory holds one member."""
    d, out, fed = zlib.decompressobj(31), io.BytesIO(), False
    block = stream.read(1 << 20)
    while block:
        try:
            out.write(d.decompress(block))
            fed = True
        except zlib.error:
            yield None
            return
        if d.eof:
            yield out.getvalue()
            block = d.unused_data or stream.read(1 << 20)
            d, out, fed = zlib.decompressobj(31), io.BytesIO(), False
        else:
            block = stream.read(1 << 20)
    if fed and out.getvalue():
        yield None


def parse(record: bytes | None) -> tuple | None:
    """A row of SCHEMA; None for records other than responses; malformed ones have only _corrupt."""
    from datetime import datetime, timezone

    if record is None:
        return (None, None, None, None, None, "broken gzip member")
    head, gap, rest = record.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
    if fields.get("WARC-Type", "response") != "response":
        return None
    try:
        payload = rest[: int(fields["Content-Length"])]
        _, gap, body = payload.partition(b"\r\n\r\n")
        when = datetime.strptime(fields["WARC-Date"], "%Y-%m-%dT%H:%M:%SZ").replace(tzinfo=timezone.utc)
        if not gap:
            raise ValueError("no HTTP header")
        return (int(fields["X-Page-Id"]), fields["WARC-Target-URI"], body.decode("utf-8", "replace"), when, int(fields["X-Snapshot"]), None)
    except (KeyError, ValueError) as e:
        return (None, fields.get("WARC-Target-URI"), None, None, None, f"{type(e).__name__}: {e}")


def _open(path: str):
    """A stream of bytes of a file: a plain path, or a URI of a store that pyarrow reads."""
    from pyarrow import fs

    if path.startswith("file:") and not path.startswith("file://"):
        path = "file://" + path[5:]
    store, inner = fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)
    return store.open_input_stream(inner, compression=None)


def _list(pattern: str) -> list[str]:
    """Files of a glob; in a store only the last part may have wildcards."""
    import fnmatch
    import glob

    from pyarrow import fs

    if "://" not in pattern:
        return sorted(glob.glob(pattern))
    folder, _, name = pattern.rpartition("/")
    store, inner = fs.FileSystem.from_uri(folder)
    return sorted(f"{folder}/{i.base_name}" for i in store.get_file_info(fs.FileSelector(inner)) if i.is_file and fnmatch.fnmatch(i.base_name, name))


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class ArchiveReader(DataSourceReader):
    def __init__(self, options):
        self.paths = [p for p in options.get("paths", options.get("path", "")).split(",") if p]

    def partitions(self):
        return [_File(f) for p in self.paths for f in _list(p)]

    def read(self, partition):
        with _open(partition.path) as f:
            for record in members(f):
                row = parse(record)
                if row is not None:
                    yield row


class ArchiveSource(DataSource):
    """format("page_archive"), option path: a glob of files, in a mounted file system or a store that pyarrow reads."""

    @classmethod
    def name(cls):
        return "page_archive"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return ArchiveReader(self.options)


def read_archive(spark: SparkSession, path: str, snapshots: list[int] | None = None, streamed: bool = False) -> DataFrame:
    """Pages of archive files, one task for each file.

    Files come through binaryFile, which reads any store that Spark reads but holds a file as one value of at most 2 GB.
    streamed: only their paths come so, and tasks read them through pyarrow, record by record, whatever their size.
    """
    files = spark.read.format("binaryFile").load(path)
    df = _records(files.select("path") if streamed else files.select("content"))
    return df if snapshots is None else df.filter(F.col("snapshot_ix").isin(snapshots) | F.col("_corrupt").isNotNull())


#: Characters of page that go to Spark at a time.
BATCH_CHARS = 8 << 20


def _records(files: DataFrame) -> DataFrame:
    import pyarrow as pa

    names = [f.split()[0] for f in SCHEMA.split(", ")]
    kinds = [pa.int64(), pa.string(), pa.string(), pa.timestamp("us", "UTC"), pa.int32(), pa.string()]

    def run(batches):
        for b in batches:
            for found in b.column(0):
                rows, held = [], 0
                with (_open(found.as_py()) if pa.types.is_string(found.type) else io.BytesIO(found.as_py())) as stream:
                    for r in map(parse, members(stream)):
                        if r is not None:
                            rows.append(r)
                            held += len(r[2] or "")
                        if held > BATCH_CHARS:
                            yield made(rows)
                            rows, held = [], 0
                yield made(rows)

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    return files.mapInArrow(run, SCHEMA)


def from_pages(pages: DataFrame, key: str = "page_id") -> DataFrame:
    """The given pages with derived crawl columns."""
    from ..operators.dedup import recency

    ix, ts = recency(F.col(key))
    return pages.withColumns({"snapshot_ix": ix, "crawl_ts": ts})


def select_snapshots(df: DataFrame, first: int, last: int) -> DataFrame:
    """Inclusive range over the partition column: pruned at the scan where the table is partitioned by it."""
    return df.filter(F.col("snapshot_ix").between(first, last))


def write_archives(pages: DataFrame, folder: str, files: int = 4) -> None:
    """Archive files of (page_id, url, html, crawl_ts, snapshot_ix), written by tasks into a mounted folder."""
    import os

    os.makedirs(folder, exist_ok=True)

    def run(rows):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        with open(f"{folder}/part-{part:05d}.warc.gz.tmp", "wb") as f:
            for r in rows:
                f.write(write_record(r["url"], r["html"], r["page_id"], r["crawl_ts"].strftime("%Y-%m-%dT%H:%M:%SZ"), r["snapshot_ix"]))
        os.rename(f"{folder}/part-{part:05d}.warc.gz.tmp", f"{folder}/part-{part:05d}.warc.gz")

    pages.repartition(files, "page_id").foreachPartition(run)


def write_archive_table(pages: DataFrame, path: str) -> None:
    """Records as gzip members in a parquet column: archives in any store that Spark writes, without a mounted folder."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            rows = b.to_pylist()
            made = [write_record(r["url"], r["html"], r["page_id"], r["crawl_ts"].strftime("%Y-%m-%dT%H:%M:%SZ"), r["snapshot_ix"]) for r in rows]
            yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], names=["content"])

    pages.select("page_id", "url", "html", "crawl_ts", "snapshot_ix").mapInArrow(run, "content binary").write.parquet(path)


def read_archive_table(spark: SparkSession, path: str) -> DataFrame:
    return _records(spark.read.parquet(path).select("content"))
