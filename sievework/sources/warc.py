"""WARC files as a Spark data source (``spark.read.format("warc")``), and a writer of test files."""

from __future__ import annotations

import gzip
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "record_id string, warc_type string, url string, ts string, html string"


def parse_records(stream) -> Iterator[tuple]:
    """Records of an uncompressed WARC byte stream: version line, headers, empty line, block of Content-Length bytes."""
    while line := stream.readline():
        if not line.startswith(b"WARC/"):
            continue
        heads = {}
        while (line := stream.readline()).strip():
            name, _, value = line.decode("utf-8", "replace").partition(":")
            heads[name.strip().lower()] = value.strip()
        body = stream.read(int(heads.get("content-length", 0)))
        if heads.get("warc-type") == "response":  # an HTTP message: its own headers end at the first empty line
            body = body.partition(b"\r\n\r\n")[2] or body
        yield heads.get("warc-record-id"), heads.get("warc-type"), heads.get("warc-target-uri"), heads.get("warc-date"), body.decode("utf-8", "replace")


class _File(InputPartition):
    def __init__(self, uri: str):
        self.uri = uri


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[_File]:
        """One partition for each file; gzip members can't be split."""
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")
        info = store.get_file_info(path)
        found = [info] if info.is_file else store.get_file_info(fs.FileSelector(path, recursive=True))
        scheme = self.path.partition("://")[0] if "://" in self.path else "file"
        return [_File(f"{scheme}://{f.path}") for f in found if f.is_file and f.path.endswith((".warc", ".warc.gz"))]

    def read(self, partition: _File) -> Iterator[tuple]:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(partition.uri)
        with store.open_input_stream(path, compression=None) as raw:
            yield from parse_records(gzip.GzipFile(fileobj=raw) if path.endswith(".gz") else raw)


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


def read_warc(spark: SparkSession, path: str):
    spark.dataSource.register(WarcSource)
    return spark.read.format("warc").load(path)


def record_bytes(record_id: str, url: str, html: str, ts: str = "2024-01-01T00:00:00Z") -> bytes:
    body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n\r\n" + html.encode()
    head = f"WARC/1.0\r\nWARC-Type: response\r\nWARC-Record-ID: {record_id}\r\nWARC-Target-URI: {url}\r\nWARC-Date: {ts}\r\nContent-Length: {len(body)}\r\n\r\n"
    return head.encode() + body + b"\r\n\r\n"
