"""WARC and WET files as a Spark data source, and a writer for fixtures and round trips.

``spark.dataSource.register(WarcSource)`` then ``spark.read.format("warc").load(path)``
gives one row per record. Each file is one input partition, read as a stream of
members, so memory holds one record at a time; a broken record ends its file
with a row whose ``error`` tells why. Paths are those the Python workers can
open; for other stores ``read_binary`` goes through Spark's own reader.
"""

from __future__ import annotations

import glob
import gzip
import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

SCHEMA = "type string, record_id string, url string, date string, headers map<string,string>, payload string, error string"


def parse_stream(stream) -> Iterator[tuple]:
    """Records of an open, uncompressed stream."""
    while True:
        line = stream.readline()
        while line in (b"\r\n", b"\n"):
            line = stream.readline()
        if not line:
            return
        if not line.startswith(b"WARC/"):
            yield (None, None, None, None, {}, None, "no version line")
            return
        headers: dict[str, str] = {}
        while (line := stream.readline()) not in (b"\r\n", b"\n", b""):
            k, _, v = line.decode("utf-8", "replace").partition(":")
            headers[k.strip()] = v.strip()
        size = headers.get("Content-Length", "")
        if not size.isdigit():
            yield (None, None, None, None, headers, None, "no length")
            return
        block = stream.read(int(size))
        if len(block) < int(size):
            yield (None, None, None, None, headers, None, "cut off")
            return
        kind = headers.get("WARC-Type")
        if kind == "response" and b"\r\n\r\n" in block and block.startswith(b"HTTP/"):
            block = block.partition(b"\r\n\r\n")[2]
        yield (kind, headers.get("WARC-Record-ID"), headers.get("WARC-Target-URI"), headers.get("WARC-Date"), headers, block.decode("utf-8", "replace"), None)


def record_bytes(kind: str, url: str, payload: str, record_id: str | None = None, date: str = "2024-01-01T00:00:00Z") -> bytes:
    """One record; a response gets an HTTP head."""
    block = payload.encode("utf-8")
    if kind == "response":
        block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n" + block
    head = f"WARC/1.0\r\nWARC-Type: {kind}\r\nWARC-Record-ID: {record_id or f'<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, url)}>'}\r\nWARC-Target-URI: {url}\r\nWARC-Date: {date}\r\nContent-Length: {len(block)}\r\n\r\n"
    return head.encode("utf-8") + block + b"\r\n\r\n"


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        found = sorted(glob.glob(os.path.join(self.path, "*.w*"))) if os.path.isdir(self.path) else sorted(glob.glob(self.path))
        return [_File(p) for p in found] or [_File("")]

    def read(self, partition):
        if partition.path:
            opener = gzip.open if partition.path.endswith(".gz") else open
            with opener(partition.path, "rb") as f:
                try:
                    yield from parse_stream(f)
                except (EOFError, OSError) as e:
                    yield (None, None, None, None, {}, None, f"broken member: {type(e).__name__}")


@dataclass
class _Written(WriterCommitMessage):
    name: str


class _Writer(DataSourceWriter):
    def __init__(self, path: str, kind: str):
        self.path, self.kind = path, kind

    def write(self, rows):
        os.makedirs(self.path, exist_ok=True)
        name = f"part-{uuid.uuid4().hex}.warc.gz"
        with open(os.path.join(self.path, f".{name}"), "wb") as f:
            for r in rows:
                f.write(gzip.compress(record_bytes(self.kind, r["url"], r["payload"]), 6, mtime=0))
        return _Written(name)

    def commit(self, messages):
        """Show the files of the attempts that count; what lost attempts wrote stays hidden."""
        for m in messages:
            if m is not None:
                os.replace(os.path.join(self.path, f".{m.name}"), os.path.join(self.path, m.name))

    def abort(self, messages):
        for m in messages:
            if m is not None and os.path.exists(hidden := os.path.join(self.path, f".{m.name}")):
                os.remove(hidden)


class WarcSource(DataSource):
    """Options: ``path``; for writing ``kind`` (``response`` or ``conversion``) over rows ``(url, payload)``."""

    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options["path"], self.options.get("kind", "response"))


def read_binary(spark: SparkSession, path: str) -> DataFrame:
    """The same rows from any store that Spark can open: whole files through ``binaryFile``."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import io

        names = [x.split(" ")[0] for x in SCHEMA.replace("map<string,string>", "m").split(", ")]
        for b in batches:
            for content in b["content"]:
                raw = io.BytesIO(content)
                stream = gzip.GzipFile(fileobj=raw) if content[:2] == b"\x1f\x8b" else raw
                rows: list[tuple] = []
                for record in parse_stream(stream):
                    rows.append(record)
                    if len(rows) == 256:
                        yield pd.DataFrame(rows, columns=names)
                        rows = []
                if rows:
                    yield pd.DataFrame(rows, columns=names)

    return spark.read.format("binaryFile").load(path).select(F.col("content")).mapInPandas(run, SCHEMA)
