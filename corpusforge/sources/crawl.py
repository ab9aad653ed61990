"""Crawl archives: plain or gzip files of records with a header and a body.

A record is ``WARC/<version>`` and header lines, an empty line, and ``Content-Length`` bytes of body. :func:`read_archives`
takes any path that Spark reads; the data source ``crawltext`` takes folders that driver and executors mount alike, one
partition a file, listed when the reader is planned.
"""

from __future__ import annotations

import glob
import gzip
import io
import os
from collections.abc import Iterator
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from corpusforge.engine import arrow_map

SCHEMA = "url string, record_type string, date string, body string"


def records(stream) -> Iterator[tuple[str | None, str | None, str | None, str]]:
    """Records of one open file. A cut-off last record comes with the type ``truncated`` and what there is of it."""
    while True:
        line = stream.readline()
        if not line:
            return
        if not line.startswith(b"WARC/"):
            continue
        head: dict[str, str] = {}
        while (line := stream.readline().strip()) != b"":
            name, _, value = line.decode("utf-8", "replace").partition(":")
            head[name.strip().lower()] = value.strip()
        n = int(head.get("content-length", 0))
        body = stream.read(n)
        if len(body) < n:
            yield head.get("warc-target-uri"), "truncated", head.get("warc-date"), body.decode("utf-8", "replace")
            return
        yield head.get("warc-target-uri"), head.get("warc-type"), head.get("warc-date"), body.decode("utf-8", "replace")


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        found = sorted(glob.glob(os.path.join(self.path, "*"))) if os.path.isdir(self.path) else sorted(glob.glob(self.path))
        return [_File(p) for p in found]

    def read(self, partition):
        with gzip.open(partition.path, "rb") if partition.path.endswith(".gz") else open(partition.path, "rb") as stream:
            yield from records(stream)


class CrawlText(DataSource):
    """``spark.read.format("crawltext").load(path)``"""

    @classmethod
    def name(cls):
        return "crawltext"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(self.options["path"])


#: Columns of Spark's source of whole files, which a stream has to be told.
FILES = "path string, modificationTime timestamp, length long, content binary"
#: Records of an Arrow batch.
RECORDS = 500


def _parse(batches):
    for rows in batches:
        for path, content in zip(rows.column(0).to_pylist(), rows.column(1), strict=True):
            raw = io.BytesIO(memoryview(content.as_buffer()))
            with gzip.GzipFile(fileobj=raw) if path.endswith(".gz") else raw as stream:
                found = records(stream)
                while part := list(islice(found, RECORDS)):
                    yield pa.RecordBatch.from_arrays([pa.array([path] * len(part)), *[pa.array(c, pa.string()) for c in zip(*part, strict=True)]], names=["path", "url", "record_type", "date", "body"])


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """(path, url, record_type, date, body) of archives on any store that Spark reads, one file a value, parsed as a stream."""
    files = spark.read.format("binaryFile").load(path).select("path", "content")
    return arrow_map(files, _parse, f"path string, {SCHEMA}")


def stream_archives(spark: SparkSession, path: str, max_files: int = 64) -> DataFrame:
    """The same for archives as they arrive in a folder."""
    files = spark.readStream.format("binaryFile").schema(FILES).option("maxFilesPerTrigger", max_files).load(path).select("path", "content")
    return arrow_map(files, _parse, f"path string, {SCHEMA}")


def register(spark: SparkSession) -> None:
    from corpusforge.engine import ship

    ship(spark)
    spark.dataSource.register(CrawlText)


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None) -> DataFrame:
    """Block lists, lexicons and rules in a built-in format."""
    reader = spark.read.schema(schema) if schema else spark.read
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)
