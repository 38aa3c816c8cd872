"""Text extracts of a crawl: a Python data source that reads conversion records, one partition for each file.

Records are a version line, header lines, a blank line and as many bytes of text as ``Content-Length`` says. Paths are local or
mounted; for other stores use ``read_binary``, which goes through Spark's own file source.
"""

from __future__ import annotations

import glob
import gzip
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from . import schemas


def records(data: bytes) -> Iterator[tuple[str, str, str, str]]:
    """(url, digest, date, text) of each conversion record."""
    at = 0
    while (begin := data.find(b"WARC/", at)) >= 0:
        close = data.find(b"\r\n\r\n", begin)
        if close < 0:
            return
        head = dict(line.split(": ", 1) for line in data[begin:close].decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
        body = close + 4
        at = body + int(head.get("Content-Length", "0"))
        if head.get("WARC-Type") == "conversion":
            yield head.get("WARC-Target-URI", ""), head.get("WARC-Block-Digest", ""), head.get("WARC-Date", ""), data[body:at].decode("utf-8", "replace")


def unpacked(data: bytes) -> bytes:
    return gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data


class FilePartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class ExtractReader(DataSourceReader):
    def __init__(self, pattern: str):
        self.pattern = pattern

    def partitions(self) -> list[FilePartition]:
        return [FilePartition(p) for p in sorted(glob.glob(self.pattern))]

    def read(self, partition: FilePartition) -> Iterator[tuple]:
        with open(partition.path, "rb") as f:
            yield from records(unpacked(f.read()))


class ExtractSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "textextract"

    def schema(self) -> str:
        return schemas.EXTRACT

    def reader(self, schema) -> ExtractReader:
        return ExtractReader(self.options["path"])


def read_wet(spark: SparkSession, path: str) -> DataFrame:
    spark.dataSource.register(ExtractSource)
    return spark.read.format("textextract").option("path", path).load()


def read_binary(spark: SparkSession, path: str) -> DataFrame:
    """The same from any store, whole files through Spark's binary source."""

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blob in batch.column(0):
                rows = list(records(unpacked(blob.as_py())))
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string()) for i in range(4)], ["url", "digest", "date", "text"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(parse, schemas.EXTRACT)
