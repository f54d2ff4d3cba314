"""A Python data source for page archives: `spark.read.format("page_archive").load(file)`; one partition per file (L3, L259)."""

from __future__ import annotations

import glob
import os
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "page_id long, url string, offset long, payload binary"


def encode_record(page_id: int, url: str, payload: bytes) -> bytes:
    head = f"WARC/1.1\r\nWARC-Type: resource\r\nX-Page-Id: {page_id}\r\nWARC-Target-URI: {url}\r\nContent-Length: {len(payload)}\r\n\r\n"
    return head.encode() + payload + b"\r\n\r\n"


def records(path: str) -> Iterator[tuple[int, str, int, bytes]]:
    """Records of one file, read one at a time."""
    with open(path, "rb") as f:
        while True:
            offset, line = f.tell(), f.readline()
            if not line:
                return
            if not line.startswith(b"WARC/"):
                continue
            fields = {}
            while (line := f.readline().rstrip(b"\r\n")):
                name, _, value = line.decode("utf-8", "replace").partition(":")
                fields[name.strip().lower()] = value.strip()
            payload = f.read(int(fields.get("content-length", 0)))
            yield int(fields.get("x-page-id", -1)), fields.get("warc-target-uri", ""), offset, payload


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        files = sorted(glob.glob(os.path.join(self.path, "*"))) if os.path.isdir(self.path) else [self.path]
        return [InputPartition(f) for f in files if not os.path.basename(f).startswith(("_", "."))]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from records(partition.value)


class PageArchive(DataSource):
    @classmethod
    def name(cls) -> str:
        return "page_archive"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PageArchive)


def write(pages: DataFrame, folder: str) -> None:
    """Archives of pages (page_id, url, html) in a local folder, one file per partition."""
    os.makedirs(folder, exist_ok=True)

    def emit(rows, pid):
        with open(os.path.join(folder, f"part-{pid:05d}.warc"), "wb") as f:
            for r in rows:
                f.write(encode_record(r["page_id"], r["url"], (r["html"] or "").encode()))

    def run(batches):
        from pyspark import TaskContext

        pid = TaskContext.get().partitionId()
        rows = [r for b in batches for r in b.to_pylist()]
        emit(rows, pid)
        import pyarrow as pa

        yield pa.record_batch([pa.array([len(rows)], pa.int64())], ["n"])

    pages.select("page_id", "url", "html").mapInArrow(run, "n long").collect()


def write_layout(docs: DataFrame, path: str) -> None:
    """Documents partitioned by language; rewriting one language leaves the others."""
    docs.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("lang").parquet(path)
