"""Links from crawl metadata: JSON lines ``{"url": ..., "links": [...]}``, one per page, as a Python data source."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow.fs as pafs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _store(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


class CrawlLinks(DataSource):
    """Option ``path``: a folder of JSON-line files. Rows: url, href; a page without links gives none, and lines that aren't JSON objects are skipped."""

    @classmethod
    def name(cls) -> str:
        return "crawl_links"

    def schema(self) -> str:
        return "url string, href string"

    def reader(self, schema) -> DataSourceReader:
        return CrawlReader(self.options["path"])


class CrawlReader(DataSourceReader):
    """One partition a file; lines stream, so a task holds one page's links."""

    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self) -> list[InputPartition]:
        store, path = _store(self.path)
        files = store.get_file_info(pafs.FileSelector(path, recursive=True))
        names = sorted(f.path for f in files if f.is_file and f.base_name.endswith((".json", ".jsonl")))
        return [InputPartition(n) for n in names] or [InputPartition(None)]

    def read(self, partition: InputPartition) -> Iterator[tuple[str, str]]:
        if partition.value is None:
            return
        store, _ = _store(self.path)
        rest = b""
        with store.open_input_stream(partition.value) as source:
            while part := source.read(1 << 20):
                *lines, rest = (rest + part).split(b"\n")
                for line in lines:
                    yield from _links(line)
        yield from _links(rest)


def _links(line: bytes) -> Iterator[tuple[str, str]]:
    try:
        page = json.loads(line) if line.strip() else {}
    except ValueError:
        return
    if isinstance(page, dict):
        for href in page.get("links") or ():
            yield page.get("url"), href


def read_crawl(spark: SparkSession, path: str):
    spark.dataSource.register(CrawlLinks)
    return spark.read.format("crawl_links").option("path", path).load()
