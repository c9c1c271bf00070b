"""A Python data source for crawl archives: one partition per file, response records as page_id, url, html."""

from __future__ import annotations

import gzip
import io
import zlib
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "page_id long, url string, html string, status string"


def records(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, body) of the records of an uncompressed archive; a cut last record is left out."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError("not a crawl archive record")
        head: dict[str, str] = {}
        while (line := stream.readline()) and line.strip():
            k, _, v = line.decode("utf-8", "replace").partition(":")
            head[k.strip().lower()] = v.strip()
        n = int(head.get("content-length", "0"))
        body = stream.read(n)
        if len(body) < n:
            return
        yield head, body


def pages(raw: bytes, first_id: int) -> Iterator[tuple[int, str | None, str | None, str]]:
    data = gzip.decompress(raw) if raw[:2] == b"\x1f\x8b" else raw
    for i, (head, body) in enumerate(records(io.BytesIO(data))):
        if head.get("warc-type") == "response":
            _, _, html = body.partition(b"\r\n\r\n")
            yield first_id + i, head.get("warc-target-uri"), html.decode("utf-8", "replace"), "ok"


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class _Reader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self):
        return [_File(p) for p in self.paths]

    def read(self, partition):
        with open(partition.value, "rb") as f:
            yield from pages(f.read(), zlib.crc32(partition.value.encode()) << 24)


class WarcSource(DataSource):
    """spark.dataSource.register(WarcSource); spark.read.format("warc").option("paths", "a.warc.gz,b.warc").load().

    Paths are opened by the executors, so they must be on a file system that is mounted there. For a store that only
    Spark reads, use read_archives().
    """

    @classmethod
    def name(cls):
        return "warc"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader([p for p in self.options["paths"].split(",") if p])


def read_archives(spark, glob: str):
    """The same rows through Spark's own file reader: any store that Spark can open."""
    import pandas as pd

    def run(frames):
        for f in frames:
            for path, raw in zip(f["path"], f["content"]):
                try:
                    rows = list(pages(raw, zlib.crc32(path.encode()) << 24))
                except (ValueError, OSError, EOFError, zlib.error) as e:
                    rows = [(None, path, None, f"broken: {type(e).__name__}")]
                yield pd.DataFrame(rows, columns=["page_id", "url", "html", "status"]).astype({"page_id": "Int64"})

    return spark.read.format("binaryFile").load(glob).select("path", "content").mapInPandas(run, SCHEMA)


def write_archive(rows: list[tuple[str, str]]) -> bytes:
    """A gzip-compressed archive of (url, html) responses, one member each."""
    out = []
    for url, html in rows:
        body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n\r\n" + html.encode()
        head = f"WARC/1.0\r\nWARC-Type: response\r\nWARC-Target-URI: {url}\r\nContent-Length: {len(body)}\r\n\r\n".encode()
        out.append(gzip.compress(head + body + b"\r\n\r\n"))
    return b"".join(out)
