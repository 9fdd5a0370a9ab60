"""A data source in Python for text edge lists (u v t by white space), for formats that Spark's own readers lack.

spark.dataSource.register(EdgeLines); spark.read.format("temporal_edges").option("parts", 8).load(path). Each part reads its
own byte range of one file, from the line that starts in it. The path may be of any file system that Arrow knows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

CHUNK = 1 << 20


class Span(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def _open(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


def _lines(span: Span) -> Iterator[bytes]:
    """Lines that start within the span; the last one may end beyond it."""
    system, path = _open(span.path)
    with system.open_input_file(path) as f:
        at = span.start
        f.seek(max(0, at - 1))
        rest = b""
        if at:  # a line that starts before belongs to the part before
            while (chunk := f.read(CHUNK)) and b"\n" not in chunk:
                at += len(chunk)
            if not chunk:
                return
            cut = chunk.index(b"\n") + 1
            at, rest = at - 1 + cut, chunk[cut:]
        while at < span.end:
            while b"\n" not in rest:
                if not (chunk := f.read(CHUNK)):
                    if rest:
                        yield rest
                    return
                rest += chunk
            *whole, rest = rest.split(b"\n")
            for line in whole:
                if at >= span.end:
                    return
                yield line
                at += len(line) + 1


class EdgeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.parts = options["path"], int(options.get("parts", "8"))

    def partitions(self) -> list[Span]:
        system, path = _open(self.path)
        found = system.get_file_info(path)
        inner = [found] if found.type == fs.FileType.File else system.get_file_info(fs.FileSelector(path, recursive=True))
        out = []
        for f in inner:
            if f.type == fs.FileType.File and f.size and not f.base_name.startswith(("_", ".")):
                own = self.path if found.type == fs.FileType.File else self.path.rstrip("/") + f.path[len(path.rstrip("/")) :]
                step = -(-f.size // self.parts)
                out += [Span(own, low, min(low + step, f.size)) for low in range(0, f.size, step)]
        return out

    def read(self, partition: Span) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, int]] = []

        def batch() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([e[k] for e in held], pa.int64()) for k in range(3)], ["u", "v", "t"])

        for line in _lines(partition):
            parts = line.split()
            try:
                u, v, t = map(int, parts[:3])
            except ValueError:  # comments, and lines that aren't three numbers
                continue
            held.append((u, v, t))
            if len(held) >= 50_000:
                yield batch()
                held.clear()
        if held:
            yield batch()


class EdgeLines(DataSource):
    @classmethod
    def name(cls) -> str:
        return "temporal_edges"

    def schema(self) -> str:
        return "u bigint, v bigint, t bigint"

    def reader(self, schema: object) -> EdgeReader:
        return EdgeReader(self.options)
