"""A data source of binary tile files: spark.read.format("tiles").option("q", q).load(folder), and the same for writing.

A file is a sequence of records of one size: bi and bj as little-endian 32-bit integers, then q*q little-endian doubles, so it splits at any record and a
task reads its byte range only. Files are opened through Arrow's file systems (local or mounted folders, HDFS, object stores) by URI.
Writing: tasks write files under a name that starts with _, commit renames them; an aborted or repeated task leaves nothing visible. Append adds files,
overwrite removes the folder's tile files when it commits. Null tiles raise.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyarrow import fs as arrow_fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

SCHEMA = "bi int, bj int, tile array<double>"
#: Bytes that a task reads at most, and that are held at once.
SPLIT, BUFFER = 128 << 20, 8 << 20


def _open(uri: str) -> tuple[arrow_fs.FileSystem, str]:
    return arrow_fs.FileSystem.from_uri(uri)


def _record(q: int) -> np.dtype:
    return np.dtype([("bi", "<i4"), ("bj", "<i4"), ("tile", "<f8", (q * q,))])


def _files(uri: str) -> list[arrow_fs.FileInfo]:
    system, path = _open(uri)
    found = system.get_file_info(arrow_fs.FileSelector(path, allow_not_found=True))
    return sorted((f for f in found if f.is_file and not f.base_name.startswith(("_", "."))), key=lambda f: f.path)


@dataclass
class Span(InputPartition):
    path: str
    first: int
    count: int


@dataclass
class Written(WriterCommitMessage):
    path: str | None


class Reader(DataSourceReader):
    def __init__(self, uri: str, q: int) -> None:
        self.uri, self.q = uri, q

    def partitions(self) -> list[InputPartition]:
        size, out = _record(self.q).itemsize, []
        for f in _files(self.uri):
            if f.size % size:
                raise ValueError(f"{f.path} does not hold whole tiles of side {self.q}")
            n, step = f.size // size, max(1, SPLIT // size)
            out += [Span(f.path, k, min(step, n - k)) for k in range(0, n, step)]
        return out or [Span("", 0, 0)]

    def read(self, span: Span) -> Iterator[pa.RecordBatch]:
        kind = _record(self.q)
        step = max(1, BUFFER // kind.itemsize)
        if not span.count:
            return
        with _open(self.uri)[0].open_input_file(span.path) as f:
            for k in range(span.first, span.first + span.count, step):
                n = min(step, span.first + span.count - k)
                rows = np.frombuffer(f.read_at(n * kind.itemsize, k * kind.itemsize), kind)
                flat = np.ascontiguousarray(rows["tile"]).ravel()
                tiles = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * (self.q * self.q)), pa.array(flat))
                yield pa.RecordBatch.from_arrays([pa.array(rows["bi"].copy()), pa.array(rows["bj"].copy()), tiles], names=["bi", "bj", "tile"])


class Writer(DataSourceArrowWriter):
    def __init__(self, uri: str, q: int, overwrite: bool) -> None:
        self.uri, self.q, self.overwrite = uri, q, overwrite

    def write(self, batches: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        system, path = _open(self.uri)
        system.create_dir(path, recursive=True)
        name, any_rows = f"{path}/_{uuid.uuid4().hex}.tiles", False
        with system.open_output_stream(name) as out:
            for b in batches:
                rows = np.empty(b.num_rows, _record(self.q))
                rows["bi"], rows["bj"] = b.column("bi").to_numpy(), b.column("bj").to_numpy()
                tiles = b.column("tile")
                if tiles.null_count:
                    raise ValueError("a tile is null")
                rows["tile"] = np.asarray(tiles.flatten()).reshape(b.num_rows, self.q * self.q)
                out.write(rows.tobytes())
                any_rows |= b.num_rows > 0
        if any_rows:
            return Written(name)
        system.delete_file(name)
        return Written(None)

    def commit(self, messages: list[WriterCommitMessage | None]) -> None:
        system, _ = _open(self.uri)
        old = [f.path for f in _files(self.uri)] if self.overwrite else []
        for m in messages:
            if m is not None and m.path:
                folder, name = m.path.rsplit("/", 1)
                system.move(m.path, f"{folder}/{name[1:]}")
        for path in old:
            system.delete_file(path)

    def abort(self, messages: list[WriterCommitMessage | None]) -> None:
        system, _ = _open(self.uri)
        for m in messages:
            if m is not None and m.path:
                system.delete_file(m.path)


class TileSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tiles"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return Reader(self.options["path"], int(self.options["q"]))

    def writer(self, schema, overwrite: bool) -> DataSourceArrowWriter:
        return Writer(self.options["path"], int(self.options["q"]), overwrite)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(TileSource)
