"""Sources: tables, lines, whole files, binary words, pattern lists, and byte ranges of huge files."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lines(spark: SparkSession, path: str) -> DataFrame:
    """A word for each line: value."""
    return spark.read.text(path)


def whole(spark: SparkSession, path: str) -> DataFrame:
    """A word for each file: path, value."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), "value")


def binary(spark: SparkSession, path: str) -> DataFrame:
    """A byte word for each file: path, length, content."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")


def patterns(spark: SparkSession, path: str) -> DataFrame:
    """A pattern list from CSV or JSON lines: pattern_id, family, pattern, mode."""
    schema = "pattern_id int, family string, pattern string, mode string"
    return spark.read.schema(schema).json(path) if path.endswith(".json") else spark.read.schema(schema).csv(path, header=True, escape='"')


class _Range(InputPartition):
    def __init__(self, word: int, path: str, first: int, start: int, stop: int):
        self.word, self.path, self.first, self.start, self.stop = word, path, first, start, stop


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.paths = sorted(p for p in options["path"].split(",") if p)
        self.chunk = int(options.get("chunkBytes", options.get("chunkbytes", 4 << 20)))
        self.per_task = max(1, int(options.get("taskBytes", options.get("taskbytes", 64 << 20))) // self.chunk)

    @staticmethod
    def _open(path: str):
        from pyarrow import fs

        return fs.FileSystem.from_uri(path if "://" in path else "file://" + path)

    def partitions(self) -> list[_Range]:
        out = []
        for word, path in enumerate(self.paths):
            system, inner = self._open(path)
            size, step = system.get_file_info(inner).size, self.chunk * self.per_task
            out += [_Range(word, path, a // self.chunk, a, min(size, a + step)) for a in range(0, max(size, 1), step)]
        return out

    def read(self, part: _Range) -> Iterator[pa.RecordBatch]:
        system, inner = self._open(part.path)
        names = ["word_id", "path", "chunk_ix", "offset", "payload"]
        with system.open_input_file(inner) as file:
            file.seek(part.start)
            for i, at in enumerate(range(part.start, max(part.stop, part.start + 1), self.chunk)):
                payload = file.read(min(self.chunk, part.stop - at))
                yield pa.RecordBatch.from_arrays([pa.array([part.word], pa.int64()), pa.array([part.path]), pa.array([part.first + i], pa.int32()), pa.array([at], pa.int64()), pa.array([payload], pa.binary())], names)


class ByteRanges(DataSource):
    """Format ``byte_ranges``: every file is one byte word in ordered chunks; tasks read disjoint ranges of it.

    Options: path (comma-separated files), chunkBytes, taskBytes. A chunk may cut a multi-byte letter: byte automata
    give the same answer wherever a word is cut.
    """

    @classmethod
    def name(cls) -> str:
        return "byte_ranges"

    def schema(self) -> str:
        return "word_id long, path string, chunk_ix int, offset long, payload binary"

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)


def byte_ranges(spark: SparkSession, path: str, chunk_bytes: int = 4 << 20, task_bytes: int = 64 << 20) -> DataFrame:
    spark.dataSource.register(ByteRanges)
    return spark.read.format("byte_ranges").option("path", path).option("chunkBytes", chunk_bytes).option("taskBytes", task_bytes).load()
