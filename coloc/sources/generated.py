"""The distance study's pairs as a data source of their own: spark.read.format("coloc_pairs").option("reps", 2).load().

With the options files (URIs of Parquet files, one in a line) and column, pairs have the numbers in that column instead; tasks read a row group each.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import pyarrow.fs
import pyarrow.parquet as pq
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

PAIRS, RANGES, WIDTH, SIDE = 30, 10, 0.2, 100.0


def _draw(tag: str, key: int) -> float:
    return int(hashlib.md5(f"{tag}{key}".encode()).hexdigest()[:8], 16) / 4294967296.0


class _Repetition(InputPartition):
    def __init__(self, number: int):
        self.number = number


def _pairs(numbers: Iterator[int]) -> Iterator[tuple]:
    for i in numbers:
        of, x, y = i // PAIRS, SIDE * _draw("px", i), SIDE * _draw("py", i)
        r, t = WIDTH * (of % RANGES + _draw("pr", i)), 2 * math.pi * _draw("pt", i)
        yield of, of % RANGES, f"a{i}", "f1", x, y
        yield of, of % RANGES, f"b{i}", "f2", x + r * math.cos(t), y + r * math.sin(t)


class _Reader(DataSourceReader):
    def __init__(self, reps: int):
        self.reps = reps

    def partitions(self) -> list[_Repetition]:
        return [_Repetition(k) for k in range(self.reps)]

    def read(self, partition: _Repetition) -> Iterator[tuple]:
        return _pairs(range(partition.number * RANGES * PAIRS, (partition.number + 1) * RANGES * PAIRS))


def _opened(uri: str) -> pq.ParquetFile:
    fs, path = pyarrow.fs.FileSystem.from_uri(uri)
    return pq.ParquetFile(fs.open_input_file(path))


class _RowGroup(InputPartition):
    def __init__(self, uri: str, number: int):
        self.uri, self.number = uri, number


class _NumbersReader(DataSourceReader):
    def __init__(self, files: list[str], column: str):
        self.files, self.column = files, column

    def partitions(self) -> list[_RowGroup]:
        return [_RowGroup(uri, k) for uri in self.files for k in range(_opened(uri).num_row_groups)]

    def read(self, partition: _RowGroup) -> Iterator[tuple]:
        numbers = _opened(partition.uri).read_row_group(partition.number, [self.column])[self.column]
        return _pairs(i for i in numbers.to_pylist() if i is not None)


class PairSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "coloc_pairs"

    def schema(self) -> str:
        return "set_id long, range_id int, object_id string, feature string, x double, y double"

    def reader(self, schema) -> DataSourceReader:
        if self.options.get("files"):
            return _NumbersReader(self.options["files"].split("\n"), self.options["column"])
        return _Reader(int(self.options.get("reps", "1")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PairSource)
