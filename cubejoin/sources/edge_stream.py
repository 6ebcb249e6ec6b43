"""A Python data source for edges: ``spark.read.format("edges")`` and ``readStream``.

Option ``edges`` holds "src dst" pairs separated by semicolons, or ``n``,
``vertices`` and ``seed`` ask for generated ones.  As a stream each batch brings
``rate`` edges.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def _mixed(i: int, seed: int, modulus: int) -> int:
    x = (i * 0x9E3779B97F4A7C15 + seed * 0xBF58476D1CE4E5B9) & (2**64 - 1)
    x ^= x >> 29
    x = (x * 0x94D049BB133111EB) & (2**64 - 1)
    return (x ^ (x >> 32)) % modulus


def _edge(options: dict, i: int) -> tuple[int, int]:
    if "edges" in options:
        a, b = options["edges"].split(";")[i].split()
        return int(a), int(b)
    modulus, seed = int(options.get("vertices", 100)), int(options.get("seed", 1))
    return _mixed(2 * i, seed, modulus), _mixed(2 * i + 1, seed, modulus)


def _total(options: dict) -> int:
    return len(options["edges"].split(";")) if "edges" in options else int(options.get("n", 100))


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__(lo)
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self):
        n, parts = _total(self.options), int(self.options.get("partitions", 4))
        return [_Range(n * k // parts, n * (k + 1) // parts) for k in range(parts)]

    def read(self, partition) -> Iterator[tuple[int, int]]:
        for i in range(partition.lo, partition.hi):
            yield _edge(self.options, i)


class _StreamReader(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.options = options

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict):
        end = min(_total(self.options), start["at"] + int(self.options.get("rate", 10)))
        return iter([_edge(self.options, i) for i in range(start["at"], end)]), {"at": end}

    def readBetweenOffsets(self, start: dict, end: dict):
        return iter([_edge(self.options, i) for i in range(start["at"], end["at"])])

    def commit(self, end: dict) -> None:
        pass


class EdgeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "edges"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _StreamReader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeSource)
