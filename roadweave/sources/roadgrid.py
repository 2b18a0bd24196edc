"""The lattice as a data source: ``spark.read.format("roadgrid").option("side", 80)``."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.network import FIRST, SIDE, STEP

SCHEMA = "s long, src long, dst long, length double, travel_time long"
_FIELDS = pa.schema([("s", pa.int64()), ("src", pa.int64()), ("dst", pa.int64()), ("length", pa.float64()), ("travel_time", pa.int64())])


class Rows(InputPartition):
    """A run of the lattice's rows."""

    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RoadGridReader(DataSourceReader):
    def __init__(self, side: int, first: int, step: int, parts: int):
        self.side, self.first, self.step, self.parts = side, first, step, parts

    def partitions(self) -> list[Rows]:
        edges = [self.side * k // self.parts for k in range(self.parts + 1)]
        return [Rows(a, b) for a, b in zip(edges, edges[1:]) if b > a]

    def read(self, partition: Rows) -> Iterator[pa.RecordBatch]:
        n, rows = self.side, []
        streets = n * (n - 1)
        for i in range(partition.first, partition.last):
            for j in range(n - 1):
                for back in (0, 1):
                    a, b = i * n + j + back, i * n + j + 1 - back
                    rows.append((back * streets + i * (n - 1) + j, a, b, 100.0 + 10 * (i % 7), 3))
            if i == n - 1:
                continue
            for k, j in enumerate(range(self.first, n, self.step)):
                for up in (0, 1):
                    a, b = (i + up) * n + j, (i + 1 - up) * n + j
                    rows.append((2 * streets + (2 * k + up) * (n - 1) + i, a, b, 200.0, 1 + j // self.step % 2))
        yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows), _FIELDS)], schema=_FIELDS)


class RoadGrid(DataSource):
    """Options: ``side``, ``first`` arterial column, ``step`` between arterials, ``parts``."""

    @classmethod
    def name(cls) -> str:
        return "roadgrid"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> RoadGridReader:
        number = lambda name, default: int(self.options.get(name, default))
        return RoadGridReader(number("side", SIDE), number("first", FIRST), number("step", STEP), number("parts", 8))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RoadGrid)
