"""The cuboid of cells as a Python data source: spark.read.format("cells").option("a", ..)..."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Cells(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class CellReader(DataSourceReader):
    """Edges of a range of cells a partition, as Arrow batches."""

    def __init__(self, sides: tuple[int, int, int], parts: int):
        self.sides, self.parts = sides, parts

    def partitions(self) -> list[InputPartition]:
        n = int(np.prod(self.sides))
        cuts = [n * k // self.parts for k in range(self.parts + 1)]
        return [Cells(a, b) for a, b in zip(cuts, cuts[1:]) if a < b]

    def read(self, partition: Cells) -> Iterator[pa.RecordBatch]:
        a, b, c = self.sides
        for first in range(partition.first, partition.last, 100_000):
            vid = np.arange(first, min(first + 100_000, partition.last))
            for step, n, place in ((1, a, vid % a), (a, b, vid // a % b), (a * b, c, vid // (a * b))):
                src = vid[place < n - 1]
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(src + step)], names=["src", "dst"])


class CellSource(DataSource):
    """Options a, b, c (sides) and parts."""

    @classmethod
    def name(cls) -> str:
        return "cells"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return CellReader(tuple(int(self.options[x]) for x in "abc"), int(self.options.get("parts", 8)))
