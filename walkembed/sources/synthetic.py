"""A Python data source: edges of the synthetic graph, generated where they are read."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class Range(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


class SyntheticGraphSource(DataSource):
    """``spark.read.format("synthetic_graph")``: i meets (i + j*j + j) mod n for j = 1..half.

    Options: ``n`` nodes, ``half`` edges a node, ``rows_per_partition`` nodes a task.
    """

    @classmethod
    def name(cls) -> str:
        return "synthetic_graph"

    def schema(self) -> str:
        return "a long, b long"

    def reader(self, schema: StructType) -> DataSourceReader:
        return SyntheticGraphReader(int(self.options.get("n", 1000)), int(self.options.get("half", 5)), int(self.options.get("rows_per_partition", 1_000_000)))


class SyntheticGraphReader(DataSourceReader):
    def __init__(self, n: int, half: int, rows: int):
        self.n, self.half, self.rows = n, half, rows

    def partitions(self) -> list[InputPartition]:
        return [Range(lo, min(lo + self.rows, self.n)) for lo in range(0, max(self.n, 1), self.rows)]

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        j = np.arange(1, self.half + 1)
        for lo in range(partition.begin, partition.end, 65_536):
            i = np.arange(lo, min(lo + 65_536, partition.end))
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(i, self.half)), pa.array(((i[:, None] + j * j + j) % self.n).ravel())], ["a", "b"])
