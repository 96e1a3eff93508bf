"""A Python data source: raw pairs from two columns of a Parquet table, read in the tasks."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class Groups(InputPartition):
    """Row groups ``begin`` to ``end`` (exclusive) of a file."""

    def __init__(self, file: str, begin: int, end: int):
        self.file, self.begin, self.end = file, begin, end


class TablePairsSource(DataSource):
    """``spark.read.format("table_pairs")``: (a, b) of the columns named by the options ``a`` and ``b`` of the file or folder ``path``."""

    @classmethod
    def name(cls) -> str:
        return "table_pairs"

    def schema(self) -> str:
        return "a long, b long"

    def reader(self, schema: StructType) -> DataSourceReader:
        return TablePairsReader(self.options["path"], self.options["a"], self.options["b"], int(self.options.get("row_groups", 1)))


def _opened(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(path) if ":/" in path else (fs.LocalFileSystem(), path)


class TablePairsReader(DataSourceReader):
    def __init__(self, path: str, a: str, b: str, groups: int):
        self.path, self.a, self.b, self.groups = path, a, b, groups

    def partitions(self) -> list[InputPartition]:
        files, where = _opened(self.path)
        found = [where]
        if files.get_file_info(where).type == fs.FileType.Directory:
            found = sorted(f.path for f in files.get_file_info(fs.FileSelector(where, recursive=True)) if f.is_file and not f.base_name.startswith(("_", ".")))
        sizes = [(f, pq.ParquetFile(f, filesystem=files).num_row_groups) for f in found]
        return [Groups(f, lo, min(lo + self.groups, n)) for f, n in sizes for lo in range(0, n, self.groups)]

    def read(self, partition: Groups) -> Iterator[pa.RecordBatch]:
        file = pq.ParquetFile(partition.file, filesystem=_opened(self.path)[0])
        for batch in file.iter_batches(65_536, row_groups=range(partition.begin, partition.end), columns=[self.a, self.b]):
            yield pa.RecordBatch.from_arrays([batch.column(self.a).cast(pa.int64()), batch.column(self.b).cast(pa.int64())], ["a", "b"])
