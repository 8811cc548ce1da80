"""A Python data source: the block construction as ``spark.read.format("block_matrix")``, generated or over a table's keys."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Groups(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.row_max = int(options.get("n", 100)), int(options.get("row_max", 10))
        self.parts = int(options.get("parts", 4))

    def partitions(self) -> list[_Groups]:
        groups = self.n // self.row_max
        cuts = [groups * k // self.parts for k in range(self.parts + 1)]
        return [_Groups(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]

    def read(self, partition: _Groups) -> Iterator[tuple]:
        for group in range(partition.first, partition.last):
            entries = [(group * self.row_max + k, 1.0) for k in range(self.row_max)]
            for copy in range(self.row_max):
                yield (group * self.row_max + copy, entries)


class _RowGroup(InputPartition):
    def __init__(self, path: str, group: int):
        self.path, self.group = path, group


def _open(path: str):
    """File system and place of a path or URI."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if ":" in path.split("/")[0] else (fs.LocalFileSystem(), path)


class _TableReader(DataSourceReader):
    """A row for each key of Parquet files, read by the tasks: its entries are the columns of the key's group."""

    def __init__(self, options: dict):
        self.path, self.key, self.row_max = options["path"], options["key"], int(options.get("row_max", 10))

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs, parquet

        files, at = _open(self.path)
        inside = [at] if files.get_file_info(at).is_file else sorted(f.path for f in files.get_file_info(fs.FileSelector(at, recursive=True)) if f.is_file and f.base_name[0] not in "._")
        out = []
        for path in inside:
            with files.open_input_file(path) as file:
                out += [_RowGroup(path, k) for k in range(parquet.ParquetFile(file).num_row_groups)]
        return out

    def read(self, partition: _RowGroup) -> Iterator[pa.RecordBatch]:
        from pyarrow import parquet

        with _open(self.path)[0].open_input_file(partition.path) as file:
            for batch in parquet.ParquetFile(file, pre_buffer=False).iter_batches(10_000, [partition.group], [self.key], use_threads=False):
                key = batch.column(0).drop_null().to_numpy().astype(np.int64)
                col = (key // self.row_max * self.row_max)[:, None] + np.arange(self.row_max)
                entries = pa.StructArray.from_arrays([pa.array(col.ravel()).cast(pa.int32()), pa.array(np.ones(col.size))], ["col", "val"])
                bounds = pa.array(np.arange(len(key) + 1, dtype=np.int32) * self.row_max)
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.ListArray.from_arrays(bounds, entries)], names=["row_id", "entries"])


class BlockMatrixSource(DataSource):
    """Options: n (columns), row_max (columns of a group), parts; or path (Parquet), key (a column of whole numbers) and row_max."""

    @classmethod
    def name(cls) -> str:
        return "block_matrix"

    def schema(self) -> str:
        return "row_id bigint, entries array<struct<col:int,val:double>>"

    def reader(self, schema) -> DataSourceReader:
        return _TableReader(self.options) if "path" in self.options else _Reader(self.options)
