"""A data source for run folders: spark.read.format("prefix_runs").option("path", ...).

Each file of a run is one partition; rows come in file order with an ``__ordinal``. Register with
``spark.dataSource.register(PrefixRuns)``. Files are opened by address (file, hdfs, s3, gs) where they lie.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import LongType, StructField, StructType


class RunFile(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _files(path: str) -> tuple:
    from pyarrow import fs

    system, root = fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")
    return system, sorted(x.path for x in system.get_file_info(fs.FileSelector(root)) if x.path.endswith(".parquet"))


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[RunFile]:
        return [RunFile(p) for p in _files(self.path)[1]]

    def read(self, partition: RunFile) -> Iterator:
        import pyarrow as pa
        import pyarrow.parquet as pq

        at = 0
        with _files(self.path)[0].open_input_file(partition.path) as f:
            for batch in pq.ParquetFile(f).iter_batches(8192):
                ordinal = pa.array(range(at, at + batch.num_rows), pa.int64())
                at += batch.num_rows
                yield pa.RecordBatch.from_arrays([*batch.columns, ordinal], names=[*batch.schema.names, "__ordinal"])


class PrefixRuns(DataSource):
    @classmethod
    def name(cls) -> str:
        return "prefix_runs"

    def schema(self) -> StructType:
        import pyarrow.parquet as pq
        from pyspark.sql.pandas.types import from_arrow_schema

        system, files = _files(self.options["path"])
        first = pq.read_schema(system.open_input_file(files[0]))
        return StructType([*from_arrow_schema(first).fields, StructField("__ordinal", LongType())])

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options["path"])
