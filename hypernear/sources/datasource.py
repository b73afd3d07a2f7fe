"""A Python data source that reads a saved index's points by path: spark.read.format("hypernear_index").load(path)."""

from __future__ import annotations

import re

import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "shard int, leaf long, pos long, id long, r_x double, x_par double, x_perp double, x array<double>"


class IndexSource(DataSource):
    """Each file of the index is one partition. Paths are opened by their scheme (file, hdfs, s3, gs), as Arrow knows it; without one, as files."""

    @classmethod
    def name(cls) -> str:
        return "hypernear_index"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return IndexReader(self.options.get("path", ""))


class IndexReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.replace("file:/", "file:///", 1) if re.match("file:/[^/]", path) else path

    def store(self):
        """The file system of the path, and the path in it."""
        if "://" in self.path:
            return fs.FileSystem.from_uri(self.path)
        return fs.LocalFileSystem(), self.path

    def partitions(self) -> list[InputPartition]:
        system, root = self.store()
        found = [f.path for f in system.get_file_info(fs.FileSelector(f"{root}/points", recursive=True, allow_not_found=True)) if f.path.endswith(".parquet")]
        return [InputPartition(f) for f in sorted(found)] or [InputPartition("")]

    def read(self, partition: InputPartition):
        if partition.value:
            names = [part.split()[0] for part in SCHEMA.split(", ")]
            with self.store()[0].open_input_file(partition.value) as file:
                yield from pq.ParquetFile(file).iter_batches(columns=names)
