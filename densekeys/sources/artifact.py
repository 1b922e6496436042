"""`spark.read.format("densekeys").load(path)`: the buckets of a written artifact, a partition for each super-bucket group."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "bucket long, size long, tau long, seed long, tries long, offset long"


class Files(InputPartition):
    def __init__(self, path: str):
        self.path = path


class BucketReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
        return [Files(f) for f in ds.dataset(f"{root}/rows", filesystem=system, format="parquet").files]

    def read(self, partition: Files):
        import numpy as np
        import pyarrow.dataset as ds
        from pyarrow import fs

        from densekeys.functions.kernel import side_sizes

        system, root = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
        with system.open_input_stream(next(f.path for f in system.get_file_info(fs.FileSelector(f"{root}/manifest")) if f.base_name.startswith("part-"))) as f:
            eps = json.loads(f.read())["params"]["eps"]
        for row in ds.dataset(partition.path, filesystem=system, format="parquet").to_table().to_pylist():
            size = np.frombuffer(row["sizes"], np.int64)
            columns = np.frombuffer(row["buckets"], np.int64), size, side_sizes(size, eps), np.frombuffer(row["seeds"], np.int64), np.frombuffer(row["tries"], np.int64), row["base"] + np.cumsum(size) - size
            yield from zip(*(c.tolist() for c in columns), strict=True)


class ArtifactSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "densekeys"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> BucketReader:
        return BucketReader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ArtifactSource)


def read_keys(spark: SparkSession, path: str, cols: list[str], fmt: str = "parquet", schema: str | None = None) -> DataFrame:
    """Only the key columns, so that the reader prunes the rest."""
    reader = spark.read.format(fmt)
    if schema:
        reader = reader.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.load(path).select(*cols)
