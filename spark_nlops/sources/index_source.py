"""A Python data source that reads a stored text index by bucket: ``spark.read.format("nlops_index").option("path", ...)``."""

from __future__ import annotations

import glob
import os

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class BucketPartition(InputPartition):
    def __init__(self, files: list[str]) -> None:
        self.files = files


class IndexReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.path, self.bucket = options["path"].removeprefix("file://"), options.get("bucket")

    def partitions(self):
        folders = sorted(glob.glob(os.path.join(self.path, "vectors", f"bucket={self.bucket if self.bucket is not None else '*'}")))
        return [BucketPartition(sorted(glob.glob(os.path.join(f, "*.parquet")))) for f in folders] or [BucketPartition([])]

    def read(self, partition):
        import pyarrow.parquet as pq

        for name in partition.files:
            for batch in pq.ParquetFile(name).iter_batches():
                for row in batch.to_pylist():
                    yield row["key"], row["vec"]


class IndexSource(DataSource):
    """Local or mounted folders; ``vectors.index.load_text_index`` is the reader for any file system."""

    @classmethod
    def name(cls) -> str:
        return "nlops_index"

    def schema(self) -> str:
        return "key bigint, vec array<double>"

    def reader(self, schema) -> IndexReader:
        return IndexReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(IndexSource)
