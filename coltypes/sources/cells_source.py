"""A data source for very large collections: many Parquet files as one long table of cells.

``spark.read.format("cells").option("paths", "a.parquet,b.parquet").load()`` gives (table_id, header,
ordinal, value) with one partition per row group, so 10^5 tables need no plan of that many unions.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _open(path: str) -> pq.ParquetFile:
    store, inner = fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path.removeprefix("file:"))
    return pq.ParquetFile(store.open_input_file(inner))


class CellsSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cells"

    def schema(self) -> str:
        return "table_id string, header string, ordinal int, value string"

    def reader(self, schema) -> CellsReader:
        return CellsReader([p for p in self.options.get("paths", "").split(",") if p])


class CellsReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((path, k)) for path in self.paths for k in range(_open(path).num_row_groups)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        path, group = partition.value
        name = path.rstrip("/").rsplit("/", 1)[-1].removesuffix(".parquet")
        file = _open(path)
        for ordinal, field in enumerate(file.schema_arrow):
            if pa.types.is_nested(field.type) or pa.types.is_binary(field.type):
                continue
            for batch in file.iter_batches(65536, row_groups=[group], columns=[field.name]):
                values = pc.drop_null(batch.column(0).cast(pa.string()))
                n = len(values)
                yield pa.record_batch([pa.array([name] * n), pa.array([field.name] * n), pa.array([ordinal] * n, pa.int32()), values], ["table_id", "header", "ordinal", "value"])


def register(spark) -> None:
    spark.dataSource.register(CellsSource)
