"""A Python data source for stores: spark.read.format("eqdict").option("path", ...).load() gives a row for each cell."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.fs as pafs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

CELLS = "bucket long, cell int, split_seed int, func_no int, m int, seed int, extra int, planes array<long>"


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


def _opened(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if ":" in path.split("/")[0] else (pafs.LocalFileSystem(), path)


class CellReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        fs, base = _opened(self.path)
        if fs.get_file_info(f"{base}/manifest").type == pafs.FileType.NotFound:
            raise FileNotFoundError(f"{self.path} has no manifest: not a store, or its build did not end")
        with fs.open_input_file(next(f.path for f in fs.get_file_info(pafs.FileSelector(f"{base}/manifest")) if f.base_name.startswith("part-"))) as f:
            json.loads(f.read())
        return [_File(f.path) for f in fs.get_file_info(pafs.FileSelector(f"{base}/buckets")) if f.base_name.endswith(".parquet")]

    def read(self, partition: _File) -> Iterator[pa.RecordBatch]:
        fs, _ = _opened(self.path)
        names = [c.split()[0] for c in CELLS.split(", ")]
        kinds = (pa.int64(), *(pa.int32(),) * 6, pa.list_(pa.int64()))
        for b in ds.dataset(partition.path, filesystem=fs, format="parquet").to_batches(columns=["bucket", "split_seed", "func_no", "cells"]):
            rows = [(r["bucket"], i, r["split_seed"], r["func_no"], c["m"], c["seed"], c["extra"], c["planes"]) for r in b.to_pylist() for i, c in enumerate(r["cells"])]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


class StoreSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "eqdict"

    def schema(self) -> str:
        return CELLS

    def reader(self, schema) -> DataSourceReader:
        return CellReader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(StoreSource)
