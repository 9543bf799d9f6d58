"""Lists of keys from text, CSV, JSON, ORC, Parquet or JDBC, pruned to the columns asked for."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def read_keys(spark: SparkSession, path: str | None, columns: list[str] | None = None, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A table of keys. A text file gives the column `value`, one key a line."""
    reader = spark.read.format(format).options(**options)
    if schema:
        reader = reader.schema(schema)
    df = reader.load(path) if path else reader.load()
    return df.select(*columns) if columns else df
