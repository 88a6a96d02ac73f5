"""Reading tables and key columns with pruning and pushdown."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import types as T


def read(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """A Parquet table; named columns and the filter reach the scan."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*columns) if columns else df


def read_as(spark: SparkSession, fmt: str, path: str, schema: T.StructType | str, **options) -> DataFrame:
    """A csv, json, orc, text or other table with its schema given, so that nothing is inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)
