"""Ordered and bucketed files, and models on disk."""

from __future__ import annotations

import json
from dataclasses import fields

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from modelsort.functions.models import Composite, EcdfBucket, LinearBucket, Model, RadixBucket, Rmi, SampleEcdf, SplitterTree, WithHeavy
from modelsort.operators.sorters import SortedFrame
from modelsort.plans.partitioner import PART, assign


STORED = (EcdfBucket, LinearBucket, RadixBucket, Rmi, SampleEcdf, SplitterTree, WithHeavy)


def write_ordered(sf: SortedFrame, path: str) -> DataFrame:
    """Write the rows in key order, a file a part, with a side table of ranges in ``path/_ranges``.

    Returns the side table ``file, low, high, rows, offset``; its minima and
    maxima let a reader open only the files that a range touches.
    """
    spark, key = sf.df.sparkSession, sf.key.column
    sf.df.withColumn("part", F.col(PART)).drop(PART).write.parquet(f"{path}/rows")
    back = spark.read.parquet(f"{path}/rows")
    ranges = back.groupBy(F.col("_metadata.file_name").alias("file")).agg(F.min("part").alias("part"), F.min(key).alias("low"), F.max(key).alias("high"), F.count("*").alias("rows"))
    from pyspark.sql import Window

    before = F.coalesce(F.sum("rows").over(Window.orderBy("part", "file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranges.withColumn("offset", before).write.parquet(f"{path}/ranges")
    return spark.read.parquet(f"{path}/ranges")


def read_range(spark: SparkSession, path: str, key: str, low, high) -> DataFrame:
    """Rows of ordered files with a key in [low, high]; only files whose range touches it are opened."""
    ranges = spark.read.parquet(f"{path}/ranges").where((F.col("high") >= F.lit(low)) & (F.col("low") <= F.lit(high)))
    files = [r["file"] for r in ranges.select("file").collect()]
    schema = spark.read.parquet(f"{path}/rows").schema
    rows = spark.read.schema(schema).parquet(*(f"{path}/rows/{f}" for f in files)) if files else spark.createDataFrame([], schema)
    return rows.where(F.col(key).between(F.lit(low), F.lit(high))).drop("part")


def write_bucketed(df: DataFrame, sf: SortedFrame, path: str) -> None:
    """The out-of-place copy: rows in a folder per bucket of the model."""
    bucketed = assign(df, sf.key, sf.model)
    bucketed.repartition("__bucket").write.partitionBy("__bucket").parquet(path)


def _pack(model: object) -> dict:
    """A model as plain values, its inner models too."""
    if isinstance(model, Composite):
        return {"kind": "Composite", "root": _pack(model.root), "children": {str(b): _pack(c) for b, c in model.children.items()}}
    values = {f.name: getattr(model, f.name) for f in fields(model)}
    plain = lambda v: v.tolist() if isinstance(v, np.ndarray) else [plain(x) for x in v] if isinstance(v, list) else _pack(v) if isinstance(v, (Model, Rmi, SampleEcdf)) else v
    return {"kind": type(model).__name__} | {name: plain(v) for name, v in values.items()}


def _unpack(row: dict) -> object:
    kind = row["kind"]
    if kind == "Composite":
        return Composite(_unpack(row["root"]), {int(b): _unpack(c) for b, c in row["children"].items()})
    arrays = {"SplitterTree": ("splitters", "heavy"), "WithHeavy": ("heavy",), "SampleEcdf": ("sample",), "Rmi": ("bounds",)}.get(kind, ())
    values = {name: np.array(v, float) if name in arrays and v is not None else _unpack(v) if isinstance(v, dict) else v for name, v in row.items() if name != "kind"}
    if kind == "Rmi":
        values |= {name: [np.array(x, float) for x in values[name]] for name in ("slopes", "intercepts")}
    return {c.__name__: c for c in STORED}[kind](**values)


def save_model(spark: SparkSession, model: Model, path: str) -> None:
    """Any model as one Parquet row: its kind, its buckets and its values as JSON, which keeps doubles exactly."""
    spark.createDataFrame([(type(model).__name__, int(getattr(model, "buckets", 0)), json.dumps(_pack(model)))], "kind string, k int, model string").coalesce(1).write.parquet(path)


def load_model(spark: SparkSession, path: str) -> Model:
    return _unpack(json.loads(spark.read.parquet(path).first()["model"]))
