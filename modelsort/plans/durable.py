"""Intermediate results that outlive a lost executor.

An intermediate is a Parquet folder below the shared folder that the cluster
names in ``spark.checkpoint.dir``. A folder of our own is made only on a local
master without that setting, as in tests. ``release`` deletes what this process wrote.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """URI of the folder that all executors and the driver share.

    On a local master, where they are one machine, a session without the setting
    gets a temporary folder; anywhere else its absence is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context = spark.sparkContext
        existing = context._jsc.sc().getCheckpointDir()
        if not existing.isDefined():
            if not context.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="modelsort-"))
            existing = context._jsc.sc().getCheckpointDir()
        root = existing.get()
    return root.rstrip("/")


def new_folder(spark: SparkSession, tag: str) -> str:
    """A fresh folder name below the shared root; nothing is created yet."""
    path = f"{shared_root(spark)}/modelsort/{tag}-{uuid.uuid4().hex}"
    _written.append(path)
    return path


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once and return a frame that reads the files, cutting its lineage."""
    spark = df.sparkSession
    path = new_folder(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Delete every intermediate of this process; frames built on them stop working."""
    hadoop = spark.sparkContext._jsc.hadoopConfiguration()
    path_class = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    while _written:
        path = path_class(_written.pop())
        path.getFileSystem(hadoop).delete(path, True)
