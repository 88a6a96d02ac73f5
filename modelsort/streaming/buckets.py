"""Frozen bucket models on streams: counts per window, late rows, drift, sorted runs, reservoirs, joins."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from modelsort.functions.keys import numeric
from modelsort.functions.models import Model
from modelsort.operators.sorters import SortConfig, SortedFrame, sort_with
from modelsort.plans.durable import new_folder

_ROCKSDB = "spark.sql.streaming.stateStore.rocksdb"
#: Session settings of a stream's state: on disk, with a bound on the native memory of a process and no lookup of each key before it is put.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    f"{_ROCKSDB}.boundedMemoryUsage": "true",
    f"{_ROCKSDB}.maxMemoryUsageMB": "512",
    f"{_ROCKSDB}.trackTotalNumberOfRows": "false",
    "spark.sql.streaming.join.stateFormatVersion": "3",  # one store a part for both sides, in place of four that each take 5 MB at least
}
NO_DATA = "spark.sql.streaming.noDataMicroBatches.enabled"
#: Cells of an interval join are so many intervals long.
CELL = 2


def replay(spark: SparkSession, folder: str, schema, files: str = "*", files_per_trigger: int | None = 1) -> DataFrame:
    """Parquet files of a folder whose names match ``files`` as a stream; ``timestamp_ntz`` columns become time stamps, as watermarks need.

    Without ``files_per_trigger`` all files that are there come in one batch.
    """
    reader = spark.readStream.schema(schema).option("pathGlobFilter", files)
    stream = (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(folder)
    return stream.withColumns({c: F.col(c).cast("timestamp") for c, kind in stream.dtypes if kind == "timestamp_ntz"})


def watermarked(stream: DataFrame, ts: str, late: str | None) -> DataFrame:
    """With the watermark, or as it is without ``late``; a watermark starts at 1970 and drops what is older."""
    return stream.withWatermark(ts, late) if late else stream


def bucket_counts(stream: DataFrame, key: str, model: Model, ts: str = "ts", window: str = "1 hour", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Rows per tumbling (or sliding) window and bucket of a frozen model."""
    span = F.window(ts, window, slide) if slide else F.window(ts, window)
    bucketed = stream.withWatermark(ts, late).withColumn("bucket", model.column(numeric(stream, key)))
    return bucketed.groupBy(span.alias("w"), "bucket").agg(F.count("*").alias("rows")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "bucket", "rows")


def session_counts(stream: DataFrame, key: str, model: Model, by: str, ts: str = "ts", gap: str = "30 minutes", late: str | None = "1 day") -> DataFrame:
    """Rows and distinct buckets of each session of ``by``."""
    bucketed = watermarked(stream, ts, late).withColumn("bucket", model.column(numeric(stream, key)))
    sessions = bucketed.groupBy(F.session_window(ts, gap).alias("w"), by).agg(F.count("*").alias("rows"), F.max("bucket").alias("top_bucket"))
    return sessions.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), by, "rows", "top_bucket")


def dedup(stream: DataFrame, columns: list[str], ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """Rows whose ``columns`` were not seen within the watermark."""
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark(columns)


def late_counter(ts: str, late_seconds: float, path: str) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: rows of a batch that lie further back than ``late_seconds`` behind the latest time before it.

    Each batch writes ``rows, late, latest`` to ``path/batch=N``; the latest time
    is read from earlier batches there, so a restarted query carries on and a repeated batch rewrites its row.
    """

    def count(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        seconds = F.col(ts).cast("double")
        latest = spark.read.schema("rows long, late long, latest double, batch long").parquet(path).where(F.col("batch") < number).agg(F.max("latest")).first()[0] if number else None
        behind = F.count(F.when(seconds < F.lit(latest) - F.lit(float(late_seconds)), 1)) if latest is not None else F.lit(0)
        found = batch.agg(F.count("*").alias("rows"), behind.cast("long").alias("late"), F.max(seconds).alias("latest"))
        found.coalesce(1).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return count


def drift_monitor(key: str, model: Model, out: list[dict], clipped_most: float = 0.05, share_most: float = 1 / 3) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: share of rows in the end buckets and fullest bucket of a batch; asks for a refit beyond bounds."""

    def watch(batch: DataFrame, number: int) -> None:
        bucket = model.column(numeric(batch, key))
        rows = batch.groupBy(bucket.alias("b")).count()
        n, top, ends = rows.agg(F.sum("count"), F.max("count"), F.sum(F.when(F.col("b").isin(0, model.buckets - 1), F.col("count")).otherwise(0))).first()
        if n:
            out.append({"batch": number, "rows": n, "max_share": top / n, "end_share": ends / n, "refit": bool(top / n > share_most or ends / n > 2 * max(clipped_most, 2 / model.buckets))})

    return watch


def sorted_runs(model: Model, key: str, path: str, config: SortConfig = SortConfig()) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: each batch sorted by the frozen model into a run of its own (a repeated batch rewrites its run)."""

    def write(batch: DataFrame, number: int) -> None:
        sort_with(batch, key, model, config).rows().write.mode("overwrite").parquet(f"{path}/run={number}")

    return write


def compact(spark: SparkSession, path: str, key: str, model: Model, config: SortConfig = SortConfig()) -> SortedFrame:
    """All runs below ``path`` as one sorted frame."""
    return sort_with(spark.read.parquet(path).drop("run"), key, model, config)


class _Reservoir(StatefulProcessor):
    """Keeps the ``size`` rows of least hash of each group: a uniform sample that repeats alike."""

    def __init__(self, size: int):
        self.size = size

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getMapState("kept", "h long", "x double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = {k[0]: v[0] for k, v in self.kept.iterator()}
        for frame in rows:
            held.update(zip(frame["h"].tolist(), frame["x"].tolist(), strict=True))
        least = dict(sorted(held.items())[: self.size])
        for h, _ in list(self.kept.iterator()):
            if h[0] not in least:
                self.kept.removeKey(h)
        for h, x in least.items():
            self.kept.updateValue((h,), (x,))
        yield pd.DataFrame({"g": [key[0]], "kept": [len(least)], "mean": [sum(least.values()) / max(len(least), 1)]})

    def close(self) -> None:
        pass


def reservoir(stream: DataFrame, id_col: str, key: str, groups: int = 8, size: int = 256) -> DataFrame:
    """Running sample of keys for a later refit: per hash group, its size and mean after each batch."""
    rows = stream.select(F.xxhash64(id_col).alias("h"), numeric(stream, key).alias("x"), F.pmod(F.xxhash64(id_col, F.lit("g")), F.lit(groups)).alias("g")).where("x is not null")
    return rows.groupBy("g").transformWithStateInPandas(_Reservoir(size), outputStructType="g long, kept long, mean double", outputMode="update", timeMode="none")


def interval_join(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, within: str = "1 hour", late: str | None = "1 day") -> DataFrame:
    """Pairs of two streams with equal ``by`` and the right time at or up to ``within`` before the left.

    Rows meet in cells of time, so the state reads the rows near a row and not all of its ``by``. A
    right row lies in one cell and a left row in each that its interval touches, so a pair meets once.
    """
    since = F.col(left_ts) - F.expr(f"INTERVAL {within}")
    width = F.expr(f"greatest(1L, {CELL} * (unix_micros(TIMESTAMP_LTZ '2000-01-01') - unix_micros(TIMESTAMP_LTZ '2000-01-01' - INTERVAL {within})))")
    cell = lambda at: F.floor(F.unix_micros(at) / width)
    l = watermarked(left, left_ts, late).withColumn("__cell", F.explode(F.sequence(cell(since), cell(F.col(left_ts))))).alias("l")
    r = watermarked(right, right_ts, late).withColumnRenamed(by, "__by").withColumn("__at", cell(F.col(right_ts))).alias("r")
    near = (F.col(f"l.{by}") == F.col("__by")) & (F.col("__cell") == F.col("__at")) & (F.col(right_ts) <= F.col(left_ts)) & (F.col(right_ts) >= since)
    return l.join(r, near).drop("__by", "__cell", "__at")


def asof_static(stream: DataFrame, static: DataFrame, stream_ts: str, static_ts: str, by: str, columns: tuple[str, ...] = ()) -> DataFrame:
    """Stream rows with ``columns`` of the last static row of equal ``by`` at or before them; no match gives nulls.

    The static rows become intervals to the next one of their group, so the join is
    stateless: an equi-join with a range condition. Of static rows at one time the last by ``columns`` counts.
    """
    ahead = Window.partitionBy("__by").orderBy(static_ts, *columns)
    spans = static.select(F.col(by).alias("__by"), F.col(static_ts), *columns).withColumn("__until", F.lead(static_ts).over(ahead))
    near = (F.col(by) == F.col("__by")) & (F.col(static_ts) <= F.col(stream_ts)) & (F.col("__until").isNull() | (F.col(stream_ts) < F.col("__until")))
    return stream.join(spans.hint("merge"), near, "left").drop("__by", "__until")  # sorted, since a broadcast would pass through the driver


def run_to_files(query_frame: DataFrame, tag: str, mode: str = "append", closing: bool = True) -> DataFrame:
    """Run a stream over what is there now into Parquet and return its result; nothing of it passes through the driver.

    A repeated batch rewrites its own files. Of ``complete`` results only the last
    two are kept and the last is returned. State is held by RocksDB, out of the
    executors' heap, and checkpointed below the shared folder. ``closing`` runs the batch without
    rows after the last one, which gives what a watermark ends: windows, unmatched rows of outer joins.
    """
    spark = query_frame.sparkSession
    path = new_folder(spark, tag)
    written: list[str] = []

    def write(batch: DataFrame, number: int) -> None:
        place = f"{path}/batch={number % 2 if mode == 'complete' else number}"
        batch.write.mode("overwrite").parquet(place)
        written.append(place)

    settings = STATE | {NO_DATA: str(closing).lower()}
    before = {k: spark.conf.get(k, None) for k in settings}
    for k, v in settings.items():
        spark.conf.set(k, v)
    try:
        stream = query_frame.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", new_folder(spark, f"{tag}-state")).trigger(availableNow=True).start()
        stream.awaitTermination()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    if not written:
        return spark.createDataFrame([], query_frame.schema)
    return spark.read.schema(query_frame.schema).parquet(*(written[-1:] if mode == "complete" else dict.fromkeys(written)))
