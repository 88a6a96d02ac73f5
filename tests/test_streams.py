"""Results of streams: written by the executors, the last of complete results, and empty ones."""

import pytest
from pyspark.sql import functions as F

from modelsort import catalog
from modelsort.streaming import buckets as streaming

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["stream_asof_static", "stream_session_counts", "stream_interval_join"])
def test_results_do_not_pass_through_the_driver(spark, name):
    before = {t.name for t in spark.catalog.listTables()}
    assert catalog.queries()[name](spark, DATA).inputFiles()
    assert {t.name for t in spark.catalog.listTables()} == before  # a memory sink holds its rows on the driver


def test_complete_results_are_the_last_ones(spark, tmp_path):
    for i in range(4):
        spark.range(10 * i, 10 * i + 10).coalesce(1).write.mode("append").parquet(str(tmp_path / "rows"))
    stream = streaming.replay(spark, str(tmp_path / "rows"), "id long").groupBy((F.col("id") % 3).alias("k")).count()
    assert {tuple(r) for r in streaming.run_to_files(stream, "last", "complete").collect()} == {(0, 14), (1, 13), (2, 13)}


def test_streams_without_files_give_no_rows(spark, tmp_path):
    assert streaming.run_to_files(streaming.replay(spark, str(tmp_path), "id long"), "none").collect() == []


@pytest.mark.parametrize("days", [0, 20000])
def test_interval_join_takes_a_folder_of_files(spark, tmp_path, days):
    """As a cluster writes a table, also with moments before 1970."""
    spark.read.parquet(f"{DATA}/events.parquet").withColumn("ts", F.expr(f"ts - INTERVAL {days} DAYS")).repartition(3).write.parquet(str(tmp_path / "events.parquet"))
    query = catalog.queries()["stream_interval_join"]
    wanted = sorted(query(spark, DATA).collect())
    assert wanted and sorted(query(spark, str(tmp_path)).collect()) == wanted


def joined(spark, path, rows, within):
    spark.createDataFrame(rows, "i long, u long, s double").select("i", "u", F.timestamp_seconds("s").alias("ts")).write.parquet(path)
    left = streaming.replay(spark, path, "i long, u long, ts timestamp", files_per_trigger=None)
    right = streaming.replay(spark, path, "i long, u long, ts timestamp", files_per_trigger=None).select(F.col("i").alias("j"), "u", F.col("ts").alias("at"))
    return streaming.interval_join(left, right, "u", "ts", "at", within, late=None)


@pytest.mark.parametrize(("within", "seconds"), [("1 hour", 3600), ("0 seconds", 0), ("90 minutes", 5400)])
def test_interval_join_equals_brute_force(spark, tmp_path, within, seconds):
    times = [0.0, 0.0, -1e-6, 1e-6, 3600.0, 3600.000001, 7200.0, 5400.0, -3600.0, -7200.0, 1.7e9, 1.7e9 + 3600, None]
    rows = [(i, i % 7 if i % 5 == 4 else 0, s) for i, s in enumerate(times)] + [(99, None, 0.0)]
    exact = lambda s: round(s * 1e6)
    wanted = sorted((i, j) for i, u, t in rows for j, v, s in rows if u is not None and u == v and t is not None and s is not None and exact(t) - seconds * 10**6 <= exact(s) <= exact(t))
    found = streaming.run_to_files(joined(spark, str(tmp_path / "rows"), rows, within), "pairs", closing=False)
    assert sorted(tuple(r) for r in found.select("i", "j").collect()) == wanted


def test_interval_join_takes_months(spark, tmp_path):
    days = [0.0, 31.0, 59.0, 90.0]  # of 1970: a month back from March 1 is February 1
    found = streaming.run_to_files(joined(spark, str(tmp_path / "rows"), [(i, 0, 86400 * d) for i, d in enumerate(days)], "1 month"), "pairs", closing=False)
    assert sorted(tuple(r) for r in found.select("i", "j").collect()) == [(0, 0), (1, 0), (1, 1), (2, 1), (2, 2), (3, 2), (3, 3)]


def test_interval_join_reads_near_rows_only(spark, tmp_path):
    frame = joined(spark, str(tmp_path / "rows"), [(i, 0, 7200.0 * i) for i in range(300)], "1 hour")
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, streaming.STATE[key])
    try:
        stream = frame.writeStream.format("noop").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
        stream.awaitTermination()
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)
    first = stream.recentProgress[0]["stateOperators"][0]["customMetrics"]
    assert 0 < first["rocksdbGetCount"] < 20 * 300  # each row against each other would be 90,000


@pytest.mark.parametrize("days", [0, 20000])
def test_session_counts_take_a_folder_of_files(spark, tmp_path, days):
    """As a cluster writes a table, also with moments before 1970; one batch writes the result."""
    spark.read.parquet(f"{DATA}/events.parquet").withColumn("ts", F.expr(f"ts - INTERVAL {days} DAYS")).repartition(3).write.parquet(str(tmp_path / "events.parquet"))
    query = catalog.queries()["stream_session_counts"]
    wanted, found = sorted(query(spark, DATA).collect()), query(spark, str(tmp_path))
    assert wanted and sorted(found.collect()) == wanted
    assert all("/batch=0/" in f for f in found.inputFiles())


def test_streams_leave_the_session_as_it_was(spark, tmp_path):
    keys = [*streaming.STATE, streaming.NO_DATA]
    before = [spark.conf.get(k, None) for k in keys]
    streaming.run_to_files(streaming.replay(spark, str(tmp_path), "id long"), "none", closing=False)
    assert [spark.conf.get(k, None) for k in keys] == before
