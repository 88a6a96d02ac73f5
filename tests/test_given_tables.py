"""Queries that once made their rows up take those of the given tables; states of the worked example."""

import duckdb
import pytest

from modelsort import catalog
from modelsort.operators import blocks

DATA = "/root/testdata/sf0.001"


def rows_of(table, columns="count(*)"):
    return duckdb.execute(f"SELECT {columns} FROM '{DATA}/{table}.parquet'").fetchall()


def found(spark, name):
    return catalog.queries()[name](spark, DATA)


def example():
    return blocks.classify([float(x) for x in catalog.EXAMPLE], catalog.EXAMPLE_LINE, catalog.EXAMPLE_BLOCK)


def test_blocks_of_all_events(spark):
    assert example().array() == [39, 33, 28, 25, 34, 47, 11, 2, 48, 50, 10, 6, 13, 9, 18, 22, 27, 29, 12, 36]
    assert found(spark, "worked_example_blocks").count() == rows_of("events")[0][0]


def test_buckets_of_all_events(spark):
    assert {r["idx"] for r in found(spark, "worked_example_buckets").collect()} == {r[0] for r in rows_of("events", "event_id")}


def test_contiguous_blocks_of_all_events(spark):
    assert [x for bucket in example().contiguous() for x in bucket] == [11, 2, 10, 6, 13, 9, 12, 18, 22, 28, 25, 27, 29, 39, 33, 34, 47, 48, 50, 36]
    assert found(spark, "worked_example_contiguous").count() == rows_of("events")[0][0]


def test_sizes_of_all_events(spark):
    assert sum(r["rows"] for r in found(spark, "worked_example_sizes").collect()) == rows_of("events")[0][0]


def test_sort_of_all_events_by_the_line_of_the_example(spark):
    assert [r["key"] for r in found(spark, "worked_example_sorted").orderBy("position").collect()] == sorted(r[0] for r in rows_of("events", "value"))


def test_traces_hold_all_events(spark):
    assert sum(len(r["keys"].split(",")) for r in found(spark, "block_trace_function").collect()) == rows_of("events")[0][0]


def test_peaks_of_all_events(spark):
    keys = [float(x) for x in catalog.EXAMPLE]
    assert [blocks.classify(keys, catalog.EXAMPLE_LINE, b).peak for b in (1, 2, 4)] == [1, 5, 12]
    assert sum(r["copy"] for r in found(spark, "peak_memory").collect()) == 3 * rows_of("events")[0][0]


def test_operation_model_of_all_users(spark):
    assert sum(r["n"] for r in found(spark, "operation_model").collect()) == rows_of("events")[0][0]


def test_stored_model_is_that_of_the_table(spark):
    low, high = rows_of("events", "min(value), max(value)")[0]
    assert tuple(found(spark, "model_store").first()) == pytest.approx((256, 256 / (high - low), -256 / (high - low) * low))


def test_generator_source_serves_all_events(spark):
    assert {r["id"] for r in found(spark, "key_generator_source").collect()} == {r[0] for r in rows_of("events", "event_id")}


def test_generated_families_of_all_events(spark):
    rows = found(spark, "generated_families").collect()
    assert len(rows) == 16 and {r["rows"] for r in rows} == {rows_of("events")[0][0]}


def test_scaling_goes_up_to_the_whole_table(spark):
    assert max(r["rows"] for r in found(spark, "experiment_scaling").collect()) == rows_of("embeddings", "sum(len(embedding))")[0][0]
