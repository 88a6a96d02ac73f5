"""Proofs walk rows where they lie, and the words of the experiments are counted once."""

import pytest
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec
from modelsort.operators import sorters, verify
from modelsort.plans import durable
from modelsort.plans.partitioner import PART
from modelsort.sources import datasets


def lying(spark, parts, kind="double", **key):
    """Rows as given, a partition a part."""
    rows = spark.sparkContext.parallelize([[(p, v) for v in values] for p, values in enumerate(parts)], len(parts)).flatMap(lambda x: x)
    df = spark.createDataFrame(rows, f"{PART} int, v {kind}")
    return sorters.SortedFrame(df, KeySpec("v", **key), len(parts), None, None, None, None)


def test_proof_moves_no_rows(spark):
    df = spark.range(1000).select(F.pmod("id", F.lit(7)).cast("double").alias("v"))
    sf = sorters.SortedFrame(sorters.builtin_sort(df, "v").withColumn(PART, F.spark_partition_id()), KeySpec("v"), 1, None, None, None, None)
    found = verify.proof(sf)
    assert found.first()[:] == (1000, 7, 0)
    assert "hashpartitioning" not in found._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize(
    ("parts", "kind", "key", "wanted", "fell"),
    [
        ([[], [1.0, 1.0], [], [1.0, 2.0], [0.5, 3.0]], "double", {}, (6, 4, 1), (0, 1)),
        ([[None, -0.0, 0.0], [float("inf"), float("nan")], [float("nan")]], "double", {}, (6, 4, 0), (0, 0)),
        ([[1.0, None], [float("nan"), 2.0]], "double", {}, (4, 4, 2), (2, 0)),
        ([["b", "a"], ["a", None]], "string", {"ascending": False, "nulls_first": False}, (4, 3, 0), (0, 0)),
        ([[False, True], [False]], "boolean", {}, (3, 3, 1), (0, 1)),
    ],
)
def test_proof_of_odd_keys(spark, parts, kind, key, wanted, fell):
    sf = lying(spark, parts, kind, **key)
    assert verify.proof(sf).first()[:] == wanted and verify.descents(sf).first()[:] == fell


def test_parts_that_span_partitions_and_share_them(spark):
    df = spark.createDataFrame([(0, 1), (0, 3), (1, 2), (1, 4)], f"{PART} int, v int").coalesce(1)
    more = df.unionByName(spark.createDataFrame([(1, 3), (1, 5)], f"{PART} int, v int").coalesce(1))
    sf = sorters.SortedFrame(more, KeySpec("v"), 2, None, None, None, None)
    assert verify.descents(sf).first()[:] == (1, 1)


def test_words_are_counted_once(spark):
    before = len(durable._written)
    datasets.carrier(spark, "/root/testdata/sf0.001", "zipf")
    assert sum("word-counts" in p for p in durable._written[before:]) == 1
