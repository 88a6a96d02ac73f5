"""Measures and distribution functions against plain counts, with hot, null and missing keys."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec
from modelsort.functions.models import LinearBucket
from modelsort.operators import metrics, rank, sorters

HOT = [5.0] * 400 + [float(v) for v in range(300)] + [None, None, -1.5]


def frame(spark, values):
    return spark.createDataFrame(list(enumerate(values)), "id long, x double").repartition(7)


@pytest.mark.parametrize("values", [HOT, [], [None], [3.0], [2.0] * 9])
def test_cumulative_rows(spark, values):
    steps, n = rank.cumulative(frame(spark, values), "x")
    keys = np.sort([v for v in values if v is not None])
    assert n == len(keys)
    assert sorted(map(tuple, steps.collect())) == [(x, int((keys == x).sum()), int((keys <= x).sum())) for x in np.unique(keys)]


def test_exact_ecdf_keeps_columns_and_leaves_nulls_out(spark):
    found = rank.exact_ecdf(frame(spark, HOT), "x")
    keys = np.sort([v for v in HOT if v is not None])
    assert found.columns == ["id", "x", "ecdf", "position"]
    assert sorted((r["x"], r["position"]) for r in found.collect()) == [(x, int((keys <= x).sum())) for x in keys]


def test_measures_of_empty_and_hot_keys(spark):
    line = LinearBucket(0.02, 0.0, 8)
    ecdf = lambda x: F.least(F.lit(1.0), F.greatest(F.lit(0.0), x / 300))
    empty = frame(spark, [])
    assert metrics.violations(empty, F.col("x"), ecdf).first()[0] == 0
    assert metrics.ecdf_error(empty, F.col("x"), ecdf).first()["max_error"] is None
    assert tuple(metrics.displacement(empty, F.col("x"), line.column(F.col("x")), [F.col("id")]).first()) == (0, None, 0)
    hot = frame(spark, HOT)
    keys = np.sort([v for v in HOT if v is not None])
    misses = np.abs(np.clip(keys / 300, 0, 1) - np.searchsorted(keys, keys, side="right") / len(keys))
    found = metrics.ecdf_error(hot, F.col("x"), ecdf).first()
    assert (found["max_error"], found["mean_error"]) == pytest.approx((misses.max(), misses.mean()))
    assert metrics.violations(hot, F.col("x"), lambda x: -x).first()[0] == len(np.unique(keys)) - 1
    backwards = metrics.displacement(frame(spark, [float(v) for v in range(100)]), F.col("x"), -F.col("x"), [F.col("id")]).first()
    assert tuple(backwards) == (100, 99, 99)


def test_ablation_counts_every_key(spark):
    for row in metrics.fit_ablation(frame(spark, HOT), "x", (8,)):
        assert 400 / 701 <= row["max_share"] <= 1


def test_falls_across_parts(spark):
    sf = sorters.linear_partition_sort(frame(spark, [float(v) for v in range(5000)]), KeySpec("x", ties=("id",)), config=sorters.SortConfig(parts=5))
    assert metrics.falls(sf.df, sf.key, "x").first()[0] == 0
    down = sf.df.withColumn("y", -F.col("x"))
    assert metrics.falls(down, sf.key, "y").first()[0] == 4999
