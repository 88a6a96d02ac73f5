"""Every sorter against a plain sort, on ordinary and awkward keys."""

import math

import pytest
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec
from modelsort.operators import aggs, joins, rank, sorters, verify
from modelsort.operators.sorters import SortConfig

SORTERS = {"linear": sorters.linear_partition_sort, "tree": sorters.tree_sample_sort, "radix": sorters.radix_partition_sort, "ecdf": sorters.ecdf_two_pass_sort, "two_way": sorters.two_way_sort, "auto": sorters.auto_sort}
INF = float("inf")
CASES = {
    "empty": [],
    "one": [3.0],
    "equal": [7.0] * 50,
    "two_values": [1.0, 2.0] * 30,
    "sorted": [float(i) for i in range(200)],
    "reversed": [float(-i) for i in range(200)],
    "special": [None, float("nan"), INF, -INF, 0.0, -0.0, 5.0, None, -3.5, float("nan")] * 6,
    "outlier": [float(i % 17) for i in range(300)] + [1e300],
    "skewed": [math.exp(i % 40) for i in range(400)],
}
SMALL = SortConfig(k=8, base_rows=16, parts=3)


def expected(values, ascending, nulls_first):
    def order(pair):
        i, v = pair
        if v is None:
            return (0 if nulls_first else 2, 0, 0.0, i)
        nan = math.isnan(v)
        sign = 1 if ascending else -1
        return (1, sign * nan, 0.0 if nan else sign * v, i)

    return [i for i, _ in sorted(enumerate(values), key=order)]


@pytest.mark.parametrize("case", sorted(CASES))
@pytest.mark.parametrize("name", ["linear", "tree"])
@pytest.mark.parametrize(("ascending", "nulls_first"), [(True, True), (False, False), (False, True)])
def test_awkward_keys(spark, case, name, ascending, nulls_first):
    df = spark.createDataFrame(list(enumerate(CASES[case])), "id int, x double").repartition(3)
    key = KeySpec("x", ascending, nulls_first, ("id",))
    found = rank.global_position(SORTERS[name](df, key, config=SMALL)).orderBy("position").collect()
    assert [r["id"] for r in found] == expected(CASES[case], ascending, nulls_first)
    assert [r["position"] for r in found] == list(range(1, len(found) + 1))


@pytest.mark.parametrize("name", ["radix", "ecdf", "two_way", "auto"])
@pytest.mark.parametrize("case", ["special", "outlier", "equal", "empty"])
def test_baselines_on_awkward_keys(spark, name, case):
    df = spark.createDataFrame(list(enumerate(CASES[case])), "id int, x double").repartition(2)
    found = rank.global_position(SORTERS[name](df, KeySpec("x", ties=("id",)), config=SMALL)).orderBy("position").collect()
    assert [r["id"] for r in found] == expected(CASES[case], True, True)


def test_long_edges(spark):
    values = [2**63 - 1, -(2**63), 2**53 + 1, 2**53, 2**53 - 1, 0, -1, None]
    df = spark.createDataFrame(list(enumerate(values)), "id int, x long")
    found = rank.global_position(sorters.linear_partition_sort(df, KeySpec("x", ties=("id",)), config=SMALL)).orderBy("position")
    assert [r["x"] for r in found.collect()] == [None, *sorted(v for v in values if v is not None)]


def test_types_without_an_order_are_refused(spark):
    with pytest.raises(TypeError):
        sorters.linear_partition_sort(spark.createDataFrame([(1, [1])], "id int, x array<int>"), "x")


def test_refinement_bounds_every_open_bucket(spark):
    df = spark.range(6000).select("id", F.exp(F.pmod(F.xxhash64("id"), F.lit(4000)) / 250.0).alias("x"))
    found = sorters.linear_partition_sort(df, KeySpec("x", ties=("id",)), config=SortConfig(k=16, base_rows=400, parts=4))
    assert found.trace.rounds >= 2 and found.trace.largest[-1] <= 3000
    assert verify.descents(found).first()[:] == (0, 0)
    assert verify.same_bag(found.rows(), df)


def test_plan_moves_payload_once_and_stays_in_the_jvm(spark):
    df = spark.range(1000).select("id", (F.col("id") * 7 % 1000).cast("double").alias("x"), F.lit("payload").alias("p"))
    plan = sorters.linear_partition_sort(df, KeySpec("x", ties=("id",))).df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "shufflepartitionidpassthrough" in plan
    assert "Python" not in plan and "Arrow" not in plan


def test_merge_join_plans_no_further_exchange(spark):
    a = spark.range(500).select("id", F.lit(1).alias("a"))
    b = spark.range(250, 750).select("id", F.lit(2).alias("b"))
    joined = joins.merge(a, b, "id")
    plan = joined._jdf.queryExecution().executedPlan().toString()
    assert plan.count("shufflepartitionidpassthrough") == 2 and "hashpartitioning" not in plan
    assert joined.count() == 250


def test_equal_keys_spread_without_ties(spark):
    df = spark.range(4000).select("id", F.lit(5.0).alias("x"))
    found = sorters.linear_partition_sort(df, "x", config=SortConfig(parts=4))
    assert found.parts >= 4 and found.df.groupBy("__part").count().agg(F.max("count")).first()[0] < 2000
    assert {tuple(r) for r in rank.ranks(found).select("rank", "dense_rank", "percent_rank", "cume_dist").collect()} == {(1, 1, 0.0, 1.0)}
    assert rank.global_position(found).select("position").distinct().count() == 4000


def test_band_join_with_nulls_and_ties(spark):
    a = spark.createDataFrame([(i, v) for i, v in enumerate([1.0, 1.0, 2.5, None, float("nan"), 9.0])], "i int, x double")
    b = spark.createDataFrame([(j, v) for j, v in enumerate([0.5, 1.5, 3.0, None, 100.0])], "j int, y double")
    found = {(r["i"], r["j"]) for r in joins.band(a, b, "x", "y", 0.5).collect()}
    assert found == {(0, 0), (0, 1), (1, 0), (1, 1), (2, 2)}


def test_asof_without_matches(spark):
    l = spark.createDataFrame([(1, 5.0), (2, 1.0), (3, None)], "i int, t double")
    r = spark.createDataFrame([(10, 2.0), (11, 5.0)], "j int, u double")
    found = {x["i"]: x["j"] for x in joins.asof(l, r, "t", "u", columns=("j",)).collect()}
    assert found == {1: 11, 2: None, 3: None}


def test_fit_per_group_and_heavy(spark):
    df = spark.range(2000).select((F.col("id") % 3).alias("g"), F.col("id").cast("double").alias("x"))
    lines = aggs.fit_per_group(df, "g", "x", 16).collect()
    assert len(lines) == 3 and all(r["slope"] > 0 for r in lines)
    assert aggs.heavy(df, "g", 0.3).count() == 3
