"""Sorts without ties, keys that hold most rows, and raw keys that the numeric view rounds."""

from collections import Counter
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec, order_bits, order_bits_np
from modelsort.functions.models import Composite, LinearBucket, Rmi, SplitterTree
from modelsort.operators import joins, lookup, rank, sorters, topk, verify
from modelsort.operators.sorters import SortConfig
from modelsort.sources import sinks
from modelsort.streaming import buckets as streaming

SORTERS = ["linear_partition_sort", "tree_sample_sort", "radix_partition_sort", "ecdf_two_pass_sort", "two_way_sort", "classic_copy_sort"]
N, PARTS = 40_000, 8
CONFIG = SortConfig(parts=PARTS, base_rows=512)


def hot(spark, *more):
    return spark.range(N).repartition(4).select(F.when(F.col("id") % 5 < 4, F.lit(7.0)).otherwise(F.col("id").cast("double")).alias("k"), *more)


def check(found, columns, fair=N / PARTS):
    lying = found.df.withColumn("p", F.spark_partition_id()).select("p", *columns).collect()
    keys = [tuple(r[c] for c in columns) for r in lying]
    assert keys == sorted(keys)
    sizes = Counter(r["p"] for r in lying)
    assert max(sizes.values()) <= 2 * fair
    assert [int(x) for x in found.counts()] == [sum(n for q, n in sizes.items() if q < p) for p in range(found.parts)]
    return keys


@pytest.mark.parametrize("name", SORTERS)
def test_bare_hot_key_spans_parts(spark, name):
    keys = check(getattr(sorters, name)(hot(spark), "k", config=CONFIG), ["k"])
    assert len(keys) == N and sum(k == (7.0,) for k in keys) == N * 4 // 5 + (0 if 7 % 5 < 4 else 1)


@pytest.mark.parametrize("name", SORTERS)
def test_hot_key_is_cut_by_its_ties(spark, name):
    check(getattr(sorters, name)(hot(spark, "id"), KeySpec("k", ties=("id",)), config=CONFIG), ["k", "id"])


@pytest.mark.parametrize("payload", ["constant", "distinct", "map"])
def test_hot_key_with_payload(spark, payload):
    made = {"constant": F.lit("x"), "distinct": F.col("id"), "map": F.create_map(F.lit("a"), F.col("id"))}[payload]
    df = hot(spark, "id", made.alias("p")) if payload == "map" else hot(spark, made.alias("p"))
    found = sorters.linear_partition_sort(df, "k", config=CONFIG)
    check(found, ["k"])
    assert found.rows().select("p").where("p is null").count() == 0


def test_repeated_rows_keep_their_values(spark):
    df = spark.createDataFrame([(-0.0 if i % 2 else 0.0,) for i in range(8000)], "k double")
    found = sorters.linear_partition_sort(df, "k", config=SortConfig(parts=4, base_rows=16))
    signs = Counter(str(r["k"]) for r in found.rows().collect())
    assert signs == {"-0.0": 4000, "0.0": 4000}


@pytest.mark.parametrize("name", SORTERS)
def test_strings_with_shared_leading_bytes(spark, name):
    df = spark.range(N).repartition(4).select(F.format_string("https://example.org/%08d/%s", F.pmod(F.xxhash64("id"), F.lit(N)), F.lit("é" * 3)).alias("k"))
    check(getattr(sorters, name)(df, "k", config=CONFIG), ["k"])


def test_strings_that_differ_late(spark):
    df = spark.range(N).select(F.concat(F.when(F.col("id") % 2 == 0, "aaaaaaaaaaaaaaaa").otherwise("bbbbbbbbbbbbbbbb"), F.lpad(F.pmod(F.xxhash64("id"), F.lit(N)), 6, "0")).alias("k"))
    check(sorters.linear_partition_sort(df, "k", config=CONFIG), ["k"])


def test_integers_and_decimals_beyond_doubles(spark):
    df = spark.range(N).select((F.lit(2**60) + F.pmod(F.xxhash64("id"), F.lit(9000))).alias("k"))
    check(sorters.linear_partition_sort(df, "k", config=CONFIG), ["k"])
    fine = spark.createDataFrame([(Decimal("1234567890123456789") + Decimal(i * 7919 % 4001).scaleb(-10),) for i in range(4001)], "k decimal(38,10)")
    check(sorters.linear_partition_sort(fine, "k", config=SortConfig(parts=3, base_rows=64)), ["k"], 4001 / 3)


@pytest.mark.parametrize("ascending", [True, False])
@pytest.mark.parametrize("nulls_first", [True, False])
def test_hot_nulls_and_descending_cuts(spark, ascending, nulls_first):
    df = spark.range(N).select(F.when(F.col("id") % 3 > 0, F.pmod(F.col("id"), F.lit(50)).cast("double")).alias("k"), "id")
    key = KeySpec("k", ascending, nulls_first, ("id",))
    found = sorters.linear_partition_sort(df, key, config=CONFIG)
    lying = [(r["k"], r["id"]) for r in found.rows().collect()]
    wanted = sorted(((r["k"], r["id"]) for r in df.collect()), key=lambda t: ((t[0] is None) != nulls_first, 0.0 if t[0] is None else t[0] if ascending else -t[0], t[1]))
    assert lying == wanted
    assert found.df.groupBy("__part").count().agg(F.max("count")).first()[0] <= 2 * N / PARTS
    assert verify.descents(found).first()["within_parts"] == 0


def test_ranks_of_a_key_in_many_parts(spark):
    for df, key in ((hot(spark), KeySpec("k")), (hot(spark, "id"), KeySpec("k", ties=("id",)))):
        got = {r["k"]: (r["rank"], r["dense_rank"], round(r["cume_dist"], 9)) for r in rank.ranks(sorters.linear_partition_sort(df, key, config=CONFIG)).distinct().collect()}
        values = np.sort([r["k"] for r in df.collect()])
        distinct = np.unique(values)
        assert got == {k: (int(np.searchsorted(values, k)) + 1, i + 1, round(np.searchsorted(values, k, "right") / N, 9)) for i, k in enumerate(distinct.tolist())}


def test_estimated_sizes_give_exact_answers(spark):
    df = spark.range(20_000).select("id", (F.pmod(F.xxhash64("id"), F.lit(1 << 30)) / 1000).alias("x"))
    found = sorters.linear_partition_sort(df, KeySpec("x", ties=("id",)), config=SortConfig(parts=5, base_rows=100, histogram_share=0.02))
    values = np.sort([r["x"] for r in df.collect()])
    assert [topk.quantile(df, found, q) for q in (0.1, 0.5, 0.99)] == [values[int(np.ceil(q * 20_000)) - 1] for q in (0.1, 0.5, 0.99)]
    assert sorted(r["count"] for r in rank.ntile(found, 7).groupBy("tile").count().collect()) == [2857] * 6 + [2858]
    bare = sorters.linear_partition_sort(df.select("x"), "x", config=SortConfig(parts=5, histogram_share=0.002, equality=False))
    assert verify.proof(bare).first()[:] == (20_000, len(np.unique(values)), 0)


def test_bits_on_the_jvm(spark):
    rng = np.random.default_rng(3)
    x = np.concatenate([[0.0, -0.0, 5e-324, -5e-324, 2.0**-1022, np.nextafter(2.0**-1022, 0), np.inf, -np.inf, 1.7976931348623157e308], 2.0 ** np.arange(-60, 60), np.nextafter(2.0 ** np.arange(-60, 60), 0), rng.normal(size=300) * 10.0 ** rng.integers(-300, 300, 300)])
    df = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)] + [(-1, float("nan")), (-2, None)], "i long, x double").withColumn("bits", order_bits(F.col("x")))
    got = {r["i"]: r["bits"] for r in df.collect()}
    assert [got[i] for i in range(len(x))] == order_bits_np(x).tolist() and got[-1] is None and got[-2] is None
    assert "Python" not in df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("method", sorted(sorters.SEQUENTIAL))
def test_sequential_orders(method):
    rng = np.random.default_rng(5)
    for x in (rng.normal(size=30_000), np.floor(rng.exponential(20, 30_000)), np.zeros(5000), np.array([3.0]), np.zeros(0), np.exp(rng.normal(0, 8, 20_000)), -np.arange(9000.0)):
        order = sorters.sequential_order(x, method, base=1024)
        assert (np.sort(order) == np.arange(len(x))).all() and (x[order] == np.sort(x)).all()


def test_correction_touches_open_runs_only():
    x = np.array([1.0, 2.0, 9.0, 3.0, 4.0, 4.0, 20.0])
    order, run, open_ = sorters.counting_order(x, np.array([0, 1, 2, 3, 4, 4, 6]))
    assert order.tolist() == list(range(7)) and open_.tolist() == [False, False, True, True, True, True, False]


@pytest.mark.parametrize("how", joins.HOW)
@pytest.mark.parametrize("side", ["left", "right", "both"])
def test_heavy_keys_of_joins(spark, how, side):
    left = [(k % 40, k) for k in range(200)] + [(7, -1)] * (3000 if side != "right" else 3) + [(99, 5), (None, 6)]
    right = [(k % 50, -k) for k in range(100)] + [(7 if side == "right" else 8, -9)] * (3000 if side != "left" else 3) + [(77, 1), (None, 2)]
    a, b = spark.createDataFrame(left, "k long, x long"), spark.createDataFrame(right, "k long, y long")
    wanted = Counter(tuple(r) for r in a.join(b, "k", how).collect())
    assert Counter(tuple(r) for r in joins.merge(a, b, "k", how, parts=4).collect()) == wanted
    assert Counter(tuple(r) for r in joins.salted(a, b, "k", how, heavy_share=0.02, salts=5).collect()) == wanted


def test_lookup_bounds_are_those_of_a_line(spark):
    df = spark.range(20_000).select(F.exp(F.col("id") / 1000.0).alias("x"), "id")
    index = lookup.RmiIndex.build(df, "x", ("id",), leaves=64, block=64)
    width = index.below + index.above
    assert np.median(width) < 0.2 * width.max()
    asked = df.where("id % 37 = 0").select("x")
    assert {r["id"] for r in index.lookup(asked).collect()} == set(range(0, 20_000, 37))
    assert {r["id"] for r in lookup.BinarySearch.build(index, fences=10).lookup(asked).collect()} == set(range(0, 20_000, 37))


def test_distributed_rmi_equals_that_of_the_driver(spark):
    x = np.sort(np.random.default_rng(1).normal(size=4000))
    df = spark.createDataFrame([(float(v),) for v in x], "x double")
    a, b = Rmi.two_level_distributed(df, "x", 32), Rmi.two_level(x, 32).monotone(x)
    probe = np.linspace(-5, 5, 400)
    assert np.allclose(a.predict(probe), b.predict(probe), atol=1e-9)
    assert SplitterTree.fit_distributed(df, "x", 16).splitters.tolist() == SplitterTree.fit(x, 16).splitters.tolist()
    for few in ([], [1.0], [2.0, 2.0]):
        model = Rmi.two_level_distributed(spark.createDataFrame([(v,) for v in few], "x double"), "x", 8)
        assert (np.diff(model.predict(np.arange(5.0))) >= 0).all()


def test_trees_are_joined_when_refined():
    tree = SplitterTree(np.array([1.0, 5.0]), np.zeros(0))
    both = tree.joined([SplitterTree(np.array([2.0, 3.0]), np.array([3.0]))])
    assert both.splitters.tolist() == [1.0, 2.0, 3.0, 5.0] and both.heavy.tolist() == [3.0]


def test_stored_models(spark, tmp_path):
    model = Composite(LinearBucket(0.5, 0.25, 4), {1: SplitterTree(np.array([2.0]), np.array([2.0]))})
    sinks.save_model(spark, model, str(tmp_path / "m"))
    x = np.linspace(-1, 9, 50)
    assert (sinks.load_model(spark, str(tmp_path / "m")).predict(x) == model.predict(x)).all()


def test_late_rows_after_a_restart(spark, tmp_path):
    batches = [spark.createDataFrame([(t,) for t in ts], "t double") for ts in ([100.0, 200.0], [50.0, 199.0], [], [100.0])]
    for number, batch in enumerate(batches):
        streaming.late_counter("t", 60, str(tmp_path / "s"))(batch, number)
    streaming.late_counter("t", 60, str(tmp_path / "s"))(batches[1], 1)
    found = {r["batch"]: (r["rows"], r["late"]) for r in spark.read.schema("rows long, late long, latest double, batch long").parquet(str(tmp_path / "s")).collect()}
    assert found == {0: (2, 0), 1: (2, 1), 2: (0, 0), 3: (1, 1)}


@pytest.mark.parametrize("method", sorted(sorters.SEQUENTIAL))
def test_sequential_orders_of_infinite_and_equal_keys(method):
    g = np.random.default_rng(3)
    ends = np.array([-0.0, 0.0, np.inf, -np.inf, 5.0])
    for x in (np.tile(ends, 3000), np.concatenate([g.normal(size=9000), np.tile(ends, 2000)]), np.full(9000, np.inf), np.tile([np.inf, -np.inf], 5000)):
        order = sorters.sequential_order(x, method, base=1024)
        assert np.array_equal(np.sort(order), np.arange(len(x))) and np.array_equal(x[order], np.sort(x))
