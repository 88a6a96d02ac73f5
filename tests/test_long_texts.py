"""Sorts of long texts: cuts are short, and the order is whole."""

import numpy as np

from modelsort.functions.keys import KeySpec
from modelsort.operators import sorters
from modelsort.plans import cuts


def test_cuts_of_long_texts_are_short_and_keep_their_order():
    texts = sorted(f"{i:04d}é".encode() + b"x" * 10_000 for i in range(40))
    found = cuts._shortened([(1, (t.hex().upper(),), 0) for t in texts])
    short = [bytes.fromhex(t) for _, (t,), _ in found]
    assert short == sorted(set(short)) and max(map(len, short)) <= 6
    assert all(a < c <= b for a, b, c in zip([b"", *texts], texts, short))


def test_sort_of_long_texts(spark):
    texts = [f"same start {i * 7919 % 5003:05d} " + "y" * 500 for i in range(5003)] + ["same start twin"] * 3000
    df = spark.createDataFrame([(t,) for t in texts], "t string").repartition(3)
    frame = sorters.linear_partition_sort(df, KeySpec("t"))
    assert [r["t"] for r in frame.rows().collect()] == sorted(texts)


def test_plans_of_cuts_hold_the_model_once(spark, monkeypatch):
    rng = np.random.default_rng(3)
    texts = ["".join(map(chr, rng.integers(97, 123, 12))) for _ in range(3000)] + ["hot text"] * 9000
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    seen = []
    find = sorters.find_cuts

    def planned(keys, *rest):
        seen.append(keys.where("__bucket in (1, 2)").sampleBy("__bucket", {1: 0.5})._jdf.queryExecution().executedPlan().toString())
        return find(keys, *rest)

    monkeypatch.setattr(sorters, "find_cuts", planned)
    frame = sorters.linear_partition_sort(df, KeySpec("t"))
    assert [r["t"] for r in frame.rows().collect()] == sorted(texts)
    assert seen and all(plan.count("conv(") == 1 for plan in seen)
