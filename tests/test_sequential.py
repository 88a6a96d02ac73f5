"""Sequential sorts of more rows than a task holds."""

import numpy as np
import pyarrow as pa
import pytest

from modelsort.operators import sorters

RNG = np.random.default_rng(5)
CASES = {
    "normal": RNG.normal(size=40_000),
    "zipf": np.floor(RNG.random(40_000) ** -1.2),
    "late": np.concatenate([np.zeros(20_000), RNG.normal(size=5_000), [1e300, -1e-300, 5e-324] * 800]),
    "ends": RNG.choice([np.inf, -np.inf, 0.0, -0.0, 1.0], 20_000),
    "close": 1.0 + RNG.integers(0, 9_000, 30_000) * 2.0**-52,
    "wide": np.exp(RNG.normal(size=30_000) * 100),
    "ascending": np.arange(30_000.0),
    "alike": np.full(20_000, 3.0),
}


@pytest.mark.parametrize("name", CASES)
@pytest.mark.parametrize("method", sorters.SEQUENTIAL)
def test_pieces_are_small_whole_and_in_order(monkeypatch, method, name):
    monkeypatch.setattr(sorters, "HELD_ROWS", 2_000)
    x = CASES[name]
    batches = (pa.record_batch([pa.array(np.arange(a, min(len(x), a + 500))), pa.array(x[a : a + 500])], names=["id", "key"]) for a in range(0, len(x), 500))
    ids, keys, last = [], [], -np.inf
    for table, alike in sorters.in_pieces(batches, "key", method, 16):
        own = table.column("key").to_numpy()
        assert len(table) <= 2_000 and own.min() >= last and (not alike or own.min() == own.max())
        order = np.arange(len(own)) if alike else sorters.sequential_order(own, method, 16, 256)
        ids, keys, last = [*ids, table.column("id").to_numpy()[order]], [*keys, own[order]], own.max()
    assert np.array_equal(np.concatenate(keys), np.sort(x)) and np.array_equal(np.sort(np.concatenate(ids)), np.arange(len(x)))
    assert np.array_equal(x[np.concatenate(ids)], np.concatenate(keys))


def test_sequential_sort_in_a_task(spark):
    df = spark.range(3_000_000).selectExpr("cast(id * 7919 % 1009 as double) as key", "id")  # over HELD_ROWS
    found = sorters.sequential_sort(df, "key").selectExpr("position - lag(position) over (order by position) as step", "key - lag(key) over (order by position) as up", "id")
    row = found.selectExpr("count(*)", "sum(id)", "max(step)", "min(step)", "min(up)").first()
    assert row[:] == (3_000_000, 3_000_000 * 2_999_999 // 2, 1, 1, 0.0)
