"""Queries over whole tables, and unmatched rows of the joins in small fixtures."""

from collections import Counter

import duckdb
import numpy as np
import pytest

from modelsort import catalog
from modelsort.functions import sampling
from modelsort.functions.models import LinearBucket, SplitterTree
from modelsort.functions.models.linear import lsq_distributed, min_max_distributed
from modelsort.operators import joins

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in ("customer", "supplier", "orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return con


@pytest.mark.parametrize("how", joins.HOW)
def test_merge_join_queries_take_all_rows(spark, duck, how):
    wanted = {"left_semi": "SELECT count(*) FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)", "left_anti": "SELECT count(*) FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)"}
    sql = wanted.get(how, f"SELECT count(*) FROM orders {how} JOIN lineitem ON o_orderkey = l_orderkey")
    assert catalog.queries()[f"model_merge_join_{how}"](spark, DATA).count() == duck.execute(sql).fetchone()[0]


@pytest.mark.parametrize("name", ["salted_join", "hash_join"])
def test_other_joins_take_all_rows(spark, duck, name):
    assert catalog.queries()[name](spark, DATA).count() == duck.execute("SELECT count(*) FROM orders JOIN lineitem ON o_orderkey = l_orderkey").fetchone()[0]


@pytest.mark.parametrize("name", ["rmi_lookup", "binary_search_lookup"])
def test_lookups_ask_for_all_keys(spark, duck, name):
    assert catalog.queries()[name](spark, DATA).count() == duck.execute("SELECT count(*) FROM customer").fetchone()[0]


@pytest.mark.parametrize("name", ["asof_join_backward", "asof_join_by_user", "asof_join_forward_tolerance"])
def test_asof_joins_take_all_rows(spark, duck, name):
    found = catalog.queries()[name](spark, DATA)
    assert {r["event_id"] for r in found.collect()} == {r[0] for r in duck.execute("SELECT event_id FROM events").fetchall()}


def test_stream_interval_join_takes_all_pairs(spark, duck):
    found = {tuple(r) for r in catalog.queries()["stream_interval_join"](spark, DATA).select("event_id", "other").collect()}
    ev = duck.execute("SELECT event_id, user_id, epoch(ts) FROM events").fetchall()
    assert found == {(a, b) for a, u, t in ev for b, v, s in ev if u == v and t - 3600 <= s <= t}


@pytest.mark.parametrize("how", joins.HOW)
def test_unmatched_rows_of_merge_joins(spark, how):
    left, right = [(k, (k or 0) * 10) for k in (1, 2, 2, 3, 5, None)], [(k, -k) for k in (2, 3, 3, 4, 7)]
    a, b = spark.createDataFrame(left, "k long, x long"), spark.createDataFrame(right, "k long, y long")
    pairs = [(k, x, y) for k, x in left for j, y in right if k == j]
    matched = {k for k, _, _ in pairs}
    lonely, strangers = [(k, x) for k, x in left if k not in matched], [(k, y) for k, y in right if k not in matched]
    wanted = {
        "inner": pairs,
        "left": pairs + [(k, x, None) for k, x in lonely],
        "right": pairs + [(k, None, y) for k, y in strangers],
        "full": pairs + [(k, x, None) for k, x in lonely] + [(k, None, y) for k, y in strangers],
        "left_semi": [r for r in left if r[0] in matched],
        "left_anti": lonely,
    }[how]
    assert Counter(tuple(r) for r in joins.merge(a, b, "k", how).collect()) == Counter(wanted)


def test_theta_join_takes_all_suppliers(spark):
    data = "/root/testdata/sf0.01"  # the smallest size with more than 20 suppliers
    found = catalog.queries()["theta_join"](spark, data).groupBy("s_suppkey").count()
    wanted = duckdb.execute(f"SELECT s_suppkey, count(*) FROM '{data}/customer.parquet' JOIN '{data}/supplier.parquet' ON c_acctbal < s_acctbal GROUP BY 1").fetchall()
    assert {tuple(r) for r in found.collect()} == set(wanted) and len(wanted) > 20


@pytest.mark.parametrize("op", ["<", "<=", ">", ">="])
def test_theta_join_equals_brute_force(spark, op):
    left, right = [1.0, 2.0, 2.0, 7.5, -3.0, None, float("nan")], [2.0, 0.0, 7.5, None, 100.0, float("nan")]
    a, b = spark.createDataFrame(list(enumerate(left)), "i long, x double"), spark.createDataFrame(list(enumerate(right)), "j long, y double")
    test = {"<": lambda x, y: x < y, "<=": lambda x, y: x <= y, ">": lambda x, y: x > y, ">=": lambda x, y: x >= y}[op]
    wanted = {(i, j) for i, x in enumerate(left) for j, y in enumerate(right) if x is not None and y is not None and test(x, y)}
    found = joins.theta(a, b, "x", "y", op).select("i", "j").collect()
    assert {tuple(r) for r in found} == wanted and len(found) == len(wanted)


def least_conflict(keys, k):
    """Least feasible degree by trying each."""
    s = len(keys)
    for d in range(1, s // 3 + 1):
        width = (keys[s - 1 - d] - keys[d]) / (k - 2)
        if d == s // 3 or (keys[d:] - keys[: s - d]).min() >= width:
            return d, 1 / width, 1 - keys[d] / width


def test_distributed_fits_take_the_column(spark, duck):
    keys = np.array(duck.execute("SELECT value FROM events ORDER BY value").fetchnumpy()["value"])
    row = catalog.queries()["min_conflict_fit_value"](spark, DATA).first()
    assert tuple(row) == pytest.approx(least_conflict(keys, 256))
    row = catalog.queries()["lsq_fit_value"](spark, DATA).first()
    line = LinearBucket.fit_lsq(keys, 256)
    assert tuple(row) == pytest.approx((line.slope, line.intercept), abs=1e-6)
    row = catalog.queries()["minmax_fit_value"](spark, DATA).first()
    assert tuple(row) == pytest.approx((256 / (keys[-1] - keys[0]), -256 / (keys[-1] - keys[0]) * keys[0]))


def test_distributed_fits_of_awkward_columns(spark):
    for values in ([], [None], [3.0], [3.0, 3.0, None]):
        df = spark.createDataFrame([(v,) for v in values], "value double")
        assert lsq_distributed(df, "value", 8).buckets == min_max_distributed(df, "value", 8).buckets == 1


@pytest.mark.parametrize(("t", "x"), [("events", "value"), ("documents", "n_chars"), ("customer", "c_acctbal")])
def test_fits_take_the_sample_of_the_sorters(spark, t, x):
    sample = catalog.drawn(spark, DATA, t, x)
    n = spark.read.parquet(f"{DATA}/{t}.parquet").count()
    assert 0.8 * min(n, sampling.sample_size(n, 256)) < len(sample) <= sampling.sample_size(n, 256)
    row = catalog.queries()[f"min_conflict_fit_{x}_sampled"](spark, DATA).first()
    line = LinearBucket.fit_min_conflict(sample, 256)
    assert tuple(row) == pytest.approx((line.conflict, line.slope, line.intercept))
    assert row["conflict"] == least_conflict(sample, 256)[0]


def test_sampled_models_are_fitted_on_random_keys(spark):
    sample = catalog.drawn(spark, DATA)
    query = lambda name: [tuple(r) for r in catalog.queries()[name](spark, DATA).collect()]
    line = LinearBucket.fit_balanced(sample, 256)
    assert query("balanced_fit_value") == [(line.slope, line.intercept)]
    assert query("splitters_value_sampled") == [(x,) for x in SplitterTree.fit(catalog.drawn(spark, DATA, k=16), 16).splitters]
    assert sum(r[1] for r in query("bucket_histogram_rmi")) == 1000 and query("monotone_repair") == [(0,)]
    assert len(query("rmi_tuning")) > 0
