"""Bucket models against brute force and their own invariants."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from modelsort.functions.keys import order_bits_np
from modelsort.functions.models import Composite, EcdfBucket, LinearBucket, RadixBucket, Rmi, SplitterTree, WithHeavy, tune_rmi
from modelsort.functions.models.linear import FITS
from modelsort.functions.sampling import alpha, equidistant, heavy_keys, sample_size
from modelsort.operators import blocks, sorters

FLOATS = st.lists(st.floats(-1e6, 1e6, allow_nan=False), min_size=1, max_size=200)


def brute_degree(sample, k):
    s = len(sample)
    for d in range(1, s // 3 + 1):
        if min(sample[i + d] - sample[i] for i in range(s - d)) >= (sample[s - 1 - d] - sample[d]) / (k - 2):
            return d
    return s // 3


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(-(10**6), 10**6), min_size=6, max_size=120, unique=True), st.integers(3, 64))
def test_min_conflict_finds_least_degree(values, k):
    sample = np.sort(np.array(values, float))
    line = LinearBucket.fit_min_conflict(sample, k)
    if line.conflict is None:
        return
    d, s = line.conflict, len(sample)
    assert d == brute_degree(sample, k) and d <= s // 3
    scale = max(1.0, abs(line.slope) * max(abs(sample[0]), abs(sample[-1])))
    assert line.slope * sample[d] + line.intercept == pytest.approx(1, abs=1e-6 * scale)
    assert line.slope * sample[s - 1 - d] + line.intercept == pytest.approx(k - 1, abs=1e-6 * scale)
    assert np.bincount(line.predict(sample)).max() <= -(-s // 3) + 2


@settings(max_examples=60, deadline=None)
@given(FLOATS, st.sampled_from(sorted(FITS)), st.integers(1, 40))
def test_lines_never_fall(values, fit, k):
    sample = np.sort(np.array(values))
    line = FITS[fit](sample, k)
    assert (np.diff(line.predict(sample)) >= 0).all()
    assert line.predict(sample).min() >= 0 and line.predict(sample).max() < line.buckets
    assert (line.mirrored().predict(sample) == line.k - 1 - line.predict(sample)).all()


@settings(max_examples=60, deadline=None)
@given(FLOATS, st.integers(2, 20))
def test_heavy_keys_get_buckets_of_their_own(values, k):
    x = np.sort(np.array([round(v) % 13 for v in values], float))
    model = WithHeavy(LinearBucket.fit_min_max(x, k), heavy_keys(x, k))
    found = model.predict(x)
    assert (np.diff(found) >= 0).all() and found.max() < model.buckets
    for b in model.equality_buckets():
        assert len(np.unique(x[found == b])) == 1


def test_bad_lines_are_refused():
    for slope, intercept in ((-1.0, 0.0), (float("nan"), 0.0), (1.0, float("inf"))):
        with pytest.raises(ValueError):
            LinearBucket(slope, intercept, 4)


def test_degenerate_samples_give_constants():
    for sample in (np.zeros(0), np.full(9, 3.0)):
        assert all(f(sample, 8).buckets == 1 for f in FITS.values())
    assert LinearBucket.fit_min_conflict(np.array([1.0, 2.0, 3.0]), 16).buckets == 16
    assert LinearBucket.fit_min_conflict(np.array([1.0, 2, 3, 4, 5]), 2).buckets == 2


def test_worked_example_states():
    keys = [18, 39, 33, 28, 25, 34, 11, 27, 47, 2, 48, 50, 10, 6, 36, 13, 9, 12, 22, 29]
    line = LinearBucket(0.15, -1.55, 4)
    assert line.predict(np.array(keys, float)).tolist() == [1, 3, 3, 2, 2, 3, 0, 2, 3, 0, 3, 3, 0, 0, 3, 0, 0, 0, 1, 2]
    found = blocks.classify([float(k) for k in keys], line, 2)
    assert found.sizes == [7, 2, 4, 7] and sum((s - 5) ** 2 for s in found.sizes) == 18
    assert found.left == {0: [12.0], 3: [36.0]} and found.peak <= 8
    own = LinearBucket.fit_min_conflict(np.sort(np.array(keys, float)), 4)
    assert own.conflict == 6 and own.slope == pytest.approx(0.1) and own.intercept == pytest.approx(-0.3)


def test_tree_sends_equal_keys_left_and_to_equality_buckets():
    tree = SplitterTree(np.array([1.0, 2.0, 3.0]), np.array([2.0]))
    assert tree.predict(np.array([0.5, 1.0, 1.5, 2.0, 2.5, 3.0, 9.0])).tolist() == [0, 0, 1, 2, 3, 3, 4]
    assert tree.equality_buckets() == {2}
    assert len(equidistant(np.arange(100.0), 8)) == 7


def test_radix_and_order_bits():
    x = np.array([-np.inf, -5.5, -0.0, 0.0, 1e-300, 7.25, 1e300, np.inf, np.nan])
    bits = order_bits_np(x)
    assert (np.diff(bits.astype(float)) >= 0).all() and bits[2] == bits[3]
    model = RadixBucket.fit(float(-(2**62)), float(2**62), 8)
    assert (np.diff(model.predict(np.linspace(-(2.0**62), 2.0**62, 999))) >= 0).all()
    assert sorters.small_radix_sort(np.array([3.5, -1.0, 0.0, -7.25, 3.25])).tolist() == [-7.25, -1.0, 0.0, 3.25, 3.5]
    assert sorters.small_radix_sort(np.array([5, -3, 2**40, -(2**50), 0])).tolist() == [-(2**50), -3, 0, 5, 2**40]


@settings(max_examples=40, deadline=None)
@given(st.lists(st.floats(-1e3, 1e3, allow_nan=False), min_size=5, max_size=300), st.sampled_from(["spline", "lsq"]))
def test_repaired_rmi_is_monotone(values, leaf):
    sample = np.sort(np.array(values))
    model = Rmi.two_level(sample, 8, leaf=leaf).monotone(sample)
    probe = np.sort(np.concatenate([sample, np.linspace(sample[0] - 1, sample[-1] + 1, 101)]))
    assert (np.diff(model.predict(probe)) >= -1e-12).all()
    assert (np.diff(EcdfBucket(model, 16).predict(probe)) >= 0).all()


@pytest.mark.parametrize("leaf", ["spline", "lsq"])
def test_repaired_rmi_of_keys_too_close_for_a_line(leaf):
    for sample in (np.array([0.0, 5e-324, 1e-320, 1.0, 2.0]), np.array([-1e308, 0.0, 5e-324, 1e-300, 1e308]), np.array([0.0, 0.0, 1e-310, 1e-310, 2e-310])):
        model = Rmi.two_level(sample, 8, leaf=leaf).monotone(sample)
        assert (np.diff(model.predict(sample)) >= 0).all()


def test_rmi_levels_and_tuning():
    sample = np.sort(np.random.default_rng(1).normal(size=2000))
    exact = np.arange(2000) / 2000
    error = [np.abs(Rmi.fit(sample, w, ["spline"] * len(w)).predict(sample) - exact).mean() for w in ([1], [1, 64], [1, 8, 64])]
    assert error[1] < error[0] / 5 and error[2] < error[0] / 5
    assert Rmi.two_level(sample, 4000).empty_leaves() > 0.1
    table = tune_rmi(sample, (8, 64))
    assert table[0]["mean_error"] <= table[-1]["mean_error"]


def test_composite_numbers_children_densely():
    root = LinearBucket(1.0, 0.0, 4)
    model = Composite(root, {1: LinearBucket(10.0, -10.0, 10)})
    assert model.buckets == 13
    assert model.predict(np.array([0.5, 1.0, 1.95, 2.0, 3.5])).tolist() == [0, 1, 10, 11, 12]


def test_oversampling():
    assert alpha(1 << 20) == pytest.approx(4.0)
    assert sample_size(1 << 20, 256) == 1023
