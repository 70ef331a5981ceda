"""Rank rules, selection kernels, cost model and intervals: no Spark."""

import math
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from exactrank.functions import kernels
from exactrank.functions.ranks import rank_gap, target_rank
from exactrank.plans.costmodel import METHODS, predict, sketch_dominates_at, suggest_eps
from exactrank.plans.ledger import ci95


def test_rules():
    assert [target_rank(10, q).low for q in ("0.25", "0.3", "0.5", "0.75", "0.99", "1")] == [2, 2, 4, 7, 9, 9]
    assert target_rank(30, "0.1").low == 2 and target_rank(30, 0.1).low == 2  # 3, not 3.0000000004
    assert target_rank(0, "0.5") is None
    assert [target_rank(10, q, "floor0").low for q in ("0", "0.5", "1")] == [0, 5, 9]
    t = target_rank(10, "0.5", "midpoint")
    assert (t.low, t.high, t.weight) == (4, 5, Fraction(1, 2))
    t = target_rank(11, "0.25", "linear")
    assert (t.low, t.high, t.weight) == (2, 3, Fraction(1, 2))
    assert target_rank(1, "0.7", "linear").low == 0
    for bad in (lambda: target_rank(5, "1.1"), lambda: target_rank(5, "0.5", "none")):
        with pytest.raises(ValueError):
            bad()


def test_gap_with_ties_stops_where_the_literal_one_goes_on():
    # The tie-heavy worked examples: the pivot itself is the answer.
    assert rank_gap(300000, 288006, 12021) == ("hit", 0)
    assert rank_gap(5000, 4998, 4) == ("hit", 0)
    assert 300000 - 288006 == 11994 and 5000 - 4998 == 2


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 12), min_size=1, max_size=60), st.integers(-1, 13), st.data())
def test_the_gap_leads_to_the_answer_for_any_pivot(values, pivot, data):
    ordered = sorted(values)
    k = data.draw(st.integers(0, len(values) - 1))
    side, d = rank_gap(k, sum(v < pivot for v in values), sum(v == pivot for v in values))
    if side == "hit":
        assert pivot == ordered[k]
    elif side == "right":
        assert [v for v in ordered if v > pivot][d - 1] == ordered[k]
    else:
        assert [v for v in ordered if v < pivot][-d] == ordered[k]


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(-50, 50), min_size=1, max_size=400), st.data())
def test_selection_kernels(values, data):
    a = np.array(values)
    k = data.draw(st.integers(0, len(a) - 1))
    want = np.sort(a)[k]
    assert kernels.quickselect(a, k) == kernels.median_of_medians(a, k) == kernels.sample_select(a, k) == want


@settings(max_examples=100, deadline=None)
@given(st.lists(st.lists(st.integers(-9, 9), max_size=30), min_size=1, max_size=8), st.integers(1, 20), st.sampled_from(["left", "right"]))
def test_nearest_buffer_is_a_sorted_slice_in_bounded_memory(batches, d, side):
    b = kernels.NearestBuffer(d, side)
    for x in batches:
        b.add(pa.array(x, pa.int64()))
    ordered = sorted(v for x in batches for v in x)
    want = ordered[:d] if side == "right" else ordered[-d:]
    got = b.result()
    assert sorted(got.to_pylist() if got is not None else []) == want
    assert b.peak <= 2 * d + 30


def test_three_way_and_reservoir():
    import random

    below, equal, above = kernels.three_way(pa.array([3, 1, 2, 2, 5]), pa.scalar(2))
    assert (below.to_pylist(), equal, above.to_pylist()) == ([1], 2, [3, 5])
    counts = {v: 0 for v in range(6)}
    for seed in range(3000):
        r = kernels.Reservoir(random.Random(seed))
        for part in ([0], [1, 2], [3, 4, 5]):
            r.add(pa.array(part))
        counts[r.value.as_py()] += 1
    # Chi-square with 5 degrees of freedom, 99.9 %.
    assert sum((c - 500) ** 2 / 500 for c in counts.values()) < 20.5


def test_cost_model_and_eps():
    small, large = (predict("guided", n, 120) for n in (1e8, 1e9))
    assert small["rounds"] == large["rounds"] == 3 and large["shuffles"] == 0
    sort = predict("full_sort", 1e9, 120)
    assert sort["shuffles"] == 1 and sort["network"] > large["network"] / 120 and sort["exec_time"] > 1e9 / 120
    assert predict("prune_tree", 1e9, 120)["rounds"] > 20
    assert all(predict(m, 1e7, 40)["work"] > 0 for m in METHODS)
    assert 2350 < sketch_dominates_at(0.01, 50_000) < 2353
    eps, levels = suggest_eps(10**13, 800_000)
    assert 4 * eps * 10**13 * (4 * eps) ** (levels - 1) <= 1_000_000 and levels <= 3
    assert suggest_eps(0, 1) == (0.01, 1)


def test_intervals():
    mean, low, high = ci95([1.0, 2.0, 3.0])
    assert mean == 2 and math.isclose(high - mean, 4.303 / math.sqrt(3), rel_tol=1e-6) and low < mean
    assert ci95([5.0]) == (5.0, 5.0, 5.0)
