"""Rank summaries: invariants, error bounds, sizes, merging in any shape."""

import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from exactrank.functions.summaries import AdaptiveSummary, BufferedSummary, RankSummary, RegularSample, StreamSummary, fold_left, merge, tree_merge

SHAPES = {
    "uniform": lambda r, n: r.random(n), "ties": lambda r, n: r.integers(0, 7, n).astype(float), "sorted": lambda r, n: np.sort(r.random(n)),
    "reversed": lambda r, n: np.sort(r.random(n))[::-1], "constant": lambda r, n: np.zeros(n), "tail": lambda r, n: r.exponential(1, n),
    "two": lambda r, n: r.integers(0, 2, n).astype(float), "waves": lambda r, n: np.sin(np.arange(n)),
}
MAKERS = {"stream": StreamSummary, "buffered": lambda e: BufferedSummary(e, 300, 50), "adaptive": AdaptiveSummary}


def check(s: RankSummary, values: np.ndarray, eps: float) -> None:
    ordered = np.sort(values)
    assert s.n == len(values) == s.g.sum() and (np.diff(s.v) >= 0).all()
    assert s.v[0] == ordered[0] and s.v[-1] == ordered[-1]
    assert s.worst() <= max(1, math.floor(2 * eps * s.n))
    for k in {0, s.n - 1, *range(0, s.n, max(1, s.n // 37))}:
        x = s.query(k)
        low, high = np.searchsorted(ordered, x), np.searchsorted(ordered, x, "right") - 1
        assert max(0, low - k, k - high) <= eps * s.n + 1, (k, x)


@pytest.mark.parametrize("shape", SHAPES)
@pytest.mark.parametrize("kind", MAKERS)
def test_bounds_on_every_shape(kind, shape):
    values = SHAPES[shape](np.random.default_rng(3), 3000)
    s = MAKERS[kind](0.02)
    s.insert_many(values)
    check(s.summary(), values, 0.02)


def test_sizes_flushes_and_compressions():
    values = np.random.default_rng(5).random(40_000)
    s = BufferedSummary(0.01, 5000, 1000)
    s.insert_many(values[:39_000])
    s.summary()
    assert s.flushes == math.ceil(39_000 / 5000)
    small = StreamSummary(0.05)
    small.insert_many(values[:5000].tolist())
    assert len(small.summary()) <= (1 / 0.05) * math.log2(0.05 * 5000) + 1
    a = AdaptiveSummary(0.01, 2.0)
    a.insert_many(values)
    assert len(a.summary()) <= (1 / 0.01) * math.log2(0.01 * 40_000) + 1
    assert a.head > 2 * a.start and a.compressions < 40_000 / 64 / 2  # the buffer has grown
    with pytest.raises(ValueError):
        AdaptiveSummary(0.01, 1.0)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 40), max_size=120), min_size=1, max_size=9), st.integers(0, 10**6))
def test_merging_in_any_tree_keeps_the_bound(parts, seed):
    eps = 0.05
    arrays = [np.array(p, float) for p in parts if p]
    if not arrays:
        return
    every = np.concatenate(arrays)
    sums = [RankSummary.exact(a, eps).compress() for a in arrays]
    check(fold_left(sums), every, eps)
    check(tree_merge(sums), every, eps)
    rng, left = random.Random(seed), list(sums)
    while len(left) > 1:
        a, b = left.pop(rng.randrange(len(left))), left.pop(rng.randrange(len(left)))
        left.append(merge(a, b))
    check(left[0], every, eps)
    back = RankSummary.from_bytes(left[0].to_bytes())
    assert back.n == left[0].n and (back.v == left[0].v).all() and (back.g == left[0].g).all()


def test_rank_bounds_hold():
    values = np.random.default_rng(9).integers(0, 500, 5000).astype(float)
    s = BufferedSummary(0.01, 500, 100)
    s.insert_many(values)
    done = s.summary()
    for x in (0.0, 3.0, 250.0, 499.0, 1000.0, -1.0):
        low, high = done.rank(x)
        assert low <= (values <= x).sum() <= high


def test_regular_sample_of_101_points():
    s = RegularSample(np.arange(101), 5)
    assert len(s.kept) == 21
    assert all(abs(s.rank(x) - x) <= 5 for x in range(101))
