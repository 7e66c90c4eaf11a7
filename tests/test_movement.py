"""Kernels against closed forms, the printed figures and bounds (fixtures F1, F3-F7, F13-F16; corrections E1-E7, E29-E31)."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from metricsearch.functions import movement as mv
from metricsearch.functions.metrics import METRICS


def walk(seed, n=None):
    rng = np.random.default_rng(seed)
    n = n or int(rng.integers(1, 25))
    t = np.cumsum(rng.integers(1, 50, n)).astype(float)
    return mv.align(t, *np.cumsum(rng.normal(size=(2, n)), axis=1))


def sampled(u, v, n=200_001):
    s = np.linspace(0, 1, n)
    d = np.hypot(np.interp(s, v[0], v[1]) - np.interp(s, u[0], u[1]), np.interp(s, v[0], v[2]) - np.interp(s, u[0], u[2]))
    return float(((d[1:] + d[:-1]) / 2).mean())


def test_refinement_of_the_figure():
    assert mv.refine([0.1, 0.3, 0.8], [0.1, 0.2, 0.5, 0.7, 0.8]).tolist() == [0.1, 0.2, 0.3, 0.5, 0.7, 0.8]


def test_hull_of_the_figure():
    m = mv.align([0, 3, 4, 5], [0, 2.1, 1, 2.6], [0, 0.9, 1.2, 1.5])
    assert mv.hull(m)[4] == pytest.approx(1.08)
    axis = (np.array([0.0, 1.0]), np.array([0, 2.6]), np.array([0, 1.5]))
    assert mv.sad(m, axis) == pytest.approx(0.36)


def test_closed_forms():
    s = np.array([0.0, 1.0])
    assert mv.sad((s, s, s), (s, s + 3, s + 4)) == pytest.approx(5)
    assert mv.sad((s, s, 0 * s), (s, 1 - s, 0 * s)) == pytest.approx(0.5)
    one = mv.align([7], [0.0], [0.0])
    assert mv.sad(one, (s, 0 * s + 3, 0 * s + 4)) == pytest.approx(5)


def test_alignment():
    assert mv.align([10, 20, 40], [0, 1, 2], [0, 0, 0])[0].tolist() == pytest.approx([0, 1 / 3, 1])
    assert mv.align([0, 1, 2], [0, 3, 3], [0, 0, 1], "spatial")[0].tolist() == pytest.approx([0, 0.75, 1])
    x, y = np.arange(5.0), np.arange(5.0) ** 2
    assert mv.sad(mv.align(np.arange(5), x, y), mv.align(100 + 2 * np.arange(5), x, y)) == 0
    with pytest.raises(ValueError):
        mv.align([0, 1], [0, 1], [0, 1], "speed")


def test_gap_is_closed():
    units = mv.close_gaps([(0, 1, 0, 0, 1, 0), (2, 3, 3, 0, 4, 0)])
    assert units[1] == (1, 2, 1, 0, 3, 0) and len(units) == 3


def test_unaligned_and_other_intervals():
    a = (np.array([0.0, 2.0]), np.zeros(2), np.zeros(2))
    b = (np.array([0.0, 2.0]), np.ones(2), np.zeros(2))
    with pytest.raises(ValueError):
        mv.sad(a, b)
    assert mv.sad_same_interval(a, b) == pytest.approx(1)
    assert mv.sad_same_interval(a, (np.array([0.0, 3.0]), np.ones(2), np.zeros(2))) is None


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10**6), st.integers(0, 10**6), st.integers(0, 10**6))
def test_metric_axioms_and_bounds(i, j, k):
    u, v, w = walk(i), walk(j), walk(k)
    d = mv.sad(u, v)
    assert d >= 0 and d == pytest.approx(mv.sad(v, u)) and mv.sad(u, u) == 0
    assert mv.sad(u, w) <= d + mv.sad(v, w) + 1e-9
    lo, hi = mv.hull_bounds(mv.hull(u), mv.hull(v))
    assert lo - 1e-9 <= d <= hi + 1e-9 and lo >= 0
    for r in (0.3, 1.0, 3.0):
        (a, ea, _), (b, eb, _) = mv.tube(u, r), mv.tube(v, r)
        near = mv.sad(a, b)
        assert abs(near - d) <= min(2 * r, ea + eb) + 1e-9
        assert ea < r / 2 or ea == 0
        gap = np.hypot(np.interp(u[0], a[0], a[1]) - u[1], np.interp(u[0], a[0], a[2]) - u[2])
        assert gap.max() <= r + 1e-9
    m = len(mv.refine(u[0], v[0])) - 1
    assert max(len(u[0]), len(v[0])) - 1 <= m <= len(u[0]) + len(v[0]) - 3


@pytest.mark.parametrize("seed", range(6))
def test_integral_and_moving_distance(seed):
    u, v = walk(seed, 9), walk(seed + 50, 7)
    assert mv.sad(u, v) == pytest.approx(sampled(u, v), abs=1e-5)
    moving = mv.moving_distance(u, v)
    for s in (0.0, 0.31, 0.77, 1.0):
        p = np.hypot(np.interp(s, v[0], v[1]) - np.interp(s, u[0], u[1]), np.interp(s, v[0], v[2]) - np.interp(s, u[0], u[2]))
        assert mv.value_at(moving, s) == pytest.approx(p, abs=1e-6)


def test_many_equals_one_by_one():
    block = mv.flatten([walk(i) for i in range(40)])
    q, m = walk(99), METRICS["sad"]
    assert np.allclose(mv.sad_many(q, block), [mv.sad(q, m.one(block, i)) for i in range(40)])
    u = m.one(block, 3)
    d = np.hypot(q[1][:, None] - u[1], q[2][:, None] - u[2])
    assert METRICS["hausdorff"].many(q, block)[3] == pytest.approx(max(d.min(0).max(), d.min(1).max()))
    assert METRICS["frechet"].many(q, block, [3])[0] >= METRICS["hausdorff"].many(q, block)[3] - 1e-9


def test_empty_word_sets():
    m = METRICS["jaccard"]
    store = m.pack([set(), {"a"}, {"a", "b"}])
    assert m.many(frozenset(), store).tolist() == [0, 1, 1]
    assert m.many(frozenset({"a"}), store).tolist() == pytest.approx([1, 0, 0.5])
