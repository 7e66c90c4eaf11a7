"""Indexes in memory against brute force; corrections E8-E19 and E27, fixtures F2, F8-F12, F14-F15."""

import numpy as np
import pytest

from metricsearch.functions.metrics import METRICS
from metricsearch.plans.baselines import Gnat, Mvpt, Scan
from metricsearch.plans.centers import Counter, assign_pruned, matrix
from metricsearch.plans.tree import ESTIMATES, Node, VoronoiTree, estimate
from metricsearch.plans.workloads import u_turn, utilisation

E = METRICS["euclid"]


def grid(n=14):
    return E.pack([(x, y) for x in range(n) for y in range(n)])


def brute(m, store, q, r):
    return sorted(np.flatnonzero(m.many(q, store) <= r).tolist())


@pytest.mark.parametrize("radius", [0, 1, 2, 5, 30])
def test_border_on_a_grid(radius):
    store = grid()
    tree, others = VoronoiTree(E, store, 4, 8).build(), [Gnat(E, store, leaf=8).build(), Mvpt(E, store, leaf=8).build(), Scan(E, store)]
    for i in range(0, 196, 17):
        q = E.one(store, i)
        want = brute(E, store, q, radius)
        for flags in ({}, {"mode": "batch"}, {"prune": "simple"}, {"order": "none"}, {"tight": True, "report_own": True}, {"nn": False}, {"cover": False}):
            assert sorted(tree.range_search(q, radius, **flags)[0]) == want, flags
        for other in others:
            assert sorted(other.range_search(q, radius)[0]) == want


def test_knn_ways_and_estimates_agree():
    store = E.pack(np.random.default_rng(1).integers(0, 12, (400, 2)).astype(float))
    tree, gnat, mvpt, scan = VoronoiTree(E, store, 4, 10).build(), Gnat(E, store, leaf=10).build(), Mvpt(E, store, leaf=10).build(), Scan(E, store)
    for i in range(0, 400, 31):
        q = E.one(store, i)
        for k in (1, 2, 7, 60):
            want = [x for _, x in scan.knn(q, k)[0]]
            for e in ESTIMATES:
                assert tree.probe_radius(q, k, e) >= scan.knn(q, k)[0][-1][0]
                assert [x for _, x in tree.knn(q, k, name=e)[0]] == want
            for got in (tree.knn(q, k, "best_first"), tree.knn(q, k, "growing", start=0.5), gnat.knn(q, k), mvpt.knn(q, k)):
                assert [x for _, x in got[0]] == want


def test_probe_counts_distinct_objects():
    store = E.pack([(0, 0), (9, 9), (1, 0), (8, 9), (0, 2), (9, 7), (50, 50)])
    tree = VoronoiTree(E, store, 2, 2).build()
    for i in range(7):
        assert len({x for _, x in tree.knn(E.one(store, i), 2)[0]}) == 2
    assert len(tree.knn(E.one(store, 0), 99)[0]) == 7
    with pytest.raises(ValueError):
        tree.knn(E.one(store, 0), 0)


def test_copies_end_and_are_found():
    store = E.pack([(1, 1)] * 20 + [(2, 2)] * 3)
    tree = VoronoiTree(E, store, 3, 4).build()
    assert sorted(tree.range_search(E.one(store, 0), 0)[0]) == list(range(20))
    assert len(tree.knn(E.one(store, 0), 21)[0]) == 21


def test_fixture_cells():
    points = dict(a=(22, 3), b=(-4, 4), c=(21, -5), d=(19, -5), e=(-5, 4), f=(0, 0), g=(-4, 5), h=(-5, 5), i=(-5, -4), j=(1, 21), k=(-4, -4), l=(20, -4), m=(20, 0), n=(0, 20), o=(-4, -5))
    names = list(points)
    store = E.pack(list(points.values()))
    centers = np.array([names.index(c) for c in "fmn"])
    at, _ = assign_pruned(E, store, centers, matrix(E, store, centers, Counter()), np.arange(15), Counter())
    cells = ["".join(n for n, c in zip(names, at, strict=True) if c == j) for j in range(3)]
    assert cells == ["befghiko", "acdlm", "jn"]


def test_invariants():
    store = E.pack(np.random.default_rng(2).random((600, 2)))
    tree = VoronoiTree(E, store, 5, 12).build()
    assert sorted(tree.leaf_entries().tolist()) == list(range(600))
    for node in tree.nodes():
        assert np.allclose(node.pairs, node.pairs.T) and not node.pairs.diagonal().any()
        assert len(node.entries) <= 12 if node.leaf else len(node.kids) == len(node.entries) <= 5
        for j, kid in enumerate(node.kids or []):
            below = tree.leaf_entries(kid)
            d = E.many(E.one(store, int(node.entries[j])), store, below)
            assert node.cover[j] == pytest.approx(d.max())
            assert (d[:, None] <= np.stack([E.many(E.one(store, int(c)), store, below) for c in node.entries], axis=1) + 1e-12).all()
    _, ask = tree.range_search(E.one(store, 0), 9.0)
    assert ask.count < 60  # everything is reported without measuring it


def test_insert_and_delete():
    rng = np.random.default_rng(3)
    store = E.pack(rng.integers(0, 15, (300, 2)).astype(float))
    tree = VoronoiTree(E, store, 4, 8).build(np.arange(150))
    for i in range(150, 300):
        tree.insert(i)
    gone = set(rng.choice(300, 200, replace=False).tolist())
    for i in sorted(gone):
        assert tree.delete(i)
    assert not tree.delete(next(iter(gone)))
    left = [i for i in range(300) if i not in gone]
    assert sorted(tree.expand(tree.leaf_entries())) == left
    for i in left[::9]:
        q = E.one(store, i)
        d = E.many(q, store, np.array(left))
        assert sorted(tree.range_search(q, 3)[0]) == [x for x, y in zip(left, d, strict=True) if y <= 3]
        assert [x for _, x in tree.knn(q, len(left) - 1)[0]] == [left[j] for j in np.lexsort((left, d))][: len(left) - 1]
    for i in left:
        assert tree.delete(i)
    assert tree.root is None and tree.range_search((0, 0), 5)[0] == {}
    tree.insert(5)
    assert tree.expand(tree.leaf_entries()) == [5]


def test_estimates_and_measures():
    assert [estimate(e, 5.0, 3.0, 1.0) for e in ESTIMATES] == [1, 2, 3, 4, 5, 6, 7, 8, 9]
    assert utilisation([4, 4, 2]) == pytest.approx(10 / 12)
    assert [6110 - 4064, 7932 - 3008, 10114 - 2061, 16829 - 786] == [2046, 4924, 8053, 16043]
    assert u_turn({1: 5, 2: 9, 3: 4}) == 2
    assert Node([0], np.zeros((1, 1)), [0]).coordinates.shape == (1, 1)


def test_shapes_of_cost():
    store = E.pack(np.random.default_rng(4).random((4000, 2)))
    tree = VoronoiTree(E, store, 36, 100).build()
    counts = {r: np.mean([tree.range_search(E.one(store, i), r, eager=True)[1].count for i in range(0, 4000, 400)]) for r in (0.01, 0.1, 0.3, 0.6, 1.5)}
    assert 0.01 < u_turn(counts) < 1.5 and counts[1.5] < counts[0.3] / 2
