"""Indexes and scans the tree is compared with: GNAT, MVPT and the sequential scan."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import count

import numpy as np

from ..functions.metrics import Ask, Metric
from .centers import Counter, choose
from .tree import EPS

PAIRS = 50_000  # pairs of a query and an object that are measured at once


class Scan:
    """Every object is measured."""

    def __init__(self, metric: Metric, store):
        self.metric, self.store = metric, store

    def build(self) -> Scan:
        return self

    def range_search(self, q, r: float, eager: bool = False):
        ask = Ask(self.metric, self.store, q, eager)
        d = ask.ds(np.arange(self.metric.size(self.store)))
        return {int(i): float(d[i]) for i in np.flatnonzero(d <= r)}, ask

    def knn(self, q, k: int, eager: bool = False):
        ask = Ask(self.metric, self.store, q, eager)
        d = ask.ds(np.arange(self.metric.size(self.store)))
        order = np.lexsort((np.arange(len(d)), d))[:k]
        return [(float(d[i]), int(i)) for i in order], {"search": ask.count, "total": ask.count}


class _BestFirst:
    """Range and k-nearest search over nodes that give lower bounds for their children."""

    root = None

    def range_search(self, q, r: float, eager: bool = False):
        ask, found = Ask(self.metric, self.store, q, eager), {}
        stack = [(self.root, [])] if self.root is not None else []
        while stack:
            node, path = stack.pop()
            objects, kids = self._open(node, path, ask, lambda: r)
            found.update({i: d for i, d in objects if d <= r})
            stack += [(kid, way) for bound, kid, way in kids if bound <= r + EPS * (1 + r)]
        return found, ask

    def range_search_all(self, qs: np.ndarray, r: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(query positions, object positions, distances) within each query's r, for metrics on vectors. Each node is
        opened once, for all queries that reach it; what is measured is the same as query by query."""
        reach = r + EPS * (1 + r)
        stack = [(self.root, np.arange(len(qs)), np.zeros((len(qs), 0)))] if self.root is not None and len(qs) else []
        while stack:
            node, at, path = stack.pop()
            if node[0] == "leaf":
                step = max(1, PAIRS // max(1, len(node[1])))
                for first in range(0, len(at), step):
                    own = at[first : first + step]
                    i, j = np.nonzero(self._near(node, path[first : first + step], reach[own]))
                    for a in range(0, len(i), PAIRS):
                        asked, found = own[i[a : a + PAIRS]], node[1][j[a : a + PAIRS]]
                        d = self.metric.pairs(qs[asked], self.store[found])
                        hit = d <= r[asked]
                        yield asked[hit], found[hit], d[hit]
                continue
            objects, kids = self._open_all(node, at, path, qs, reach)
            for point, asked, d in objects:
                hit = d <= r[asked]
                yield asked[hit], np.full(hit.sum(), point), d[hit]
            stack += [(kid, at[some], way[some]) for some, kid, way in kids if some.any()]

    def _near(self, node, path, reach):
        """Which pairs of these queries (rows) and the leaf's objects (columns) are to be measured."""
        return np.ones((len(reach), len(node[1])), bool)

    def knn(self, q, k: int, eager: bool = False, within: float = np.inf):
        """The k nearest (distance, position); of those beyond ``within``, some may be missing."""
        ask, tick, best = Ask(self.metric, self.store, q, eager), count(), []
        limit = lambda: min(within, -best[0][0]) if len(best) >= k else within
        queue = [(0.0, next(tick), self.root, [])] if self.root is not None else []
        while queue:
            bound, _, node, path = heapq.heappop(queue)
            if bound > limit() + EPS * (1 + limit()):
                break
            objects, kids = self._open(node, path, ask, limit)
            for i, d in objects:
                heapq.heappush(best, (-d, -i))
                if len(best) > k:
                    heapq.heappop(best)
            for b, kid, way in kids:
                heapq.heappush(queue, (max(bound, b), next(tick), kid, way))
        return sorted((-a, -b) for a, b in best), {"search": ask.count, "total": ask.count}


class Gnat(_BestFirst):
    """Split points with, for each pair, the interval of distances from one to the other's cell."""

    def __init__(self, metric: Metric, store, k: int = 4, leaf: int = 100, seed: int = 1):
        self.metric, self.store, self.k, self.l = metric, store, k, leaf
        self.rng, self.counter = np.random.default_rng(seed), Counter()

    def build(self) -> Gnat:
        self.root = self._grow(np.arange(self.metric.size(self.store)))
        return self

    def _grow(self, index):
        top = [None]
        todo = [(index, top, 0)]
        while todo:  # not by recursion: cells of one split point over may be deep
            index, above, place = todo.pop()
            splits = choose(self.metric, self.store, index, self.k, "greedy", self.rng, self.counter) if len(index) > self.l else index[:1]
            if len(index) <= self.l or len(splits) < 2:
                above[place] = ("leaf", index)
                continue
            rest = index[~np.isin(index, splits)]
            d = np.stack([self.counter.many(self.metric, self.store, s, rest) for s in splits])
            at = self._nearest(d)
            between = np.stack([self.counter.many(self.metric, self.store, s, splits) for s in splits])
            low, high = between.copy(), between.copy()
            for j in range(len(splits)):
                own = d[:, at == j]
                if own.size:
                    low[:, j], high[:, j] = np.minimum(low[:, j], own.min(axis=1)), np.maximum(high[:, j], own.max(axis=1))
            kids = [None] * len(splits)
            above[place] = ("inner", splits, low, high, kids)
            todo += [(rest[at == j], kids, j) for j in reversed(range(len(splits))) if (at == j).any()]
        return top[0]

    @staticmethod
    def _nearest(d):
        """The nearest split point of each object. Objects between several of them are dealt to these in turn: where
        most distances are the same, one cell would else get nearly all objects, level after level."""
        tied = d == d.min(axis=0)
        n = tied.sum(axis=0)
        return (tied & (tied.cumsum(axis=0) == np.arange(d.shape[1]) % n + 1)).argmax(axis=0)

    def _open(self, node, path, ask, limit):
        if node[0] == "leaf":
            return list(zip(node[1].tolist(), ask.ds(node[1]).tolist(), strict=True)), []
        _, splits, low, high, kids = node
        bounds, objects = np.zeros(len(splits)), []
        for i, s in enumerate(splits.tolist()):
            r = limit()
            if bounds[i] > r + EPS * (1 + r):
                continue  # its whole cell, itself included, is out of reach
            d = ask.d(s)
            objects.append((s, d))
            bounds = np.maximum(bounds, np.maximum(low[i] - d, d - high[i]))
        return objects, [(float(bounds[j]), kid, path) for j, kid in enumerate(kids) if kid is not None]

    def _open_all(self, node, at, path, qs, reach):
        _, splits, low, high, kids = node
        bounds, objects, within = np.zeros((len(at), len(splits))), [], reach[at]
        for i, s in enumerate(splits.tolist()):
            some = np.flatnonzero(~(bounds[:, i] > within))
            d = self.metric.many(self.store[s], qs, at[some])
            objects.append((s, at[some], d))
            bounds[some] = np.maximum(bounds[some], np.maximum(low[i] - d[:, None], d[:, None] - high[i]))
        return objects, [(bounds[:, j] <= within, kid, path) for j, kid in enumerate(kids) if kid is not None]


class Mvpt(_BestFirst):
    """Vantage points with shells of equal size; leaves keep the distances to the vantage points above them."""

    def __init__(self, metric: Metric, store, shells: int = 4, leaf: int = 100, vantage: int = 1, seed: int = 1):
        self.metric, self.store, self.m, self.l, self.v = metric, store, shells, leaf, vantage
        self.rng, self.counter = np.random.default_rng(seed), Counter()

    def build(self) -> Mvpt:
        n = self.metric.size(self.store)
        self.root = self._grow(np.arange(n), np.zeros((n, 0)))
        return self

    def _grow(self, index, path):
        if len(index) <= self.l:
            return ("leaf", index, path)
        at = int(self.rng.integers(len(index)))
        point = int(index[at])
        keep = np.arange(len(index)) != at
        index, path = index[keep], path[keep]
        d = self.counter.many(self.metric, self.store, point, index)
        if d.max(initial=0.0) == d.min(initial=0.0):
            return ("inner", point, [(float(d.min(initial=0.0)), float(d.max(initial=0.0)), ("leaf", index, np.column_stack([path, d])))])
        order = np.argsort(d, kind="stable")
        shells = []
        for part in np.array_split(order, self.m):
            if len(part):
                shells.append((float(d[part].min()), float(d[part].max()), self._grow(index[part], np.column_stack([path[part], d[part]]))))
        return ("inner", point, shells)

    def _open(self, node, path, ask, limit):
        if node[0] == "leaf":
            _, index, stored = node
            r = limit()
            if stored.shape[1] and np.isfinite(r):
                near = np.abs(stored - np.array(path)[None, :]).max(axis=1) <= r + EPS * (1 + r)
                index = index[near]
            return list(zip(index.tolist(), ask.ds(index).tolist() if len(index) else [], strict=True)), []
        _, point, shells = node
        d = ask.d(point)
        return [(point, d)], [(max(low - d, d - high, 0.0), kid, [*path, d]) for low, high, kid in shells]

    def _open_all(self, node, at, path, qs, reach):
        _, point, shells = node
        d = self.metric.many(self.store[point], qs, at)
        way = np.column_stack([path, d])
        return [(point, at, d)], [(np.maximum(np.maximum(low - d, d - high), 0.0) <= reach[at], kid, way) for low, high, kid in shells]

    def _near(self, node, path, reach):
        near = super()._near(node, path, reach)
        for known, own in zip(node[2].T, path.T, strict=True):
            near &= np.abs(known[None, :] - own[:, None]) <= reach[:, None]
        return near
