"""Voronoi tree over objects in one store: build, range and k-nearest-neighbour search, inserts and deletes.

A node holds entries (objects), all distances between them, and the distances to two of them (pivots). An inner node's
entries are the centres of cells; each has a child over its cell and a cover radius. Routing centres occur again
within their own cells; results are leaf entries alone. Comparisons are closed, with a slack of ``EPS`` for rounding
wherever an object is dropped or accepted without measuring it, so results equal those of a scan.
"""

from __future__ import annotations

import heapq
from itertools import count

import numpy as np

from ..functions.metrics import Ask, Metric
from .centers import Counter, assign_pruned, choose, matrix

EPS = 1e-9
FAR = 1e200  # stands for an infinite radius
ESTIMATES = {f"DE{i}": (i // 3, i % 3 - 1) for i in range(9)}


def estimate(name: str, d: np.ndarray | float, pair: np.ndarray | float, cover: np.ndarray | float):
    """Key of a subtree in the radius probe: one of three bases, minus, without or plus the cover radius."""
    base, sign = ESTIMATES[name]
    value = (np.abs(d - pair), np.maximum(d, pair), d + pair)[base]
    return value + sign * cover


class Node:
    __slots__ = ("entries", "pairs", "pivots", "kids", "cover", "live", "size")

    def __init__(self, entries, pairs, pivots, kids=None, cover=None, live=None):
        self.entries, self.pairs, self.pivots = np.asarray(entries, np.int64), pairs, np.asarray(pivots, np.int64)
        self.kids, self.cover = kids, np.zeros(len(entries)) if cover is None else cover
        self.live = np.ones(len(entries), bool) if live is None else live

    @property
    def leaf(self) -> bool:
        return self.kids is None

    @property
    def coordinates(self) -> np.ndarray:
        return self.pairs[:, self.pivots]


class VoronoiTree:
    """Tree of degree k with leaves of at most l entries. ``members`` maps an entry to equal objects it stands for."""

    def __init__(self, metric: Metric, store, k: int = 36, leaf: int = 100, centers: str = "greedy", n_pivots: int = 2, seed: int = 1, aux: bool = True):
        if not 1 < k <= leaf:
            raise ValueError("the degree must be over 1 and at most the leaf size")
        self.metric, self.store, self.k, self.l, self.how, self.n_pivots, self.seed, self.aux = metric, store, k, leaf, centers, n_pivots, seed, aux
        self.rng, self.counter, self.members, self.root = np.random.default_rng(seed), Counter(), {}, None
        self.ident: np.ndarray | None = None  # object of each position, where one object has several

    # Building

    def build(self, index: np.ndarray | None = None) -> VoronoiTree:
        index = np.arange(self.metric.size(self.store)) if index is None else np.asarray(index, np.int64)
        seen: dict[bytes, int] = {}
        distinct = []
        for i in index.tolist():
            first = seen.setdefault(self.metric.key(self.store, i), i)
            if first == i:
                distinct.append(i)
            else:
                self.members.setdefault(first, []).append(i)
        self.root = self._grow(np.array(distinct, np.int64)) if distinct else None
        return self

    def _node(self, entries, kids=None, cover=None) -> Node:
        pivots = self.rng.choice(len(entries), min(self.n_pivots, len(entries)), replace=False) if len(entries) else []
        return Node(entries, matrix(self.metric, self.store, np.asarray(entries), self.counter), pivots, kids, cover)

    def _grow(self, index: np.ndarray) -> Node:
        if len(index) <= self.l:
            return self._node(index)
        centers = choose(self.metric, self.store, index, self.k, self.how, self.rng, self.counter)
        if len(centers) < 2:
            return self._node(index)  # cannot be split: one place in the metric space
        node = self._node(centers)
        at, d = assign_pruned(self.metric, self.store, centers, node.pairs, index, self.counter)
        if np.bincount(at, minlength=len(centers)).max() == len(index):
            return self._node(index)
        node.kids = [self._grow(index[at == j]) for j in range(len(centers))]
        node.cover = np.array([d[at == j].max(initial=0.0) for j in range(len(centers))])
        return node

    # Walking

    def nodes(self, node: Node | None = None):
        stack = [node or self.root] if (node or self.root) else []
        while stack:
            n = stack.pop()
            yield n
            stack += n.kids or []

    def leaf_entries(self, node: Node | None = None) -> np.ndarray:
        rows = [n.entries for n in self.nodes(node) if n.leaf]
        return np.concatenate(rows) if rows else np.zeros(0, np.int64)

    def expand(self, entries) -> list[int]:
        out = []
        for i in entries:
            out.append(int(i))
            out += self.members.get(int(i), [])
        return out

    # Search within nodes

    def nearest(self, node: Node, ask: Ask, prune: str = "mindist", order: str = "pivot") -> tuple[int, float, dict[int, float]]:
        """Position and distance of the entry nearest to the query, and all distances measured on the way."""
        n, memo = len(node.entries), {}
        if not self.aux:
            d = ask.ds(node.entries)
            i = int(d.argmin())
            return i, float(d[i]), dict(enumerate(d.tolist()))
        ranked = np.arange(n)
        if order == "pivot" and n > 2:
            for p in node.pivots.tolist():
                memo[p] = ask.d(int(node.entries[p]))
            away = np.linalg.norm(node.coordinates - np.array([memo[p] for p in node.pivots.tolist()]), axis=1)
            ranked = np.argsort(away, kind="stable")
        alive, best, at = np.ones(n, bool), np.inf, -1
        for i in ranked.tolist():
            if not alive[i]:
                continue
            if i not in memo:
                memo[i] = ask.d(int(node.entries[i]))
            u, alive[i] = memo[i], False
            if u < best or (u == best and i < at):
                best, at = u, i
            slack = EPS * (1 + u)
            if prune == "simple":
                alive &= node.pairs[i] <= 2 * u + slack
            else:
                alive &= (node.pairs[i] >= u - best - slack) & (node.pairs[i] <= u + best + slack)
        return at, best, memo

    def range_search(self, q, r: float, eager: bool = False, ask: Ask | None = None, **flags) -> tuple[dict[int, float | None], Ask]:
        """Objects within r: position -> distance, None where it was never measured; and the query with its count.

        Flags (all on by default): ``prune`` and ``order`` of :meth:`nearest`, ``nn`` for the reach rule, ``cover`` for
        cover radii, ``mode='batch'`` to measure all entries of a node in one call, ``report_own`` and ``tight`` for
        two further rules that save distances.
        """
        ask = ask or Ask(self.metric, self.store, q, eager)
        found: dict[int, float | None] = {}
        if self.root is not None and r >= 0:
            self._search(self.root, True, ask, min(r, FAR), found, flags)
        out: dict[int, float | None] = {}
        for i, d in found.items():
            for j in self.expand([i]):
                out[j] = d
        return out, ask

    def _report(self, node: Node, j: int, found: dict) -> None:
        for i in [node.entries[j]] if node.leaf else self.leaf_entries(node.kids[j]):
            found.setdefault(int(i), None)

    def _search(self, root: Node, inside: bool, ask: Ask, r: float, found: dict, flags: dict) -> None:
        stack = [(root, inside)]
        while stack:
            node, within = stack.pop()
            if flags.get("mode") == "batch":
                step = self._all_at_once(node, within, ask, r, found)
            else:
                step = self._inside(node, ask, r, found, flags) if within else self._outside(node, ask, r, found, flags)
            stack += step

    def _all_at_once(self, node: Node, within: bool, ask: Ask, r: float, found: dict) -> list:
        d = ask.ds(node.entries)
        if node.leaf:
            for j in np.flatnonzero(d <= r).tolist():
                found[int(node.entries[j])] = float(d[j])
            return []
        slack = EPS * (1 + r + d)
        whole = d + node.cover <= r - slack
        for j in np.flatnonzero(whole).tolist():
            self._report(node, j, found)
        go = ~whole & (d - node.cover <= r + slack) & (d <= d.min() + 2 * r + slack)
        return [(node.kids[j], False) for j in np.flatnonzero(go).tolist()]

    def _inside(self, node: Node, ask: Ask, r: float, found: dict, flags: dict) -> list:
        i, near, memo = self.nearest(node, ask, flags.get("prune", "mindist"), flags.get("order", "pivot"))
        pair, slack = node.pairs[i], EPS * (1 + r + near + node.pairs[i])

        def d(j: int) -> float:
            if j not in memo:
                memo[j] = ask.d(int(node.entries[j]))
            return memo[j]

        if node.leaf:
            for j in range(len(node.entries)):
                if j in memo:
                    if memo[j] <= r:
                        found[int(node.entries[j])] = memo[j]
                elif pair[j] + near <= r - slack[j]:
                    self._report(node, j, found)
                elif pair[j] - near <= r + slack[j] and d(j) <= r:
                    found[int(node.entries[j])] = d(j)
            return []
        cover = node.cover if flags.get("cover", True) else np.full(len(pair), np.inf)
        whole, go = pair + near + cover <= r - slack, []
        reach = (pair - near - cover <= r + slack) & ((pair <= 2 * near + 2 * r + slack) | (not flags.get("nn", True)))
        for j in range(len(pair)):
            if j == i:
                if flags.get("report_own") and near + cover[j] <= r - slack[j]:
                    self._report(node, j, found)
                else:
                    go.append((node.kids[j], True))
            elif whole[j]:
                self._report(node, j, found)
            elif reach[j] and (not flags.get("nn", True) or pair[j] <= 2 * r or d(j) <= near + 2 * r + slack[j]):
                if not (flags.get("tight") and j in memo and memo[j] - cover[j] > r + slack[j]):
                    go.append((node.kids[j], False))
        return go

    def _outside(self, node: Node, ask: Ask, r: float, found: dict, flags: dict) -> list:
        left = np.ones(len(node.entries), bool)
        cover = node.cover if node.leaf or flags.get("cover", True) else np.full(len(left), np.inf)
        near, kept = np.inf, []
        for i in range(len(left)):
            if not left[i]:
                continue
            u, left[i] = ask.d(int(node.entries[i])), False
            near = min(near, u)
            slack = EPS * (1 + r + u)
            if self.aux:
                whole = left & (u + node.pairs[i] + cover <= r - slack)
                for j in np.flatnonzero(whole).tolist():
                    self._report(node, j, found)
                left &= ~whole & (np.abs(u - node.pairs[i]) - cover <= r + slack)
            if node.leaf:
                if u <= r:
                    found[int(node.entries[i])] = u
            elif u + cover[i] <= r - slack:
                self._report(node, i, found)
            elif u - cover[i] <= r + slack:
                kept.append((i, u))
        nn = flags.get("nn", True)
        return [(node.kids[i], False) for i, u in kept if not nn or u <= near + 2 * r + EPS * (1 + r + u)]

    # Nearest neighbours

    def probe_radius(self, q, k: int, name: str = "DE3", ask: Ask | None = None, eager: bool = False) -> float:
        """A radius within which k distinct objects lie for sure; infinite if there are fewer.

        A queue holds nodes by an estimate and objects by an upper bound of their distance; the largest bound among
        the first k distinct live objects is the radius. Which estimate is used changes the work alone.
        """
        ask = ask or Ask(self.metric, self.store, q, eager)
        rng, tick = np.random.default_rng(self.seed + 1), count()
        queue: list = [] if self.root is None else [(0.0, next(tick), self.root, True)]
        radius, seen, total = -1.0, set(), 0
        while queue:
            key, _, what, inside = heapq.heappop(queue)
            if not isinstance(what, Node):
                who = what if self.ident is None else int(self.ident[what])
                if who not in seen:
                    seen.add(who)
                    total += 1 + len(self.members.get(what, ()))
                    radius = max(radius, key)
                    if total >= k:
                        return radius + EPS * (1 + radius)
                continue
            if inside:
                i, d, _ = self.nearest(what, ask)
            else:
                i = int(rng.integers(len(what.entries)))
                d = ask.d(int(what.entries[i]))
            upper = d + what.pairs[i]
            upper[i] = d
            for j in np.flatnonzero(what.live).tolist():
                heapq.heappush(queue, (float(upper[j]), next(tick), int(what.entries[j]), False))
            if not what.leaf:
                keys = estimate(name, d, what.pairs[i], what.cover)
                keys[i] = d - what.cover[i]
                for j, kid in enumerate(what.kids):
                    heapq.heappush(queue, (float(keys[j]), next(tick), kid, inside and j == i))
        return np.inf

    def knn(self, q, k: int, strategy: str = "probe", name: str = "DE3", eager: bool = False, start: float | None = None, factor: float = 2.0, **flags) -> tuple[list[tuple[float, int]], dict[str, int]]:
        """The k nearest (distance, position), ties to the smaller position; all objects if there are fewer.

        ``probe``: a safe radius, then one range search. ``best_first``: nodes in order of their least possible
        distance, while the k-th best shrinks. ``growing``: range searches with growing radius.
        """
        if k < 1:
            raise ValueError("k must be 1 or more")
        ask = Ask(self.metric, self.store, q, eager)
        if strategy == "best_first":
            best = self._best_first(ask, k)
            return best, {"search": ask.count, "total": ask.count}
        if strategy == "growing":
            r = start if start is not None else 1.0
            total = len(self.expand(self.leaf_entries()))
            found, _ = self.range_search(q, r, ask=ask, **flags)
            while len(found) < min(k, total):
                r *= factor
                found, _ = self.range_search(q, r, ask=ask, **flags)
        else:
            r = self.probe_radius(q, k, name, ask)
            found, _ = self.range_search(q, r, ask=ask, **flags)
        before = ask.count
        unknown = np.array([i for i, d in found.items() if d is None], np.int64)
        if len(unknown):
            found.update(zip(unknown.tolist(), ask.ds(unknown).tolist(), strict=True))
        ranked = sorted((d, i) for i, d in found.items())[:k]
        return ranked, {"search": before, "total": ask.count}

    def _best_first(self, ask: Ask, k: int) -> list[tuple[float, int]]:
        tick, best = count(), []  # best: heap of (-distance, -position)
        queue = [] if self.root is None else [(0.0, next(tick), self.root)]
        while queue:
            bound, _, node = heapq.heappop(queue)
            if len(best) >= k and bound > -best[0][0] + EPS * (1 - best[0][0]):
                break
            d = ask.ds(node.entries)
            if node.leaf:
                for e, x in zip(node.entries.tolist(), d.tolist(), strict=True):
                    for i in self.expand([e]):
                        heapq.heappush(best, (-x, -i))
                        if len(best) > k:
                            heapq.heappop(best)
            else:
                for j, kid in enumerate(node.kids):
                    heapq.heappush(queue, (max(0.0, float(d[j] - node.cover[j])), next(tick), kid))
        return sorted((-a, -b) for a, b in best)

    # Changes

    def insert(self, i: int) -> None:
        """Add the object at position i of the store; a leaf that overflows is built anew."""
        q = self.metric.one(self.store, i)
        if self.root is None:
            self.root = self._grow(np.array([i]))
            return
        node, above = self.root, None
        while True:
            at, d, _ = self.nearest(node, Ask(self.metric, self.store, q))
            if node.leaf:
                break
            node.cover[at] = max(node.cover[at], d)
            above = (node, at)
            node = node.kids[at]
        if d == 0 and self.metric.key(self.store, int(node.entries[at])) == self.metric.key(self.store, i):
            self.members.setdefault(int(node.entries[at]), []).append(i)
            return
        self._put(above, self._grow(np.concatenate([node.entries, [i]])))

    def _put(self, above, node) -> None:
        if above is None:
            self.root = node
        else:
            above[0].kids[above[1]] = node

    def delete(self, i: int) -> bool:
        """Take out the object at position i; False if it is not there. Cover radii stay: they remain upper bounds."""
        for head, rest in self.members.items():
            if i in rest:
                rest.remove(i)
                return True
        q, path, node = self.metric.one(self.store, i), [], self.root
        while node is not None:
            at, _, _ = self.nearest(node, Ask(self.metric, self.store, q))
            if node.leaf:
                break
            path.append((node, at))
            node = node.kids[at]
        if node is None or i not in node.entries:
            return False
        heirs = self.members.pop(i, [])
        left = node.entries[node.entries != i]
        if heirs:
            left = np.concatenate([left, heirs[:1]])
            if heirs[1:]:
                self.members[heirs[0]] = heirs[1:]
        for n, at in path:
            n.live[n.entries == i] = False
        if len(left):
            self._put(path[-1] if path else None, self._grow(left))
        else:
            self._drop(path)
        return True

    def _drop(self, path: list) -> None:
        """Take out an emptied leaf: its parent is built anew from what is left below it."""
        if not path:
            self.root = None
            return
        node, at = path[-1]
        rest = [self.leaf_entries(kid) for j, kid in enumerate(node.kids) if j != at]
        rest = np.concatenate(rest) if rest else np.zeros(0, np.int64)
        if len(rest):
            self._put(path[-2] if len(path) > 1 else None, self._grow(rest))
        else:
            self._drop(path[:-1])
