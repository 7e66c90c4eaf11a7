"""Choice of centres among objects in memory; the samples they work on are bounded by the degree."""

from __future__ import annotations

import numpy as np

from ..functions.metrics import Ask, Metric


class Counter:
    """Distance evaluations of a construction."""

    def __init__(self) -> None:
        self.count = 0

    def many(self, metric: Metric, store, i: int, index: np.ndarray) -> np.ndarray:
        self.count += len(index)
        return metric.many(metric.one(store, int(i)), store, index)


def spread(metric: Metric, store, index: np.ndarray, k: int, counter: Counter) -> np.ndarray:
    """Up to k of ``index`` that are far apart: each next one has the largest distance to its nearest chosen one."""
    chosen, near = [int(index[0])], None
    while len(chosen) < min(k, len(index)):
        d = counter.many(metric, store, chosen[-1], index)
        near = d if near is None else np.minimum(near, d)
        best = int(near.argmax())
        if near[best] <= 0:
            break  # fewer than k distinct objects
        chosen.append(int(index[best]))
    return np.array(chosen)


def choose(metric: Metric, store, index: np.ndarray, k: int, method: str, rng: np.random.Generator, counter: Counter) -> np.ndarray:
    """k centres by ``random``, ``greedy`` (3k random candidates, far apart), ``prototypes`` or ``foci``.

    Prototypes and foci measure every object in each of k rounds; they are here to be compared.
    """
    index = np.asarray(index)
    if method == "random":
        return np.sort(rng.choice(index, min(k, len(index)), replace=False))
    if method == "greedy":
        return np.sort(spread(metric, store, rng.choice(index, min(3 * k, len(index)), replace=False), k, counter))
    start = int(rng.choice(index))
    if method == "prototypes":
        chosen, total = [start], np.zeros(len(index))
        while len(chosen) < min(k, len(index)):
            total += counter.many(metric, store, chosen[-1], index)
            masked = np.where(np.isin(index, chosen), -1.0, total)
            chosen.append(int(index[masked.argmax()]))
        return np.sort(chosen)
    if method == "foci":
        first = int(index[counter.many(metric, store, start, index).argmax()])
        d = counter.many(metric, store, first, index)
        second, edge = int(index[d.argmax()]), float(d.max())
        chosen, error = [first, second], np.abs(edge - d)
        while len(chosen) < min(k, len(index)):
            error += np.abs(edge - counter.many(metric, store, chosen[-1], index))
            masked = np.where(np.isin(index, chosen), np.inf, error)
            chosen.append(int(index[masked.argmin()]))
        return np.sort(np.unique(chosen))
    raise ValueError(f"no way {method!r} to choose centres")


def matrix(metric: Metric, store, index: np.ndarray, counter: Counter) -> np.ndarray:
    """Pairwise distances, each evaluated once."""
    n = len(index)
    out = np.zeros((n, n))
    for i in range(n - 1):
        out[i, i + 1 :] = counter.many(metric, store, index[i], index[i + 1 :])
    return out + out.T


def assign_pruned(metric: Metric, store, centers: np.ndarray, pairs: np.ndarray, index: np.ndarray, counter: Counter) -> tuple[np.ndarray, np.ndarray]:
    """Nearest centre (lowest position on ties) and distance of each object, skipping centres by stored distances.

    A centre further than twice the best distance so far from the best one cannot be nearer. One vectorised call for
    each centre, on the objects that still need it.
    """
    best, at = np.full(len(index), np.inf), np.zeros(len(index), np.int64)
    for j, c in enumerate(centers):
        need = np.flatnonzero(pairs[at, j] <= 2 * best + 1e-9 * (1 + best)) if j else np.arange(len(index))
        if len(need):
            d = counter.many(metric, store, c, index[need])
            closer = d < best[need]
            best[need[closer]], at[need[closer]] = d[closer], j
    return at, best


__all__ = ["Ask", "Counter", "assign_pruned", "choose", "matrix", "spread"]
