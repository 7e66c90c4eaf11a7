"""Metrics behind one face: pack objects into a store, read one back, and measure one object against many."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

import numpy as np
import pyarrow as pa

from . import movement


class Metric:
    """A distance with the triangle inequality, on the objects of one Arrow type."""

    name = "metric"
    input_type = ""
    vectors = False  # stores are matrices with an object in each row, and ``pairs`` can be asked

    def pack(self, objects: list) -> Any:
        raise NotImplementedError

    def size(self, store: Any) -> int:
        raise NotImplementedError

    def one(self, store: Any, i: int) -> Any:
        raise NotImplementedError

    def many(self, q: Any, store: Any, index: np.ndarray | None = None) -> np.ndarray:
        raise NotImplementedError

    def read(self, column: pa.Array) -> Any:
        """A store from an Arrow column of objects."""
        return self.pack(column.to_pylist())

    def ready(self, q: Any, store: Any) -> Any:
        """``q`` in a form that is cheap to measure again and again against this store."""
        return q

    def key(self, store: Any, i: int) -> bytes:
        """Equal for equal objects."""
        return repr(self.one(store, i)).encode()


class _OnMovements(Metric):
    input_type = "struct<s:array<double>,x:array<double>,y:array<double>>"

    def pack(self, objects):
        return movement.flatten([tuple(np.asarray(o[k], np.float64) for k in ("s", "x", "y")) if isinstance(o, dict) else o for o in objects])

    def read(self, column):
        lists = [column.field(k) for k in ("s", "x", "y")]
        if column.null_count or any(a.null_count for a in lists):
            raise ValueError("null movements cannot be measured; filter them first")
        lengths = np.diff(lists[0].offsets.to_numpy()) if len(column) else np.zeros(0, np.int64)
        return np.concatenate([[0], np.cumsum(lengths)]).astype(np.int64), *(a.flatten().to_numpy(zero_copy_only=False) for a in lists)

    def size(self, store):
        return len(store[0]) - 1

    def one(self, store, i):
        a, b = store[0][i], store[0][i + 1]
        return store[1][a:b], store[2][a:b], store[3][a:b]

    def key(self, store, i):
        return b"|".join(a.tobytes() for a in self.one(store, i))


class Sad(_OnMovements):
    name = "sad"

    def many(self, q, store, index=None):
        return movement.sad_many(q, store if index is None else movement.pick(store, index))


class Hausdorff(_OnMovements):
    name = "hausdorff"

    def many(self, q, store, index=None):
        return movement.hausdorff_many(q, store if index is None else movement.pick(store, index))


class Frechet(_OnMovements):
    name = "frechet"

    def many(self, q, store, index=None):
        return np.array([movement.frechet(q, self.one(store, int(i))) for i in (range(self.size(store)) if index is None else index)])


class Manhattan(Metric):
    name = "l1"
    input_type = "array<double>"
    vectors = True

    def pack(self, objects):
        return np.asarray(objects, np.float64)

    def read(self, column):
        values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        return values.reshape(len(column), -1) if len(column) else np.zeros((0, 0))

    def size(self, store):
        return len(store)

    def one(self, store, i):
        return store[i]

    def many(self, q, store, index=None):
        return np.abs((store if index is None else store[index]) - q).sum(axis=1)

    def pairs(self, some, others):
        """Row by row."""
        return np.abs(others - some).sum(axis=1)

    def key(self, store, i):
        return store[i].tobytes()


class Euclid(Manhattan):
    name = "euclid"
    input_type = "struct<x:double,y:double>"

    def pack(self, objects):
        return np.array([[o["x"], o["y"]] if isinstance(o, dict) else o for o in objects], np.float64).reshape(len(objects), 2)

    def read(self, column):
        return np.stack([column.field(k).to_numpy(zero_copy_only=False) for k in ("x", "y")], axis=1)

    def many(self, q, store, index=None):
        return self.pairs(q, store if index is None else store[index])

    def pairs(self, some, others):
        d = others - some
        return np.sqrt((d * d).sum(axis=1))


@dataclass
class Sets:
    """Word sets as sorted integer lists over one vocabulary."""

    offsets: np.ndarray
    items: np.ndarray
    words: dict[str, int] = field(default_factory=dict)


@dataclass
class Marked:
    """A word set asked of one store: its size, and which words of the store's vocabulary it has."""

    size: int
    member: np.ndarray


class Jaccard(Metric):
    """One minus common over all words; two empty sets are at distance 0."""

    name = "jaccard"
    input_type = "array<string>"

    def pack(self, objects):
        words: dict[str, int] = {}
        rows = [np.unique([words.setdefault(w, len(words)) for w in set(o)]).astype(np.int64) if len(o) else np.zeros(0, np.int64) for o in objects]
        offsets = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)
        return Sets(offsets, np.concatenate(rows) if rows else np.zeros(0, np.int64), words)

    def read(self, column):
        values = column.flatten()
        if column.null_count or values.null_count:
            return self.pack(column.to_pylist())
        coded = values.dictionary_encode()
        items, lengths = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), np.diff(column.offsets.to_numpy())
        owner = np.repeat(np.arange(len(column)), lengths)
        order = np.lexsort((items, owner))
        items, owner = items[order], owner[order]
        first = np.ones(len(items), bool)
        first[1:] = (items[1:] != items[:-1]) | (owner[1:] != owner[:-1])
        offsets = np.concatenate([[0], np.cumsum(np.bincount(owner[first], minlength=len(column)))]).astype(np.int64)
        return Sets(offsets, items[first], {w: i for i, w in enumerate(coded.dictionary.to_pylist())})

    def size(self, store):
        return len(store.offsets) - 1

    def one(self, store, i):
        names = getattr(store, "_names", None)
        if names is None:
            names = store._names = list(store.words)
        return frozenset(names[j] for j in store.items[store.offsets[i] : store.offsets[i + 1]])

    def ready(self, q, store):
        words = set(q)
        member = np.zeros(len(store.words) + 1, bool)
        member[np.array([store.words[w] for w in words if w in store.words], np.int64)] = True
        return Marked(len(words), member)

    def many(self, q, store, index=None):
        n = self.size(store)
        index = np.arange(n) if index is None else np.asarray(index)
        q = q if isinstance(q, Marked) else self.ready(q, store)
        member = q.member
        starts, lengths = store.offsets[index], store.offsets[index + 1] - store.offsets[index]
        out = np.concatenate([[0], np.cumsum(lengths)])
        at = np.repeat(starts - out[:-1], lengths) + np.arange(out[-1])
        hit = np.concatenate([[0], np.cumsum(member[store.items[at]])])
        both = (hit[out[1:]] - hit[out[:-1]]).astype(np.float64)
        union = lengths + q.size - both
        return np.where(union > 0, 1.0 - both / np.where(union > 0, union, 1), 0.0)

    def key(self, store, i):
        return store.items[store.offsets[i] : store.offsets[i + 1]].tobytes()


METRICS = {m.name: m for m in (Sad(), Hausdorff(), Frechet(), Manhattan(), Euclid(), Jaccard())}


class Ask:
    """One query on one store: measures its object and counts distance evaluations.

    ``eager`` measures all objects in one call and counts only those the algorithm asks for: the count is the paper's
    cost measure, the time is not. Distances to all objects that are known already may be given in its place.
    """

    def __init__(self, metric: Metric, store: Any, q: Any, eager: bool | np.ndarray = False):
        self.metric, self.store, self.q, self.count = metric, store, metric.ready(q, store), 0
        self.all = eager if isinstance(eager, np.ndarray) else metric.many(self.q, store) if eager else None

    def d(self, i: int) -> float:
        self.count += 1
        return float(self.all[i]) if self.all is not None else float(self.metric.many(self.q, self.store, np.array([i]))[0])

    def ds(self, index: np.ndarray) -> np.ndarray:
        self.count += len(index)
        return self.all[index] if self.all is not None else self.metric.many(self.q, self.store, np.asarray(index))
