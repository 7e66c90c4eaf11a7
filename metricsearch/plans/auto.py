"""Which way to search a set: an index pays only where distances are spread and not too cheap."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..functions.metrics import METRICS
from ..operators.scan import knn_scan, range_scan
from ..operators.voronoi import _gather
from ..sources.objects import pick
from . import index as ix

SAMPLE = 300
CHEAP = ("euclid",)


def distance_profile(objs: DataFrame, metric: str, n: int = SAMPLE) -> np.ndarray:
    """Quantiles 0.01, 0.5 and 1 of the distances among the first n objects by md5."""
    m = METRICS[metric]
    _, store = _gather(pick(objs, n), metric)
    size = m.size(store)
    if size < 2:
        return np.zeros(3)
    d = np.concatenate([m.many(m.one(store, i), store, np.arange(i + 1, size)) for i in range(size - 1)])
    return np.quantile(d, (0.01, 0.5, 1.0))


def choose_strategy(objs: DataFrame, metric: str) -> str:
    """``scan`` where near distances are over half the median (every index fails) or the metric costs next to nothing,
    ``tubes`` for movements, else ``tree``."""
    near, median, _ = distance_profile(objs, metric)
    if near > median / 2 or metric in CHEAP:
        return "scan"
    return "tubes" if metric == "sad" else "tree"


def search(objs: DataFrame, queries: DataFrame, metric: str, knn: bool = False, strategy: str = "auto", tube_radius: float = 10.0, **build) -> DataFrame:
    """Range search (query_id, obj_id, dist), or with ``knn`` the k nearest, by the strategy that fits the set.

    The result is the same whatever the strategy: rows that tubes accept without measuring are measured for it.
    """
    how = choose_strategy(objs, metric) if strategy == "auto" else strategy
    if how == "scan":
        return knn_scan(objs, queries, metric) if knn else range_scan(objs, queries, metric)
    if how == "tubes" and not knn:
        from ..operators.filter_refine import attach_tubes, range_filter_refine
        from ..sources import scratch

        tubed = scratch.write_table(attach_tubes(objs, tube_radius), "tubed")
        return range_filter_refine(tubed, queries, tube_radius, "own", use_hull=False, measure=True).select("query_id", "obj_id", "dist")
    tree = ix.build(objs, metric, **build)
    return ix.knn(tree, queries)[0] if knn else ix.results(ix.range_search(tree, queries))
