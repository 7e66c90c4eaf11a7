"""Measures as SQL functions, and table functions, of one session."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import columns, movement
from .metrics import METRICS


def _pairwise(name: str):
    """Distance of two columns of objects; equal objects of the side with fewer different ones are measured in one go."""
    metric = METRICS[name]

    def run(u: pa.Array, v: pa.Array) -> pa.Array:
        sides = []
        for store in (metric.read(u), metric.read(v)):
            rows: dict[bytes, list[int]] = {}
            for i in range(len(u)):
                rows.setdefault(metric.key(store, i), []).append(i)
            sides.append((len(rows), store, list(rows.values())))
        (_, one, groups), (_, many, _) = sides if sides[0][0] <= sides[1][0] else sides[::-1]
        out = np.zeros(len(u))
        for at in groups:
            out[at] = metric.many(metric.one(one, at[0]), many, np.array(at))
        return pa.array(out, pa.float64())

    run.__annotations__ = {"u": pa.Array, "v": pa.Array, "return": pa.Array}
    return F.arrow_udf(run, "double")


def hull_radius(m: pa.Array) -> pa.Array:
    store = METRICS["sad"].read(m)
    return pa.array([movement.hull(METRICS["sad"].one(store, i))[4] for i in range(len(m))], pa.float64())


class Units:
    """Table function: the units of a movement, one row each."""

    def eval(self, obj):
        for i in range(len(obj.s) - 1):
            yield obj.s[i], obj.s[i + 1], obj.x[i], obj.y[i], obj.x[i + 1], obj.y[i + 1]


def medoid(ids, vectors) -> int:
    """Id of the vector with the least summed L1 distance to all of a group, the smaller id on ties."""
    m = np.stack([np.asarray(v, np.float64) for v in vectors])
    total = np.array([np.abs(m - row).sum() for row in m]).round(6)
    return int(np.asarray(ids)[np.lexsort((np.asarray(ids), total))[0]])


def register_functions(spark: SparkSession) -> None:
    """``sad``, ``hausdorff``, ``frechet`` and ``hull_radius`` on movements, and ``units(obj)`` as a table function."""
    for name in ("sad", "hausdorff", "frechet"):
        spark.udf.register(name, _pairwise(name))
    spark.udf.register("hull_radius", F.arrow_udf(hull_radius, "double"))
    spark.udtf.register("units", F.udtf(Units, returnType="s0 double, s1 double, x0 double, y0 double, x1 double, y1 double"))


pairwise = _pairwise
__all__ = ["columns", "hull_radius", "medoid", "pairwise", "register_functions"]
