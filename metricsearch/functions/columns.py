"""The same measures as Column expressions, for plans that stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MOVEMENT = "struct<s:array<double>,x:array<double>,y:array<double>>"


def segment_mean(px: Column, py: Column, qx: Column, qy: Column) -> Column:
    """Mean length of a displacement going linearly from p to q, in the stable form of the numpy kernel."""
    gx, gy = qx - px, qy - py
    length = F.sqrt(gx * gx + gy * gy)
    ends = F.sqrt(px * px + py * py) + F.sqrt(qx * qx + qy * qy)
    a = (px * gx + py * gy) / length
    b = a + length
    h = F.abs(px * gy - py * gx) / length

    def primitive(v: Column) -> Column:
        return 0.5 * (v * F.sqrt(v * v + h * h) + F.when(h > 0, h * h * F.asinh(v / h)).otherwise(0.0))

    return F.when(length <= 1e-9 * ends, ends / 2).otherwise((primitive(b) - primitive(a)) / length)


def align(vertices: Column, mode: str = "time") -> Column:
    """Movement on [0, 1] from an array of (t, x, y) structs in order of t; one instant becomes stationary.

    ``mode='spatial'`` replaces times by the share of the path passed, so the speed is constant; a path of length zero
    is stationary.
    """
    x, y = F.transform(vertices, lambda v: v["x"]), F.transform(vertices, lambda v: v["y"])
    if mode == "time":
        t = F.transform(vertices, lambda v: v["t"].cast("double"))
        first, last = (F.element_at(vertices, i)["t"].cast("double") for i in (1, -1))  # not of t, which each vertex would make again
    else:
        step = F.zip_with(vertices, F.slice(vertices, 2, F.greatest(F.size(vertices) - 1, F.lit(0))), lambda a, b: F.coalesce(F.sqrt((b["x"] - a["x"]) * (b["x"] - a["x"]) + (b["y"] - a["y"]) * (b["y"] - a["y"])), F.lit(0.0)))
        t = F.transform(vertices, lambda v, i: F.aggregate(F.slice(step, 1, i), F.lit(0.0), lambda total, d: total + d))
        first, last = F.element_at(t, 1), F.element_at(t, -1)
    moving = F.struct(F.transform(t, lambda v: (v - first) / (last - first)).alias("s"), x.alias("x"), y.alias("y"))
    still = F.struct(F.array(F.lit(0.0), F.lit(1.0)).alias("s"), F.array(x[0], x[0]).alias("x"), F.array(y[0], y[0]).alias("y"))
    return F.when(last > first, moving).otherwise(still)


def close_gaps(units: Column) -> Column:
    """Array of unit structs (t0, t1, x0, y0, x1, y1) with a unit put into each gap in time."""
    following = F.slice(units, 2, F.greatest(F.size(units) - 1, F.lit(0)))
    bridge = lambda a, b: F.struct(a["t1"].alias("t0"), b["t0"].alias("t1"), a["x1"].alias("x0"), a["y1"].alias("y0"), b["x0"].alias("x1"), b["y0"].alias("y1"))
    both = F.zip_with(units, following, lambda a, b: F.when(b.isNotNull() & (b["t0"] > a["t1"]), F.array(a, bridge(a, b))).otherwise(F.array(a)))
    return F.flatten(both)


def refinement(u: Column, v: Column) -> Column:
    """Intervals (s0, s1) between common breakpoints of two movements."""
    s = F.array_sort(F.array_distinct(F.concat(u["s"], v["s"])))
    return F.transform(F.slice(s, 1, F.size(s) - 1), lambda a, i: F.struct(a.alias("s0"), F.element_at(s, (i + 2).cast("int")).alias("s1")))


def hull(m: Column) -> Column:
    """Axis end points and radius of one oblique cylinder around an aligned movement."""
    x, y, s = m["x"], m["y"], m["s"]
    x0, y0, x1, y1 = x[0], y[0], F.element_at(x, -1), F.element_at(y, -1)
    away = F.transform(F.arrays_zip(s.alias("s"), x.alias("x"), y.alias("y")), lambda v: F.sqrt(F.pow(v["x"] - x0 - v["s"] * (x1 - x0), F.lit(2.0)) + F.pow(v["y"] - y0 - v["s"] * (y1 - y0), F.lit(2.0))))
    return F.struct(x0.alias("x0"), y0.alias("y0"), x1.alias("x1"), y1.alias("y1"), F.array_max(away).alias("r"))


def hull_distance(a: Column, b: Column) -> Column:
    return segment_mean(b["x0"] - a["x0"], b["y0"] - a["y0"], b["x1"] - a["x1"], b["y1"] - a["y1"])


def hull_lower(a: Column, b: Column) -> Column:
    return F.greatest(F.lit(0.0), hull_distance(a, b) - a["r"] - b["r"])


def hull_upper(a: Column, b: Column) -> Column:
    return hull_distance(a, b) + a["r"] + b["r"]


def l1(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x.cast("double") - y.cast("double"))), F.lit(0.0), lambda t, d: t + d)


def jaccard(a: Column, b: Column) -> Column:
    """Jaccard distance of two arrays read as sets; two empty ones are at distance 0."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, 0.0).otherwise(1.0 - F.size(F.array_intersect(a, b)).cast("double") / union)


def euclid(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return F.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))


def hausdorff(u: Column, v: Column) -> Column:
    """Hausdorff distance of the vertices of two movements, by nested higher-order functions."""
    pu, pv = (F.arrays_zip(m["x"].alias("x"), m["y"].alias("y")) for m in (u, v))
    gap = lambda p, q: F.sqrt((p["x"] - q["x"]) * (p["x"] - q["x"]) + (p["y"] - q["y"]) * (p["y"] - q["y"]))
    one_way = lambda a, b: F.array_max(F.transform(a, lambda p: F.array_min(F.transform(b, lambda q: gap(p, q)))))
    return F.greatest(one_way(pu, pv), one_way(pv, pu))
