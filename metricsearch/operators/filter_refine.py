"""Range search on movements by approximations: a hull, then a tube, then the exact distance for the undecided."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import columns, movement
from ..functions.metrics import METRICS
from ..sources import scratch
from .scan import collect_queries, query_blocks

HELD = 200_000  # verdicts that a task sends on at once
TUBED = "tube struct<s:array<double>,x:array<double>,y:array<double>>, tube_err double, tube_repaired boolean, n_units int, tube_units int"


def attach_tubes(objs: DataFrame, radius: float, repair: bool = True) -> DataFrame:
    """``objs`` (obj_id, obj) with hull, tube and the tube's mean deviation; once for each set, to be written."""
    m = METRICS["sad"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            store = m.read(batch["obj"])
            made = [movement.tube(m.one(store, i), radius, repair) for i in range(batch.num_rows)]
            offsets = pa.array(np.concatenate([[0], np.cumsum([len(t[0][0]) for t in made])]).astype(np.int32))
            lists = [pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([t[0][k] for t in made]) if made else np.zeros(0))) for k in range(3)]
            tubes = pa.StructArray.from_arrays(lists, ["s", "x", "y"])
            extra = [tubes, pa.array([t[1] for t in made], pa.float64()), pa.array([t[2] for t in made], pa.bool_()), pa.array((np.diff(store[0]) - 1).astype(np.int32)), pa.array([len(t[0][0]) - 1 for t in made], pa.int32())]
            yield pa.RecordBatch.from_arrays([batch["obj_id"], batch["obj"], *extra], ["obj_id", "obj", "tube", "tube_err", "tube_repaired", "n_units", "tube_units"])

    return objs.select("obj_id", "obj").mapInArrow(run, f"obj_id long, obj {columns.MOVEMENT}, {TUBED}").withColumn("hull", columns.hull(F.col("obj")))


def _slack(bounds: str, radius: float, own: np.ndarray, query: float) -> np.ndarray | float:
    if bounds == "max":
        return 2 * radius
    if bounds == "mean":
        return radius
    if bounds == "own":
        return own + query
    raise ValueError(f"no bounds {bounds!r}")


def range_filter_refine(tubed: DataFrame, queries: DataFrame, radius: float, bounds: str = "mean", use_hull: bool = True, measure: bool = False) -> DataFrame:
    """(query_id, obj_id, verdict, dist): ``accepted`` by the tubes alone, or ``exact`` with its distance.

    ``queries`` (query_id, obj, r) are tubed in the same way; a query may be asked with several r. Accepted rows have
    a null distance, or theirs with ``measure``. Objects are read in place, by hulls and tubes, against blocks of
    queries; only ids and verdicts leave a task, an object's together, and the full movement of an object with undecided
    ones is fetched by its id, once for all of them.
    """
    return _stages(tubed, queries, radius, bounds, use_hull, measure).where("verdict <> 'exact' or dist <= r").select("query_id", "obj_id", "verdict", "dist")


def _asks(own: np.ndarray, found: list) -> pa.RecordBatch:
    """One row for each object with all that was found of it: (place, query_id, r, code) with arrays of places and codes."""
    at, code = np.concatenate([f[0] for f in found]), np.concatenate([f[3] for f in found])
    n = [len(f[0]) for f in found]
    query_id, r = (np.repeat(np.array([f[k] for f in found]), n) for k in (1, 2))
    order, size = np.argsort(at, kind="stable"), np.bincount(at, minlength=len(own))
    have = np.flatnonzero(size)
    asks = pa.StructArray.from_arrays([pa.array(x[order]) for x in (query_id, r, code.astype(np.int32))], ["query_id", "r", "code"])
    offsets = np.concatenate([[0], np.cumsum(size[have])]).astype(np.int32)
    return pa.RecordBatch.from_arrays([pa.array(own[have]), pa.ListArray.from_arrays(offsets, asks)], ["obj_id", "asks"])


def _judge(queries, radius: float, bounds: str, use_hull: bool):
    """(obj_id, asks) of the objects with the (query_id, r, code) that the bounds do not rule out: 1 accepted, 2 undecided."""
    m = METRICS["sad"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            store, own, err = m.read(batch["tube"]), batch["obj_id"].to_numpy(), batch["tube_err"].to_numpy()
            x0, y0, x1, y1, away = (batch["hull"].field(k).to_numpy(zero_copy_only=False) for k in ("x0", "y0", "x1", "y1", "r"))
            found, held = [], 0
            for query_id, asked, (tube, q_err, _), hull in queries.value:
                near = movement.segment_mean(hull[0] - x0, hull[1] - y0, hull[2] - x1, hull[3] - y1) - away - hull[4]
                at = np.flatnonzero(near <= max(asked) + 1e-9) if use_hull else np.arange(len(own))
                if not len(at):
                    continue
                d, slack = m.many(tube, store, at), _slack(bounds, radius, err[at], q_err)
                for r in asked:
                    eps = 1e-9 * (1 + r)
                    keep = np.flatnonzero(d <= r + slack + eps) if not use_hull else np.flatnonzero((d <= r + slack + eps) & (near[at] <= r + 1e-9))
                    if len(keep):
                        code = np.where(d[keep] <= r - (slack[keep] if isinstance(slack, np.ndarray) else slack) - eps, 1, 2)
                        found.append((at[keep], query_id, r, code))
                        held += len(keep)
                if held >= HELD:
                    yield _asks(own, found)
                    found, held = [], 0
            if found:
                yield _asks(own, found)

    return run


def _measure(queries):
    """The asks of each object with its distance, which is taken once for each query, however many radii it has."""
    m = METRICS["sad"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            store, asks = m.read(batch["obj"]), batch["asks"].flatten()
            own = np.repeat(np.arange(batch.num_rows), np.diff(batch["asks"].offsets.to_numpy()))
            qid = asks.field("query_id").to_numpy()
            order = np.lexsort((own, qid))
            q, o = qid[order], own[order]
            other = np.concatenate([[True], q[1:] != q[:-1]])[: len(q)]
            new = other | np.concatenate([[True], o[1:] != o[:-1]])[: len(q)]
            q, o, cuts = q[new], o[new], np.append(np.flatnonzero(other[new]), new.sum())
            once = np.concatenate([np.zeros(0), *(m.many(queries.value[int(q[i])], store, o[i:j]) for i, j in zip(cuts[:-1], cuts[1:], strict=True))])
            d = np.empty(len(qid))
            d[order] = once[np.cumsum(new) - 1]
            yield pa.RecordBatch.from_arrays([asks.field("query_id"), batch["obj_id"].take(pa.array(own)), asks.field("r"), asks.field("code"), pa.array(d)], ["query_id", "obj_id", "r", "code", "dist"])

    return run


def _stages(tubed: DataFrame, queries: DataFrame, radius: float, bounds: str, use_hull: bool, measure: bool = False) -> DataFrame:
    spark, out = tubed.sparkSession, None
    for block in query_blocks(queries):
        ids, asked, radii, _ = collect_queries(block, "sad")
        by_id: dict[int, tuple] = {}
        for i, q, r in zip(ids if ids is not None else [], asked, radii if radii is not None else [], strict=True):
            by_id.setdefault(int(i), (q, []))[1].append(float(r))
        prepared = [(i, rs, movement.tube(q, radius), movement.hull(q)) for i, (q, rs) in by_id.items()]
        run = _judge(spark.sparkContext.broadcast(prepared), radius, bounds, use_hull)
        judged = tubed.select("obj_id", "hull", "tube", "tube_err").mapInArrow(run, "obj_id long, asks array<struct<query_id:long,r:double,code:int>>")
        judged = scratch.write_table(judged, "judged", "search")
        fetch = judged if measure else judged.withColumn("asks", F.filter("asks", lambda a: a["code"] == 2)).where("size(asks) > 0")
        wanted = scratch.small_side(fetch.select("obj_id").distinct())
        full = tubed.select("obj_id", "obj").join(wanted, "obj_id", "left_semi")
        exact = spark.sparkContext.broadcast({i: q for i, (q, _) in by_id.items()})
        measured = fetch.join(full, "obj_id").select("obj_id", "asks", "obj").mapInArrow(_measure(exact), "query_id long, obj_id long, r double, code int, dist double")
        if not measure:
            accepted = judged.select("obj_id", F.inline("asks")).where("code = 1").withColumn("dist", F.lit(None).cast("double"))
            measured = measured.unionByName(accepted.select(*measured.columns))
        out = measured if out is None else out.unionByName(measured)
    return out.select("query_id", "obj_id", "r", "dist", F.when(F.col("code") == 1, "accepted").otherwise("exact").alias("verdict"))


def filter_stats(tubed: DataFrame, queries: DataFrame, radius: float, bounds: str = "mean", use_hull: bool = True, by_radius: bool = False) -> DataFrame:
    """(n_filter, n_accepted, n_exact, n_result): sums over all queries, with ``by_radius`` for each r; exact is
    filter less accepted. Where ``tubed`` and ``queries`` have a column ``copies``, a row stands for so many objects."""
    rows = _stages(tubed, queries, radius, bounds, use_hull)
    n = F.lit(1)
    for side, key in ((tubed, "obj_id"), (queries, "query_id")):
        if "copies" in side.columns:
            rows = rows.join(scratch.small_side(side.select(key, F.col("copies").alias(f"{key}_n")).distinct()), key)
            n = n * F.col(f"{key}_n")
    count = lambda which: F.coalesce(F.sum(F.when(which, n)), F.lit(0)).cast("long")
    accepted, exact = count(F.col("verdict") == "accepted"), count(F.col("verdict") == "exact")
    sums = [count(F.lit(True)).alias("n_filter"), accepted.alias("n_accepted"), exact.alias("n_exact"), (accepted + count((F.col("verdict") == "exact") & (F.col("dist") <= F.col("r")))).alias("n_result")]
    return rows.groupBy("r").agg(*sums) if by_radius else rows.agg(*sums)


def tube_quality(tubed: DataFrame, radius: float) -> DataFrame:
    """(n, n_over, avg_units, avg_tube_units): tubes whose mean deviation is not below half the radius, and sizes."""
    return tubed.agg(F.count("*").alias("n"), F.count_if(F.col("tube_err") >= radius / 2).alias("n_over"), F.avg("n_units").alias("avg_units"), F.avg("tube_units").alias("avg_tube_units"))
