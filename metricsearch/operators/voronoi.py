"""Voronoi partitioning of a distributed set: centres, assignment, cover radii, reach, and joins built on them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import METRICS
from ..plans.centers import Counter, assign_pruned, choose, matrix
from ..sources.objects import pick

MOST_CENTERS = 5_000  # centres that are sent to the executors; more of them go by a salted join


class Centers:
    """Centres on the driver: their ids, objects in one store, and pair matrix."""

    def __init__(self, metric: str, ids: np.ndarray, store, counter: Counter | None = None):
        self.metric, self.ids, self.store = metric, np.asarray(ids), store
        self.counter = counter or Counter()
        self.pairs = matrix(METRICS[metric], store, np.arange(len(ids)), self.counter)

    def __len__(self) -> int:
        return len(self.ids)


def _gather(rows: DataFrame, metric: str) -> tuple[np.ndarray, object]:
    table = rows.select("obj_id", "obj").toArrow().combine_chunks()
    column = table["obj"].combine_chunks() if len(table) else None
    return table["obj_id"].to_numpy() if len(table) else np.zeros(0, np.int64), METRICS[metric].read(column) if len(table) else METRICS[metric].pack([])


def pick_centers(objs: DataFrame, metric: str, k: int, method: str = "greedy", seed: int = 1) -> Centers:
    """k centres of a set. A sample of 3k objects (k for ``random``), the first by md5, comes to the driver.

    ``prototypes`` and ``foci`` look at all objects in each round and are meant for comparisons on sets in memory; here
    they run on a sample of 40k objects.
    """
    if not 1 <= k <= MOST_CENTERS:
        raise ValueError(f"between 1 and {MOST_CENTERS} centres")
    take = {"random": k, "greedy": 3 * k}.get(method, 40 * k)
    ids, store = _gather(pick(objs.select("obj_id", "obj"), take, seed), metric)
    counter = Counter()
    m = METRICS[metric]
    chosen = choose(m, store, np.arange(len(ids)), k, method, np.random.default_rng(seed), counter) if len(ids) else np.zeros(0, np.int64)
    chosen = chosen[np.argsort(ids[chosen])]
    return Centers(metric, ids[chosen], m.pack([m.one(store, int(i)) for i in chosen]), counter)


def _as_objects(metric: str, store, index) -> list:
    """Objects as Spark rows."""
    m = METRICS[metric]
    out = []
    for i in index:
        o = m.one(store, int(i))
        if m.input_type.startswith("struct<s"):
            out.append(tuple([float(v) for v in a] for a in o))
        elif metric == "euclid":
            out.append((float(o[0]), float(o[1])))
        elif metric == "jaccard":
            out.append(sorted(o))
        else:
            out.append([float(v) for v in o])
    return out


def assign(objs: DataFrame, centers: Centers, method: str = "pruned") -> DataFrame:
    """``objs`` with ``cell`` (position of the nearest centre, the lowest on ties), ``cell_dist`` and ``n_dist``.

    ``full`` measures every centre, ``pruned`` skips centres by their stored distances. Nothing is shuffled.
    """
    shared = objs.sparkSession.sparkContext.broadcast((centers.store, centers.pairs))
    m, size = METRICS[centers.metric], len(centers)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, pairs = shared.value
        for batch in batches:
            own, n = m.read(batch["obj"]), batch.num_rows
            if method == "full":
                d = np.stack([m.many(m.one(store, j), own) for j in range(size)])
                at, best, used = d.argmin(axis=0), d.min(axis=0), np.full(n, size)
            else:
                both, counter = _joined(m, store, own), Counter()
                at, best = assign_pruned(m, both[0], np.arange(size), pairs, np.arange(size, size + n), counter)
                used = np.full(n, counter.count // max(1, n))
            arrays = [pa.array(at.astype(np.int32)), pa.array(best), pa.array(used.astype(np.int64))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *arrays], [*batch.schema.names, "cell", "cell_dist", "n_dist"])

    kept = [c for c in objs.columns if c not in ("cell", "cell_dist", "n_dist")]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in objs.select(*kept).schema)
    return objs.select(*kept).mapInArrow(run, schema + ", cell int, cell_dist double, n_dist long")


def _joined(m, first, second):
    """One store of the objects of two."""
    if isinstance(first, tuple):
        return (np.concatenate([first[0], second[0][1:] + first[0][-1]]), *(np.concatenate([a, b]) for a, b in zip(first[1:], second[1:], strict=True))), None
    if isinstance(first, np.ndarray):
        return np.concatenate([first, second]), None
    return m.pack([m.one(first, i) for i in range(m.size(first))] + [m.one(second, i) for i in range(m.size(second))]), None


def cover_radii(assigned: DataFrame) -> DataFrame:
    """(cell, cover_radius, n) from assigned objects, without any further distance."""
    return assigned.groupBy("cell").agg(F.max("cell_dist").alias("cover_radius"), F.count("*").alias("n"))


def reachable_cells(queries: DataFrame, centers: Centers, radii: dict[int, float] | None = None) -> DataFrame:
    """``queries`` (with r) once for each cell they may have results in: d(q, v) <= min d(q, u) + 2r, and, where cover
    radii are given, d(q, v) <= cover + r."""
    shared = queries.sparkSession.sparkContext.broadcast((centers.store, radii))
    m, size = METRICS[centers.metric], len(centers)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, covers = shared.value
        limit = np.array([covers.get(j, -np.inf) for j in range(size)]) if covers is not None else None
        for batch in batches:
            if not batch.num_rows:
                continue
            own, r = m.read(batch["obj"]), batch["r"].to_numpy()
            d = np.stack([m.many(m.one(store, j), own) for j in range(size)], axis=1)
            slack = 1e-9 * (1 + r[:, None] + d)
            go = d <= d.min(axis=1, keepdims=True) + 2 * r[:, None] + slack
            if limit is not None:
                go &= d <= limit[None, :] + r[:, None] + slack
            row, cell = np.nonzero(go)
            taken = batch.take(pa.array(row))
            yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(cell.astype(np.int32)), pa.array(d[row, cell])], [*taken.schema.names, "cell", "center_dist"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in queries.schema)
    return queries.mapInArrow(run, schema + ", cell int, center_dist double")


def salt(assigned: DataFrame, copies: int = 20, key: str = "obj_id") -> DataFrame:
    """A salted cell key of both sides of a join: cell * copies + a hash of the id."""
    return assigned.withColumn("salted", F.col("cell") * copies + F.pmod(F.xxhash64(key), F.lit(copies)).cast("int"))


def copy_for_salts(cells: DataFrame, copies: int = 20) -> DataFrame:
    """Rows of a small side once for each salt, under the same formula."""
    return cells.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("salted", F.col("cell") * copies + F.col("_salt")).drop("_salt")


def _local_join(metric: str, local: str, leaf: int = 64):
    m = METRICS[metric]

    def run(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        a, b, dist = [], [], []
        if len(left) and len(right):
            store, asked = m.read(left["s_obj"].combine_chunks()), m.read(right["t_obj"].combine_chunks())
            s_ids, t_ids, r = left["s_id"].to_numpy(), right["t_id"].to_numpy(), right["r"].to_numpy()
            tree = None
            if local == "tree" and len(left) > leaf:
                from ..plans.tree import VoronoiTree

                tree = VoronoiTree(m, store, min(16, leaf), leaf).build()
            for i in range(len(right)):
                q = m.one(asked, i)
                if tree is None:
                    d = m.many(q, store)
                    hit = np.flatnonzero(d <= r[i])
                    d = d[hit]
                else:
                    found, ask = tree.range_search(q, float(r[i]), mode="batch")
                    hit = np.array(sorted(found), np.int64)
                    d = np.array([np.nan if found[int(h)] is None else found[int(h)] for h in hit])
                    lost = np.flatnonzero(np.isnan(d))
                    if len(lost):
                        d[lost] = ask.ds(hit[lost])
                a.append(s_ids[hit])
                b.append(np.full(len(hit), t_ids[i]))
                dist.append(d)
        join = lambda parts, kind: np.concatenate(parts).astype(kind) if parts else np.zeros(0, kind)
        return pa.table({"s_id": join(a, np.int64), "t_id": join(b, np.int64), "dist": join(dist, np.float64)})

    return run


def range_join(s: DataFrame, t: DataFrame, r: float, metric: str, k: int = 32, local: str = "loop", centers: Centers | None = None, cell_rows: int = 20_000, own_pairs: bool = True) -> DataFrame:
    """(s_id, t_id, dist) of all pairs within r of two sets (obj_id, obj).

    Each s goes to its nearest centre's cell alone, each t to all cells it reaches, and cells are joined by a nested
    loop or a local tree; a pair meets in one place. Large cells are cut into chunks of about ``cell_rows`` of s, and
    t goes to each chunk. Give the larger set as s. ``own_pairs=False`` keeps pairs with s_id < t_id only.
    """
    centers = centers or pick_centers(s, metric, k)
    spark = s.sparkSession
    if not len(centers):
        return spark.createDataFrame([], "s_id long, t_id long, dist double")
    placed = assign(s.select("obj_id", "obj"), centers).persist()
    cells = cover_radii(placed).toPandas()
    radii = dict(zip(cells["cell"].tolist(), cells["cover_radius"].tolist(), strict=True))
    chunks = spark.createDataFrame(pd.DataFrame({"cell": cells["cell"].astype("int32"), "chunks": np.ceil(cells["n"] / cell_rows).astype("int32")}), "cell int, chunks int")
    left = placed.join(F.broadcast(chunks), "cell").select(F.col("obj_id").alias("s_id"), F.col("obj").alias("s_obj"), "cell", F.pmod(F.xxhash64("obj_id"), F.col("chunks")).cast("int").alias("chunk"))
    right = reachable_cells(t.select("obj_id", "obj", F.lit(float(r)).alias("r")), centers, radii).join(F.broadcast(chunks), "cell")
    right = right.select(F.col("obj_id").alias("t_id"), F.col("obj").alias("t_obj"), "r", "cell", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"))
    out = left.groupBy("cell", "chunk").cogroup(right.groupBy("cell", "chunk")).applyInArrow(_local_join(metric, local), "s_id long, t_id long, dist double")
    return out if own_pairs else out.where("s_id < t_id")


def range_self_join(s: DataFrame, r: float, metric: str, k: int = 32, local: str = "loop") -> DataFrame:
    """(s_id, t_id, dist) of all pairs s_id < t_id of one set within r."""
    return range_join(s, s, r, metric, k, local, own_pairs=False)
