"""Sequential scan over a distributed set: the exact baseline, and the form to use where no index pays."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import METRICS

MOST_QUERIES = 20_000  # queries that go out to the executors in one pass


def collect_queries(queries: DataFrame, metric: str, most: int = MOST_QUERIES):
    """A query table as (ids, packed objects, r, k) on the driver; larger ones must be cut into blocks by the caller."""
    rows = queries.limit(most + 1).toArrow().combine_chunks()
    if len(rows) > most:
        raise ValueError(f"more than {most} queries in one pass; use query_blocks")
    column = lambda name: rows[name].combine_chunks() if isinstance(rows[name], pa.ChunkedArray) else rows[name]
    m = METRICS[metric]
    store = m.read(column("obj")) if len(rows) else m.pack([])
    get = lambda name: column(name).to_numpy(zero_copy_only=False) if name in rows.column_names else None
    return get("query_id"), [m.one(store, i) for i in range(len(rows))], get("r"), get("k")


def query_blocks(queries: DataFrame, size: int = MOST_QUERIES) -> list[DataFrame]:
    """The query table in blocks of about ``size``, each small enough for one pass."""
    n = queries.count()
    parts = max(1, -(-n // max(1, size // 2)))
    return [queries] if n <= size else [queries.where(F.pmod(F.xxhash64("query_id"), F.lit(parts)) == i) for i in range(parts)]


def range_scan(objs: DataFrame, queries: DataFrame, metric: str) -> DataFrame:
    """(query_id, obj_id, dist) of all objects within each query's r. Objects are never shuffled."""
    m, out = METRICS[metric], None
    for block in query_blocks(queries):
        shared = objs.sparkSession.sparkContext.broadcast(collect_queries(block, metric))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ids, asked, radii, _ = shared.value
            for batch in batches:
                store, own = m.read(batch["obj"]), batch["obj_id"].to_numpy()
                for query_id, q, r in zip(ids if ids is not None else [], asked, radii if radii is not None else [], strict=True):
                    d = m.many(q, store)
                    hit = np.flatnonzero(d <= r)
                    if len(hit):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hit), query_id)), pa.array(own[hit]), pa.array(d[hit])], ["query_id", "obj_id", "dist"])

        part = objs.select("obj_id", "obj").mapInArrow(run, "query_id long, obj_id long, dist double")
        out = part if out is None else out.unionByName(part)
    return out


def best_k(found: DataFrame, k: str = "k") -> DataFrame:
    """The k nearest rows (query_id, obj_id, dist, k) of each query with their rank; ties to the smaller id."""
    order = Window.partitionBy("query_id").orderBy("dist", "obj_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= F.col(k))


def knn_scan(objs: DataFrame, queries: DataFrame, metric: str) -> DataFrame:
    """(query_id, rank, obj_id, dist) of each query's k nearest; each partition sends k rows for each query at most."""
    m, out = METRICS[metric], None
    for block in query_blocks(queries):
        shared = objs.sparkSession.sparkContext.broadcast(collect_queries(block, metric))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ids, asked, _, ks = shared.value
            best = [(np.zeros(0), np.zeros(0, np.int64))] * len(asked)
            for batch in batches:
                store, own = m.read(batch["obj"]), batch["obj_id"].to_numpy()
                for i, q in enumerate(asked):
                    d, o = np.concatenate([best[i][0], m.many(q, store)]), np.concatenate([best[i][1], own])
                    if len(d) > 4 * ks[i]:
                        near = d <= np.partition(d, int(ks[i]) - 1)[int(ks[i]) - 1]
                        d, o = d[near], o[near]
                    order = np.lexsort((o, d))[: int(ks[i])]
                    best[i] = (d[order], o[order])
            n = [len(d) for d, _ in best]
            if sum(n):
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(np.concatenate([o for _, o in best])), pa.array(np.concatenate([d for d, _ in best])), pa.array(np.repeat(ks, n).astype(np.int32))], ["query_id", "obj_id", "dist", "k"])

        part = objs.select("obj_id", "obj").mapInArrow(run, "query_id long, obj_id long, dist double, k int")
        out = part if out is None else out.unionByName(part)
    return best_k(out).select("query_id", "rank", "obj_id", "dist")
