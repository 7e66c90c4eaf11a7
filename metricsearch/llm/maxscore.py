"""Exact top-k search by integer inner product with MaxScore over signed posting lists.

Each dimension is two terms: the rows where it is positive and those where it is negative. A shard keeps a posting list
(row numbers in order, and values) for every term. A query's weight and the largest value in the list of its own sign
bound what a term can add; lists of the other sign only take away, so their bound is 0. Terms in falling order of bound
are essential until all others together stay below the query's k-th best score so far, by the sum of their bounds or by
the length of their weights times a row's length. Only the essential lists are traversed; a row in none of them cannot
compete. The others are probed, a few terms at a time, for rows whose score so far and remaining bound still reach the
k-th best. Shards (partitions of the rows) keep k rows for each query, and the shards' results are merged.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BLOCK = 4096  # rows of a shard
QUERY_BYTES = 32 << 20  # of queries sent to the executors in one pass over the rows; more queries make more passes
PROBES = 8  # terms probed between two looks at the bounds


def quantise(vector: str = "embedding", scale: int = 256) -> F.Column:
    """floor(scale * x) of each component as doubles; null where the vector is null or holds a null or non-finite."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    return F.when(F.col(vector).isNotNull() & ~F.coalesce(bad, F.lit(True)), F.transform(vector, lambda x: F.floor(x.cast("double") * scale).cast("long")))


def _matrix(column: pa.Array, width: int | None = None) -> np.ndarray:
    """Rows of a list column as one int64 matrix; shorter rows are filled with 0."""
    lengths = np.diff(column.offsets.to_numpy())
    values = column.flatten().to_numpy(zero_copy_only=False)
    width = max(int(lengths.max(initial=0)), width or 0)
    if len(lengths) and (lengths == width).all():
        return values.reshape(len(lengths), width)
    out = np.zeros((len(lengths), width), np.int64)
    out[np.arange(width)[None, :] < lengths[:, None]] = values
    return out


class Shard:
    """Posting lists of up to ``BLOCK`` rows, with the largest value in each and the rows' lengths.

    With ``counting``, ``read`` is the number of postings that searches have traversed or probed, and ``held`` that of
    all lists of their terms; a row has at most one posting in the two lists of a dimension, and a probe counts as one.
    """

    def __init__(self, ids: np.ndarray, rows: np.ndarray, counting: bool = False):
        self.ids, self.n = ids, len(ids)
        self.most, self.least = np.maximum(rows.max(axis=0), 0), np.minimum(rows.min(axis=0), 0)
        self.size = max(int(self.most.max(initial=0)), -int(self.least.min(initial=0)))
        self.values = np.ascontiguousarray(rows.T)  # values by term and row number, for probes
        self.floats = self.values.astype(np.float64)
        self.squares = self.floats * self.floats
        self.lengths = np.sqrt(self.squares.sum(axis=0))
        self.inside = np.stack([self.values < 0, self.values > 0])
        self.lists = []
        for inside in self.inside:
            ends = np.concatenate([[0], np.cumsum(inside.sum(axis=1))])
            self.lists.append((np.nonzero(inside)[1], self.values[inside], self.floats[inside], ends))
        self.counting = counting
        self.read = self.held = 0

    def _traverse(self, terms: np.ndarray, query: np.ndarray, exact: bool) -> np.ndarray:
        """Sum of the weighted values in the terms' lists, by row."""
        out = np.zeros(self.n, np.float64 if exact else np.int64)
        for sign, (rows, values, floats, ends) in enumerate(self.lists):
            own = terms[(query[terms] > 0) == sign]
            if not len(own):
                continue
            at = [slice(ends[t], ends[t + 1]) for t in own.tolist()]
            where = np.concatenate([rows[x] for x in at])
            self.read += len(where)
            weighted = np.repeat(query[own], [x.stop - x.start for x in at]) * np.concatenate([(floats if exact else values)[x] for x in at])
            if exact:
                out += np.bincount(where, weighted, self.n)
            else:
                np.add.at(out, where, weighted)
        return out

    def search(self, query: np.ndarray, own: int, k: int, floor: int | None) -> tuple[np.ndarray, np.ndarray]:
        """(score, row) of every row that may be among the query's k best, given the k-th best score so far."""
        bound = np.where(query > 0, query * self.most, query * self.least)
        order = np.argsort(-bound, kind="stable")
        order = order[query[order] != 0]
        exact = self.size * max(int(np.abs(query).max(initial=0)), 1) * max(len(query), 1) < 1 << 53
        data, q = (self.floats, query.astype(np.float64)) if exact else (self.values, query)
        self.held += self.n * len(order)
        if floor is None or floor <= 0 or not len(order):  # a row without any posting may compete: all lists are essential
            self.read += self.n * len(order)
            score = (q[order] @ data[order] if len(order) else np.zeros(self.n, data.dtype)).astype(np.int64)
            keep = (self.ids != own) & ((score >= floor) if floor is not None else True)
            return score[keep], np.flatnonzero(keep)
        weight = query[order].astype(np.float64)
        sums = np.concatenate([np.cumsum(bound[order][::-1])[::-1], [0]])  # what the terms from i on can add
        length = np.sqrt(np.concatenate([np.cumsum((weight * weight)[::-1])[::-1], [0.0]])) * (1 + 1e-9)
        slack = 1 + 1e-9 * (floor + float(sums[0]))  # more than what rounding takes away
        limit = np.minimum(sums, length * self.lengths.max(initial=0)) + slack
        if limit[0] < floor:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        essential = int(np.argmax(limit < floor))
        score = self._traverse(order[:essential], q, exact)
        alive = np.flatnonzero(score + np.minimum(sums[essential], length[essential] * self.lengths) + slack >= floor)
        # Probes: lists of the other sign for the essential terms, which can only take away, then both lists of the others.
        first = order[:essential]
        if 4 * len(alive) > self.n:  # so many probes that whole lists are read faster
            mine, ones = np.zeros(len(q), q.dtype), np.zeros(len(q))
            mine[first], ones[first] = q[first], 1
            score, seen = (mine @ data)[alive], (ones @ self.squares)[alive]
        else:
            part = data[first[:, None], alive[None, :]]
            score, seen = q[first] @ part, np.square(part, dtype=np.float64).sum(axis=0)
        self.read += essential * len(alive) - int(self.inside[(query[first] > 0).astype(int), first][:, alive].sum()) if self.counting else 0
        for at in range(essential, len(order) + PROBES, PROBES):
            known = min(at, len(order))
            rest = np.sqrt(np.maximum(self.lengths[alive] ** 2 - seen, 0)) * length[known]
            keep = score + np.minimum(sums[known], rest) + slack >= floor
            if not keep.all():
                alive, score, seen = alive[keep], score[keep], seen[keep]
            now = order[at : at + PROBES]
            if not len(now) or not len(alive):
                break
            part = data[now[:, None], alive[None, :]]
            self.read += part.size
            score, seen = score + q[now] @ part, seen + np.square(part, dtype=np.float64).sum(axis=0)
        score = score.astype(np.int64)
        keep = self.ids[alive] != own
        return score[keep], alive[keep]


def best(score: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best, ties to the smaller id; equal rows count each."""
    if len(score) > k:
        cut = np.partition(score, len(score) - k)[len(score) - k]
        over, level = score > cut, np.flatnonzero(score == cut)
        need = k - int(over.sum())
        if len(level) > need:
            level = level[np.argpartition(ids[level], need - 1)[:need]]
        pick = np.concatenate([np.flatnonzero(over), level])
        score, ids = score[pick], ids[pick]
    order = np.lexsort((ids, -score))
    return score[order], ids[order]


def _search_shards(queries, k: int):
    """Top k of each query among the partition's rows; the k-th best so far carries over from shard to shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_ids, matrix = queries.value
        kept: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64))] * len(own_ids)
        for batch in batches:
            for first in range(0, batch.num_rows, BLOCK):
                piece = batch.slice(first, BLOCK)
                rows, q = _matrix(piece["q"], matrix.shape[1]), matrix
                if rows.shape[1] > q.shape[1]:
                    q = np.pad(q, ((0, 0), (0, rows.shape[1] - q.shape[1])))
                shard = Shard(piece["vec_id"].to_numpy(), rows)
                for i, own in enumerate(own_ids.tolist()):
                    score, ids = kept[i]
                    new, at = shard.search(q[i], own, k, int(score[-1]) if len(score) >= k else None)
                    if len(new):
                        kept[i] = best(np.concatenate([score, new]), np.concatenate([ids, shard.ids[at]]), k)
        lengths = [len(s) for s, _ in kept]
        if sum(lengths):
            arrays = [np.repeat(own_ids, lengths), np.concatenate([i for _, i in kept]), np.concatenate([s for s, _ in kept])]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in arrays], ["query_id", "vec_id", "score"])

    return run


def top_k(vectors: DataFrame, every: int = 50, k: int = 5, scale: int = 256, vector: str = "embedding", query_bytes: int = QUERY_BYTES) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k best rows for each row whose vec_id is divisible by ``every``.

    Scores are exact integer inner products of floor(scale * component); ties go to the smaller vec_id. Candidates are
    all rows of another vec_id. Rows whose vector or vec_id is null, or whose vector holds a null or non-finite
    component, take no part; components must stay below 2**31 in size once scaled. Shorter vectors count as filled
    with 0. Repeated rows are candidates each; a repeated query id is asked once for each distinct vector, and ranked
    together. Queries go out as integer matrices of about ``query_bytes`` each, whatever their width; each pass reads
    all rows, and only k rows for each query and partition are shuffled. Other columns are left out.
    """
    spark = vectors.sparkSession
    rows = vectors.select("vec_id", quantise(vector, scale).alias("q")).where("vec_id is not null and q is not null")
    asked = rows.where(F.col("vec_id") % every == 0).distinct()
    total, width = asked.agg(F.count("*"), F.max(F.size("q"))).first()
    passes = max(1, -(-total * 8 * max(width or 0, 1) // query_bytes))
    found = None
    for n in range(passes):
        mine = asked.where(F.pmod(F.xxhash64("vec_id", "q"), F.lit(passes)) == n).orderBy("vec_id", "q").toArrow()
        lists = mine["q"].combine_chunks()
        block = spark.sparkContext.broadcast((mine["vec_id"].combine_chunks().to_numpy(), _matrix(lists if isinstance(lists, pa.Array) else lists.chunk(0)) if len(mine) else np.zeros((0, 1), np.int64)))
        part = rows.mapInArrow(_search_shards(block, k), "query_id long, vec_id long, score long")
        found = part if found is None else found.unionByName(part)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
