"""Connected components of an edge table by star contraction, all in joins and aggregations."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import scratch

HUBS = 200_000  # nodes with most neighbours that are sent to the executors at most; see :func:`_with_least`
HUB = 500  # neighbours of a hub at least


def _seal(edges: DataFrame, owner: str) -> tuple[DataFrame, tuple]:
    """Edges as a written table, with a signature that is equal for equal sets."""
    edges = scratch.write_table(edges.distinct(), "edges", owner)
    sign = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.sum("v")).first()
    return edges, tuple(sign)


def _with_least(edges: DataFrame, least: DataFrame, total: int) -> DataFrame:
    """Edges (u, v) joined to the rows of ``least`` (u, m, near), one for each u, ``near`` its number of edges.

    The edges of hubs, nodes with at least ``HUB`` and a ``1 / HUBS`` part of all edges, meet their rows by broadcast
    where they are; so no task gets all edges of one hub. There are at most ``2 * HUBS`` hubs, whatever the table.
    """
    hub = F.col("near") >= max(HUB, -(-total // HUBS))
    hubs = F.broadcast(least.where(hub).drop("near"))
    rest = edges.join(hubs, "u", "left_anti").join(least.where(~hub).drop("near"), "u")
    return rest.unionByName(edges.join(hubs, "u"))


def _hook_large(edges: DataFrame, total: int) -> DataFrame:
    """Tie every larger neighbour of a node to the least node around it."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("near"))
    return _with_least(both, least, total).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _hook_small(edges: DataFrame, total: int) -> DataFrame:
    """Tie a node and its smaller neighbours to the least of them. Rows have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("near"))
    others = _with_least(edges, least, total).where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return others.unionByName(least.select("u", F.col("m").alias("v")))


def components(edges: DataFrame, most_rounds: int = 60, owner: str = "query") -> DataFrame:
    """(node, component) for each node of ``edges`` (a, b) that is not the least of its component.

    ``component`` is the least node that can be reached. Loops, repeated edges and nulls are allowed and add nothing.
    Rounds grow with the logarithm of the longest path; each is cut from its lineage by a table in the shared folder,
    and the tables of the rounds before it are deleted.
    """
    name = f"{owner}/components-{uuid.uuid4().hex}"
    start = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    now, sign = _seal(start, f"{name}/0")
    for k in range(1, most_rounds + 1):
        if not sign[0]:
            break
        half = scratch.write_table(_hook_large(now, sign[0]).distinct(), "half", f"{name}/{k}/half")
        after, new = _seal(_hook_small(half, sign[0]), f"{name}/{k}")
        scratch.release(edges.sparkSession, f"{name}/{k - 1}")
        scratch.release(edges.sparkSession, f"{name}/{k}/half")
        now, sign, before = after, new, sign
        if sign == before:
            break
    else:
        raise RuntimeError(f"no fixed point after {most_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
