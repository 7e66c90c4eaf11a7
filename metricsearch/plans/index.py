"""The tree over a distributed set: upper levels on the driver, one local tree for each part, searched where it lies.

Upper cells are split level by level: a few candidates of each cell come to the driver, centres go out, objects are
assigned in place. Only then are objects shuffled, once, to their parts, and a tree is built in each. The index is one
table of node entries (with the four relations of :func:`relations` as views) and is never gathered. Queries are routed
by the upper levels and joined to the parts they reach.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.metrics import METRICS, Ask
from ..operators.scan import best_k
from ..operators.voronoi import _as_objects, _joined
from ..sources import scratch
from .centers import Counter, assign_pruned, choose
from .tree import EPS, FAR, Node, VoronoiTree

PART_ROWS = 1_000_000  # objects of a part that one task builds a tree over; larger cells are split again
ENTRY = "node_id long, entry int, obj_id long, obj {obj}, subtree long, subtree_last long, cover_radius double, is_leaf boolean, live boolean, members array<long>, pair array<double>, pos array<double>, is_pivot boolean"


class TopTree(VoronoiTree):
    """Upper levels; the kids of its lowest nodes are numbers of parts."""

    def parts_of(self, kid) -> list[int]:
        if not isinstance(kid, Node):
            return [kid]
        return [p for k in kid.kids for p in self.parts_of(k)]

    def _report(self, node: Node, j: int, found: dict) -> None:
        for part in self.parts_of(node.kids[j]):
            found.setdefault(part, "report")

    def route(self, ask: Ask, r: float, flags: dict | None = None) -> dict[int, str]:
        """part -> inside, outside or report, for all parts that may hold objects within r."""
        found: dict[int, str] = {}
        r = min(r, FAR)
        stack = [(self.root, True)]
        while stack:
            kid, within = stack.pop()
            if not isinstance(kid, Node):
                found[kid] = "inside" if within else "outside"
            elif (flags or {}).get("mode") == "batch":
                stack += self._all_at_once(kid, within, ask, r, found)
            else:
                stack += self._inside(kid, ask, r, found, flags or {}) if within else self._outside(kid, ask, r, found, flags or {})
        return found

    def home(self, ask: Ask) -> int:
        kid = self.root
        while isinstance(kid, Node):
            kid = kid.kids[self.nearest(kid, ask)[0]]
        return kid

    def bound(self, ask: Ask, k: int, sizes: dict[int, int]) -> float:
        """A radius around which cells with k objects in all lie whole; infinite if there are fewer objects."""
        rows, stack = [], [self.root]
        while stack:
            node = stack.pop()
            d = ask.ds(node.entries)
            for j, kid in enumerate(node.kids):
                if isinstance(kid, Node):
                    stack.append(kid)
                else:
                    rows.append((float(d[j] + node.cover[j]), sizes.get(kid, 0)))
        total = 0
        for reach, n in sorted(rows):
            total += n
            if total >= k:
                return reach * (1 + EPS) + EPS
        return np.inf


@dataclass
class Index:
    """A distributed tree. ``nodes`` is the table of entries by part; ``top`` stays on the driver."""

    metric: str
    k: int
    leaf: int
    top: TopTree
    sizes: dict[int, int]
    nodes: DataFrame
    seed: int = 1
    seconds: dict[str, float] = field(default_factory=dict)

    @property
    def spark(self) -> SparkSession:
        return self.nodes.sparkSession


def _schema(metric: str) -> str:
    return "part long, " + ENTRY.format(obj=METRICS[metric].input_type)


def _local_rows(tree: VoronoiTree, ids: np.ndarray, part: int, objects: list, member_ids=None) -> list[tuple]:
    """Entries of a local tree in depth-first order; a subtree is one interval of node ids."""
    rows, number = [], [0]

    def walk(node: Node) -> tuple[int, int]:
        me, number[0] = (part << 32) | number[0], number[0] + 1
        at = len(rows)
        rows.extend([None] * len(node.entries))
        spans = [walk(kid) for kid in node.kids] if node.kids else [(None, None)] * len(node.entries)
        for e, i in enumerate(node.entries.tolist()):
            members = [int(ids[j]) for j in tree.members.get(i, [])] if node.leaf else []
            rows[at + e] = (part, me, e, int(ids[i]), objects[i], spans[e][0], spans[e][1], float(node.cover[e]), node.leaf, bool(node.live[e]), members, node.pairs[e].tolist(), node.coordinates[e].tolist(), e in node.pivots)
        return me, (part << 32) | (number[0] - 1)

    if tree.root is not None:
        walk(tree.root)
    return rows


def _arrow_type(metric: str) -> pa.DataType:
    lists = pa.list_(pa.float64())
    return {"l1": lists, "jaccard": pa.list_(pa.string()), "euclid": pa.struct([("x", pa.float64()), ("y", pa.float64())])}.get(metric, pa.struct([("s", lists), ("x", lists), ("y", lists)]))


def _entry_table(rows: list[tuple], metric: str) -> pa.Table:
    names = ["part", *(f.split()[0] for f in ("node_id l, entry i, obj_id l, obj o, subtree l, subtree_last l, cover_radius d, is_leaf b, live b, members a, pair a, pos a, is_pivot b").split(", "))]
    obj = _arrow_type(metric)
    fields = list(obj) if pa.types.is_struct(obj) else None
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), obj, pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.bool_(), pa.list_(pa.int64()), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.bool_()]
    columns = [list(c) for c in zip(*rows, strict=True)] if rows else [[] for _ in names]
    if fields:
        columns[4] = [dict(zip([f.name for f in fields], o, strict=True)) for o in columns[4]]
    return pa.table({n: pa.array(c, k) for n, c, k in zip(names, columns, kinds, strict=True)})


def _grow_part(metric: str, k: int, leaf: int, how: str, seed: int, aux: bool = True):
    m = METRICS[metric]

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.sort_by("obj_id").combine_chunks()
        column = table["obj"].combine_chunks() if table["obj"].num_chunks != 1 else table["obj"].chunk(0)
        store, part = m.read(column), key[0].as_py()
        tree = VoronoiTree(m, store, k, leaf, how, seed=seed, aux=aux).build()
        return _entry_table(_local_rows(tree, table["obj_id"].to_numpy(), part, _as_objects(metric, store, range(m.size(store)))), metric)

    return run


def load_tree(table: pa.Table, metric: str, k: int = 2, leaf: int = 2) -> tuple[VoronoiTree, np.ndarray, dict[int, list[int]]]:
    """A local tree from its entries, without measuring anything: tree, object id by position, members by position."""
    m = METRICS[metric]
    table = table.sort_by([("node_id", "ascending"), ("entry", "ascending")]).combine_chunks()
    column = table["obj"].chunk(0) if table["obj"].num_chunks == 1 else table["obj"].combine_chunks()
    store, ids = m.read(column), table["obj_id"].to_numpy()
    tree = VoronoiTree(m, store, k, max(k, leaf))
    number, subtree = table["node_id"].to_numpy(), table["subtree"].to_pylist()
    cover, live, is_leaf, pivot = (table[c].to_numpy() for c in ("cover_radius", "live", "is_leaf", "is_pivot"))
    pair, members = table["pair"].combine_chunks(), table["members"].to_pylist()
    pair = pair.chunk(0) if isinstance(pair, pa.ChunkedArray) else pair
    values, at = pair.values.to_numpy(), pair.offsets.to_numpy()
    cuts = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1], [True]]))
    nodes = {}
    for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
        n = b - a
        nodes[int(number[a])] = (Node(np.arange(a, b), values[at[a] : at[b]].reshape(n, n), np.flatnonzero(pivot[a:b]), None, cover[a:b].copy(), live[a:b].copy()), a, b)
    for node, a, b in nodes.values():
        if not is_leaf[a]:
            node.kids = [nodes[s][0] for s in subtree[a:b]]
    tree.root = nodes[min(nodes)][0] if nodes else None
    held = {int(ids[i]): x for i, x in enumerate(members) if x}
    tree.ident, tree.members = ids, {i: held[o] for i, o in enumerate(ids.tolist()) if o in held}  # at all its places
    return tree, ids, tree.members


def build(objs: DataFrame, metric: str, k: int = 36, leaf: int = 100, levels: int = 1, centers: str = "greedy", seed: int = 1, part_rows: int = PART_ROWS, owner: str = "index", top_k: int | None = None) -> Index:
    """Build the index over (obj_id, obj). ``levels`` upper levels are made of all cells; after that, cells of more
    than ``part_rows`` objects are split again, so hot cells do not stay hot. Null ids and objects are left out."""
    import time

    spark, m, top_k = objs.sparkSession, METRICS[metric], top_k or k
    seconds, clock = {}, time.time()
    rows = scratch.write_table(objs.select("obj_id", "obj").where("obj_id is not null and obj is not null").withColumns({"part": F.lit(0).cast("long"), "dist": F.lit(0.0)}), "index-rows", owner)
    sizes, next_part = {0: rows.count()}, 1
    seconds["distribute"] = time.time() - clock
    store, kids_of, node_of, step = m.pack([]), {}, {}, 0
    split = [0] if sizes[0] else []
    while split:
        clock = time.time()
        order = Window.partitionBy("part").orderBy(F.md5(F.concat(F.col("obj_id").cast("string"), F.lit(f"|{seed}"))), "obj_id")
        sample = rows.where(F.col("part").isin(split)).withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= 3 * top_k)
        picked = sample.select("part", "obj_id", "obj", "rn").toArrow().sort_by([("part", "ascending"), ("rn", "ascending")]).combine_chunks()
        seconds[f"centers {step}"] = time.time() - clock
        column = picked["obj"].combine_chunks()
        own, part_of = m.read(column.chunk(0) if isinstance(column, pa.ChunkedArray) else column), picked["part"].to_numpy()
        chosen: dict[int, tuple] = {}
        for part in split:
            mine = np.flatnonzero(part_of == part)
            at = choose(m, own, mine, top_k, centers, np.random.default_rng(seed), Counter())
            if len(at) < 2:
                continue
            first = m.size(store)
            local = m.pack([m.one(own, int(i)) for i in at])
            store = _joined(m, store, local)[0] if first else local
            entries = np.arange(first, first + len(at))
            pairs = np.stack([m.many(m.one(local, i), local) for i in range(len(at))])
            pairs = np.triu(pairs, 1) + np.triu(pairs, 1).T
            node_of[part] = Node(entries, pairs, [0, 1], [next_part + i for i in range(len(at))])
            chosen[part] = (local, pairs, next_part)
            kids_of[part] = list(range(next_part, next_part + len(at)))
            next_part += len(at)
        if not chosen:
            break
        clock = time.time()
        rows = scratch.write_table(_assign_level(rows, metric, chosen), f"index-level-{step}", owner)
        stats = rows.groupBy("part").agg(F.count("*").alias("n"), F.max("dist").alias("cover")).toPandas()
        sizes = dict(zip(stats["part"].tolist(), stats["n"].tolist(), strict=True))
        cover = dict(zip(stats["part"].tolist(), stats["cover"].tolist(), strict=True))
        for part in chosen:
            node_of[part].cover = np.array([cover.get(c, 0.0) for c in kids_of[part]])
        seconds[f"assign {step}"] = time.time() - clock
        step += 1
        fresh = [c for part in chosen for c in kids_of[part]]
        split = [c for c in (fresh if step < levels else sizes) if sizes.get(c, 0) > (leaf if step < levels else part_rows)]
    top = TopTree(m, store, max(2, top_k), max(2, top_k), seed=seed)
    for part, node in node_of.items():
        node.kids = [node_of.get(c, c) for c in kids_of[part]]
    top.root = node_of.get(0, 0)
    clock = time.time()
    nodes = rows.select("part", "obj_id", "obj").groupBy("part").applyInArrow(_grow_part(metric, k, leaf, centers, seed), _schema(metric))
    nodes = scratch.write_table(nodes, "index-nodes", owner)
    seconds["local trees"] = time.time() - clock
    return Index(metric, k, leaf, top, sizes, nodes, seed, seconds)


def _assign_level(rows: DataFrame, metric: str, chosen: dict[int, tuple]) -> DataFrame:
    """Rows of the parts in ``chosen`` go to the part of their nearest centre, in place."""
    shared, m = rows.sparkSession.sparkContext.broadcast(chosen), METRICS[metric]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            store, part, dist = m.read(batch["obj"]), batch["part"].to_numpy().copy(), batch["dist"].to_numpy().copy()
            before = part.copy()
            for p in np.unique(before).tolist():
                if p in shared.value:
                    centers, pairs, first = shared.value[p]
                    mine, size = np.flatnonzero(before == p), len(pairs)
                    both = _joined(m, centers, store)[0]
                    at, best = assign_pruned(m, both, np.arange(size), pairs, mine + size, Counter())
                    part[mine], dist[mine] = first + at, best
            yield pa.RecordBatch.from_arrays([batch["obj_id"], batch["obj"], pa.array(part), pa.array(dist)], ["obj_id", "obj", "part", "dist"])

    return rows.select("obj_id", "obj", "part", "dist").mapInArrow(run, f"obj_id long, obj {m.input_type}, part long, dist double")


# Searching


def _route(index: Index, queries: DataFrame, flags: dict) -> DataFrame:
    """queries (query_id, obj, r) with part, mode and n_dist, once for each part they reach."""
    shared, m, metric = index.spark.sparkContext.broadcast(index.top), METRICS[index.metric], index.metric

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = shared.value
        for batch in batches:
            store, r = m.read(batch["obj"]), batch["r"].to_numpy()
            row, part, mode, cost = [], [], [], []
            for i in range(batch.num_rows):
                ask = Ask(m, top.store, m.one(store, i))
                found = top.route(ask, float(r[i]), flags) if isinstance(top.root, Node) else {top.root: "inside"}
                for n, (p, how) in enumerate(sorted(found.items())):
                    row.append(i)
                    part.append(p)
                    mode.append(how)
                    cost.append(ask.count if n == 0 else 0)
            taken = batch.take(pa.array(row, pa.int64()))
            yield pa.RecordBatch.from_arrays([*(taken[c] for c in ("query_id", "obj", "r")), pa.array(part, pa.int64()), pa.array(mode, pa.string()), pa.array(cost, pa.int64())], ["query_id", "obj", "r", "part", "mode", "n_dist"])

    return queries.select("query_id", "obj", F.col("r").cast("double")).mapInArrow(run, f"query_id long, obj {METRICS[metric].input_type}, r double, part long, mode string, n_dist long")


def _search_part(metric: str, flags: dict, measure: bool):
    m = METRICS[metric]

    def run(key: tuple[pa.Scalar, ...], asked: pa.Table, entries: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if len(asked) and len(entries):
            tree, ids, members = load_tree(entries, metric)
            column = asked["obj"].combine_chunks()
            store = m.read(column.chunk(0) if isinstance(column, pa.ChunkedArray) else column)
            for i, (query_id, r, mode, cost) in enumerate(zip(*(asked[c].to_pylist() for c in ("query_id", "r", "mode", "n_dist")), strict=True)):
                ask, found = Ask(m, tree.store, m.one(store, i)), {}
                tree._search(tree.root, mode == "inside", ask, min(r, FAR), found, flags)
                lost = [p for p, d in found.items() if d is None]
                if measure and lost:
                    found.update(zip(lost, ask.ds(np.array(lost)).tolist(), strict=True))
                for p, d in found.items():
                    out += [(query_id, int(o), d, 0) for o in (ids[p], *members.get(p, ()))]
                out.append((query_id, None, None, ask.count + cost))
        columns = list(zip(*out, strict=True)) if out else [[]] * 4
        return pa.table({n: pa.array(list(c), t) for n, c, t in zip(("query_id", "obj_id", "dist", "n_dist"), columns, (pa.int64(), pa.int64(), pa.float64(), pa.int64()), strict=True)})

    return run


def range_search(index: Index, queries: DataFrame, measure: bool = True, **flags) -> DataFrame:
    """(query_id, obj_id, dist, n_dist) for queries (query_id, obj, r).

    Rows without obj_id carry counts of distance evaluations: see :func:`results` and :func:`costs`. Parts that lie
    whole within reach are reported by a join alone; ``measure`` fetches their distances too. All entries of a node are
    measured in one call; ``mode="sequential"`` measures one at a time and as few as it can, to count them.
    """
    flags = {"mode": "batch", **flags}
    routed = scratch.write_table(_route(index, queries, flags), "routed", "search")
    wanted = scratch.small_side(routed.select("part").distinct())
    nodes = index.nodes.join(wanted, "part", "left_semi")
    inner = routed if measure else routed.where("mode <> 'report'")
    inner = inner.withColumn("mode", F.when(F.col("mode") == "report", "outside").otherwise(F.col("mode")))
    out = inner.groupBy("part").cogroup(nodes.groupBy("part")).applyInArrow(_search_part(index.metric, flags, measure), "query_id long, obj_id long, dist double, n_dist long")
    if not measure:
        whole = routed.where("mode = 'report'").select("query_id", "part", "n_dist")
        held = nodes.where("is_leaf").select("part", F.explode(F.concat(F.array("obj_id"), "members")).alias("obj_id"))
        out = out.unionByName(whole.join(held, "part").select("query_id", "obj_id", F.lit(None).cast("double").alias("dist"), F.lit(0).cast("long").alias("n_dist")))
        out = out.unionByName(whole.select("query_id", F.lit(None).cast("long").alias("obj_id"), F.lit(None).cast("double").alias("dist"), "n_dist"))
    return out


def results(found: DataFrame) -> DataFrame:
    return found.where("obj_id is not null").drop("n_dist")


def costs(found: DataFrame) -> DataFrame:
    """(query_id, n_dist, n_results) of a search."""
    return found.groupBy("query_id").agg(F.sum("n_dist").alias("n_dist"), F.count("obj_id").alias("n_results"))


def _radius_part(metric: str, strategy: str, name: str):
    m = METRICS[metric]

    def run(key: tuple[pa.Scalar, ...], asked: pa.Table, entries: pa.Table) -> pa.Table:
        ids, radii, cost = [], [], []
        if len(asked) and len(entries):
            tree, _, members = load_tree(entries, metric)
            column = asked["obj"].combine_chunks()
            store = m.read(column.chunk(0) if isinstance(column, pa.ChunkedArray) else column)
            for i, (query_id, k) in enumerate(zip(asked["query_id"].to_pylist(), asked["k"].to_pylist(), strict=True)):
                ask = Ask(m, tree.store, m.one(store, i))
                if strategy == "best_first":
                    held, tree.members = tree.members, {}
                    best = tree._best_first(ask, k)
                    tree.members = held
                    r = best[-1][0] * (1 + EPS) + EPS if len(best) >= k else np.inf
                else:
                    r = tree.probe_radius(None, k, name, ask)
                ids.append(query_id)
                radii.append(r)
                cost.append(ask.count)
        return pa.table({"query_id": pa.array(ids, pa.int64()), "near": pa.array(radii, pa.float64()), "cost": pa.array(cost, pa.int64())})

    return run


def knn(index: Index, queries: DataFrame, strategy: str = "probe", name: str = "DE3", start: float | None = None, factor: float = 2.0, **flags) -> tuple[DataFrame, DataFrame]:
    """(query_id, rank, obj_id, dist) of queries (query_id, obj, k), and the costs of the search.

    ``probe``: the part a query falls into gives a radius that holds k objects, the upper levels give another; the
    smaller one makes one range search. ``best_first``: the part gives its exact k-th distance instead. ``growing``:
    range searches with a growing radius for the queries that lack results.
    """
    spark, m, metric = index.spark, METRICS[index.metric], index.metric
    total = sum(index.sizes.values())
    queries = queries.select("query_id", "obj", F.col("k").cast("int"))
    if strategy == "growing":
        return _growing(index, queries, start, factor, total, flags)
    shared, sizes = spark.sparkContext.broadcast(index.top), dict(index.sizes)

    def homes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = shared.value
        for batch in batches:
            store, k = m.read(batch["obj"]), batch["k"].to_pylist()
            part, bound, cost = [], [], []
            for i in range(batch.num_rows):
                ask = Ask(m, top.store, m.one(store, i))
                part.append(top.home(ask) if isinstance(top.root, Node) else top.root)
                bound.append(top.bound(ask, k[i], sizes) if isinstance(top.root, Node) else np.inf)
                cost.append(ask.count)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(part, pa.int64()), pa.array(bound, pa.float64()), pa.array(cost, pa.int64())], [*batch.schema.names, "part", "bound", "n_dist"])

    home = queries.mapInArrow(homes, f"query_id long, obj {m.input_type}, k int, part long, bound double, n_dist long")
    home = scratch.write_table(home, "homes", "search")
    nodes = index.nodes.join(scratch.small_side(home.select("part").distinct()), "part", "left_semi")
    near = home.select("query_id", "obj", "k", "part").groupBy("part").cogroup(nodes.groupBy("part")).applyInArrow(_radius_part(metric, strategy, name), "query_id long, near double, cost long")
    asked = home.join(near, "query_id", "left").select("query_id", "obj", "k", F.least("bound", F.coalesce("near", F.lit(float("inf")))).alias("r"), (F.col("n_dist") + F.coalesce("cost", F.lit(0))).alias("before"))
    asked = scratch.write_table(asked, "asked", "search")
    found = scratch.write_table(range_search(index, asked, **flags), "found", "search")
    best = best_k(results(found).join(asked.select("query_id", "k"), "query_id")).select("query_id", "rank", "obj_id", "dist")
    spent = costs(found).join(asked.select("query_id", "before"), "query_id").select("query_id", (F.col("n_dist") + F.col("before")).alias("n_dist"), "n_results")
    return best, spent


def _growing(index: Index, queries: DataFrame, start: float | None, factor: float, total: int, flags: dict) -> tuple[DataFrame, DataFrame]:
    cover = index.top.root.cover if isinstance(index.top.root, Node) else np.array([1.0])
    r = start or max(float(np.median(cover)) / 64, 1e-6)
    left, best, spent = queries, None, None
    while True:
        found = scratch.write_table(range_search(index, left.withColumn("r", F.lit(r)), **flags), "grown", "search")
        counts = costs(found)
        cost = counts.select("query_id", "n_dist", "n_results")
        spent = cost if spent is None else spent.unionByName(cost)
        full = left.join(counts, "query_id").where(F.col("n_results") >= F.least("k", F.lit(total))).select("query_id", "k")
        done = best_k(results(found).join(full, "query_id")).select("query_id", "rank", "obj_id", "dist")
        best = done if best is None else best.unionByName(done)
        left = scratch.write_table(left.join(full.select("query_id"), "query_id", "left_anti"), "left", "search")
        if left.isEmpty():
            return best, spent.groupBy("query_id").agg(F.sum("n_dist").alias("n_dist"), F.max("n_results").alias("n_results"))
        r *= factor


# Relations, saving and loading


def relations(index: Index) -> dict[str, DataFrame]:
    """The four relations: nodes, distances (e1 < e2), pivots, info."""
    n = index.nodes
    pairs = n.select("part", "node_id", F.col("entry").alias("e1"), F.posexplode("pair").alias("e2", "d")).where("e1 < e2")
    info = index.spark.createDataFrame([(index.metric, METRICS[index.metric].input_type, index.k, index.leaf, 2, index.seed, sum(index.sizes.values()), 1)], "metric string, obj_type string, k int, l int, n_pivots int, seed int, n_objects long, format_version int")
    return {"nodes": n.drop("pair", "pos", "is_pivot"), "distances": pairs, "pivots": n.select("part", "node_id", "entry", "pos", "is_pivot"), "info": info}


def _plain(top: TopTree) -> dict:
    def node(n):
        return {"entries": n.entries.tolist(), "pairs": n.pairs.tolist(), "cover": n.cover.tolist(), "kids": [node(c) if isinstance(c, Node) else int(c) for c in n.kids]} if isinstance(n, Node) else int(n)

    return node(top.root)


def save_index(index: Index, path: str) -> None:
    """Write the four relations, by part and in depth-first order, and the upper levels beside them."""
    for name, df in relations(index).items():
        if name == "info":
            df.write.mode("overwrite").parquet(f"{path}/{name}")
        else:
            df.repartition("part").sortWithinPartitions("part", "node_id").write.mode("overwrite").partitionBy("part").parquet(f"{path}/{name}")
    objs = _as_objects(index.metric, index.top.store, range(METRICS[index.metric].size(index.top.store)))
    top = json.dumps({"tree": _plain(index.top), "objects": [list(o) for o in objs], "sizes": {str(k): v for k, v in index.sizes.items()}})
    index.spark.createDataFrame([(top,)], "top string").write.mode("overwrite").parquet(f"{path}/top")


def load_index(spark: SparkSession, path: str) -> Index:
    """An index from its relations; no distance is evaluated."""
    info = spark.read.parquet(f"{path}/info").first()
    m = METRICS[info["metric"]]
    top = json.loads(spark.read.parquet(f"{path}/top").first()["top"])
    objs = [dict(zip(("s", "x", "y"), o, strict=True)) if m.input_type.startswith("struct<s") else o for o in top["objects"]]
    tree = TopTree(m, m.pack(objs), max(2, info["k"]), max(2, info["k"]), seed=info["seed"])

    def node(n):
        return Node(n["entries"], np.array(n["pairs"]).reshape(len(n["entries"]), -1), [0, 1], [node(c) if isinstance(c, dict) else c for c in n["kids"]], np.array(n["cover"])) if isinstance(n, dict) else n

    tree.root = node(top["tree"])
    rows, pivots = spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/pivots")
    pairs = spark.read.parquet(f"{path}/distances")
    both = pairs.select("part", "node_id", F.col("e1").alias("entry"), F.col("e2").alias("other"), "d").unionByName(pairs.select("part", "node_id", F.col("e2").alias("entry"), F.col("e1").alias("other"), "d"))
    both = both.unionByName(rows.select("part", "node_id", "entry", F.col("entry").alias("other"), F.lit(0.0).alias("d")))
    lists = both.groupBy("part", "node_id", "entry").agg(F.transform(F.array_sort(F.collect_list(F.struct("other", "d"))), lambda x: x["d"]).alias("pair"))
    nodes = rows.join(lists, ["part", "node_id", "entry"]).join(pivots, ["part", "node_id", "entry"])
    names = [f.split()[0] for f in ("part l, node_id l, entry i, obj_id l, obj o, subtree l, subtree_last l, cover_radius d, is_leaf b, live b, members a, pair a, pos a, is_pivot b").split(", ")]
    return Index(info["metric"], info["k"], info["l"], tree, {int(k): v for k, v in top["sizes"].items()}, nodes.select(F.col("part").cast("long"), *names[1:]), info["seed"])


def subtree(index: Index, node_id: int) -> DataFrame:
    """Members below a node: one interval of node ids."""
    last = index.nodes.where(F.col("subtree") == node_id).agg(F.max("subtree_last")).first()[0]
    inner = F.col("node_id") >= node_id if last is None else F.col("node_id").between(node_id, last)
    return index.nodes.where(inner & F.col("is_leaf")).select(F.explode(F.concat(F.array("obj_id"), "members")).alias("obj_id"))


# Changes


def _leaves(index: Index, parts: list[int]) -> DataFrame:
    """(part, obj_id, obj) of the members of some parts, equal ones expanded."""
    held = index.nodes.where(F.col("part").isin(parts) & F.col("is_leaf"))
    return held.select("part", F.explode(F.concat(F.array("obj_id"), "members")).alias("obj_id"), "obj")


def _rebuild(index: Index, parts: list[int], rows: DataFrame) -> Index:
    grown = rows.groupBy("part").applyInArrow(_grow_part(index.metric, index.k, index.leaf, "greedy", index.seed), _schema(index.metric))
    nodes = index.nodes.where(~F.col("part").isin(parts)).unionByName(grown)
    nodes = scratch.write_table(nodes, "index-changed", "index")
    sizes = {r["part"]: r["n"] for r in nodes.where("is_leaf").groupBy("part").agg(F.sum(1 + F.size("members")).alias("n")).collect()}
    return Index(index.metric, index.k, index.leaf, index.top, sizes, nodes, index.seed)


def insert(index: Index, objs: DataFrame) -> Index:
    """The index with (obj_id, obj) added: routed along the upper levels, and the parts they fall into built anew.
    Cover radii above grow where needed."""
    m, top = METRICS[index.metric], index.top
    shared = index.spark.sparkContext.broadcast(top)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            store, parts, ways = m.read(batch["obj"]), [], []
            for i in range(batch.num_rows):
                ask, kid, way = Ask(m, shared.value.store, m.one(store, i)), shared.value.root, []
                while isinstance(kid, Node):
                    j, d, _ = shared.value.nearest(kid, ask)
                    way.append({"center": int(kid.entries[j]), "d": d})
                    kid = kid.kids[j]
                parts.append(kid)
                ways.append(way)
            kind = pa.list_(pa.struct([("center", pa.int64()), ("d", pa.float64())]))
            yield pa.RecordBatch.from_arrays([batch["obj_id"], batch["obj"], pa.array(parts, pa.int64()), pa.array(ways, kind)], ["obj_id", "obj", "part", "way"])

    placed = scratch.write_table(objs.select("obj_id", "obj").mapInArrow(place, f"obj_id long, obj {m.input_type}, part long, way array<struct<center:long,d:double>>"), "inserted", "index")
    grow = {r["center"]: r["d"] for r in placed.select(F.explode("way").alias("w")).groupBy("w.center").agg(F.max("w.d").alias("d")).collect()}
    stack = [top.root]
    while stack:
        n = stack.pop()
        if isinstance(n, Node):
            n.cover = np.maximum(n.cover, [grow.get(int(e), 0.0) for e in n.entries])
            stack += n.kids
    parts = [r["part"] for r in placed.select("part").distinct().collect()]
    return _rebuild(index, parts, _leaves(index, parts).unionByName(placed.select("part", "obj_id", "obj")))


def delete(index: Index, ids: DataFrame) -> Index:
    """The index without the objects of ``ids`` (obj_id); absent ids change nothing. Cover radii above stay."""
    ids = scratch.small_side(ids.select("obj_id").distinct())
    held = index.nodes.where("is_leaf").select("part", F.explode(F.concat(F.array("obj_id"), "members")).alias("obj_id"))
    parts = [r["part"] for r in held.join(ids, "obj_id", "left_semi").select("part").distinct().collect()]
    return _rebuild(index, parts, _leaves(index, parts).join(ids, "obj_id", "left_anti")) if parts else index


def rebuild(index: Index, objs: DataFrame, changed: int, share: float = 0.1, **how) -> Index:
    """A new index over ``objs`` once more than ``share`` of the objects have changed, else the same one."""
    return build(objs, index.metric, index.k, index.leaf, **how) if changed > share * max(1, sum(index.sizes.values())) else index


def members_table(index: Index) -> DataFrame:
    """(obj_id, part) of every object: each occurs in one leaf."""
    return index.nodes.where("is_leaf").select(F.explode(F.concat(F.array("obj_id"), "members")).alias("obj_id"), "part")


__all__ = ["Index", "build", "costs", "delete", "insert", "knn", "load_index", "members_table", "pd", "range_search", "rebuild", "relations", "results", "save_index", "subtree"]
