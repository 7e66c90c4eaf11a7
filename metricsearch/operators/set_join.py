"""Self-join of word sets within a Jaccard distance, by the rarest words of each set."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import METRICS, Marked
from ..sources import scratch

RANKED = 200_000  # words whose numbers of sets go out to the tasks; rarer ones count as equally rare
BLOCK = 2048  # sets of a rare word, or of a gathering of pairs, that one task holds together
HELD = 2_000_000  # meetings that a task sums up at once
PAIRS = 50_000_000  # meetings of one turn
GATHERED = 2 << 30  # bytes of sets, as text, that are gathered for pairs in one turn


def _rarest(counts, share: float):
    """(word, id, n, pos) of the words that a set must share with one it is near to: in an order of all words from
    rare to frequent, those before its last ceil(share * n) - 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = counts.value
        for batch in batches:
            words, ids, sizes, places = [], [], [], []
            for i, own in zip(batch["obj_id"].to_pylist(), batch["obj"].to_pylist(), strict=True):
                own.sort(key=lambda w: (known.get(w, 0), w))
                n = len(own)
                first = n - int(np.ceil((share - 1e-9) * n)) + 1 if n else 0
                words += own[:first]
                ids += [i] * min(n, first)
                sizes += [n] * min(n, first)
                places += range(min(n, first))
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array(ids, pa.int64()), pa.array(sizes, pa.int32()), pa.array(places, pa.int32())], ["word", "id", "n", "pos"])

    return run


def _numbers(n: np.ndarray, share: float) -> np.ndarray:
    """How many of its rarest words each set of n words shows."""
    return n - np.ceil((share - 1e-9) * n).astype(np.int64) + 1


def _cells(share: float):
    """(route, part, work, sets) of the sets that a rare word brings together, in order of their size: route is the
    smallest id, work the number of pairs whose sizes are near. Long lists are cut into pairs of blocks, whose sets
    meet those of the other side only."""
    kind = pa.list_(pa.struct([("id", pa.int64()), ("n", pa.int32()), ("pos", pa.int32()), ("side", pa.int32())]))

    def made(own, ids, n, pos, side, route, part):
        """One batch of cells; ``own`` numbers the cell of each set."""
        order = np.lexsort((ids, n, own))
        own, ids, n, pos, side = own[order], ids[order], n[order], pos[order], side[order]
        work = np.bincount(own, weights=_partners(own, n, share), minlength=len(route)).astype(np.int64)
        offsets = np.concatenate([[0], np.cumsum(np.bincount(own, minlength=len(route)))]).astype(np.int32)
        fields = [pa.array(ids), *(pa.array(x.astype(np.int32)) for x in (n, pos, side))]
        sets = pa.ListArray.from_arrays(offsets, pa.StructArray.from_arrays(fields, fields=list(kind.value_type)))
        return pa.RecordBatch.from_arrays([pa.array(route), pa.array(part.astype(np.int32)), pa.array(work), sets], ["route", "part", "work", "sets"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            own, ids, n, pos = _flat(batch["sets"], "id", "n", "pos")
            size = np.bincount(own, minlength=batch.num_rows)
            route = np.minimum.reduceat(ids, np.concatenate([[0], np.cumsum(size)[:-1]]))
            short = size <= BLOCK
            if short.any():
                mine = short[own]
                yield made((np.cumsum(short) - 1)[own[mine]], ids[mine], n[mine], pos[mine], np.zeros(mine.sum(), np.int64), route[short], np.zeros(short.sum(), np.int64))
            for k in np.flatnonzero(~short):
                at = np.flatnonzero(own == k)
                parts = int(-(-len(at) // BLOCK))
                block = _dealt(ids[at], parts)
                for i in range(parts):
                    for j in range(i, parts):
                        x, y = at[block == i], at[block == j] if j > i else at[:0]
                        both = np.concatenate([x, y])
                        if len(both):
                            side = np.repeat([1, 2], [len(x), len(y)]) if j > i else np.zeros(len(x), np.int64)
                            yield made(np.zeros(len(both), np.int64), ids[both], n[both], pos[both], side, route[k : k + 1], np.array([i * parts + j]))

    return run


def _flat(column: pa.Array, *names: str) -> list[np.ndarray]:
    """The row of each element of a column of lists, and the elements' fields."""
    flat = column.flatten()
    own = np.repeat(np.arange(len(column)), np.diff(column.offsets.to_numpy()))
    return [own, *(flat.field(x).to_numpy(zero_copy_only=False).astype(np.int64) for x in names)]


def _dealt(ids: np.ndarray, parts: int) -> np.ndarray:
    """A number under ``parts`` for each id, the same everywhere."""
    mixed = (ids.astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xBF58476D1CE4E5B9)
    mixed = (mixed ^ (mixed >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
    return ((mixed ^ (mixed >> np.uint64(29))) % np.uint64(parts)).astype(np.int64)


def _partners(own: np.ndarray, n: np.ndarray, share: float) -> np.ndarray:
    """For sets in order of cell and size, how many of those behind each in its cell are near enough in size."""
    most = np.floor(n / (share - 1e-9)).astype(np.int64)
    step = int(most.max(initial=0)) + 1
    return np.searchsorted(own * step + n, own * step + most, "right") - np.arange(len(n)) - 1


def _meet(share: float, turn: int, turns: int):
    """(a, b, need, c) of the pairs that the cells bring together whose smaller set is dealt to this turn: c is the number of
    shared rare words found here, need how many all cells must find."""

    def summed(found):
        a, b, need = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.lexsort((b, a))
        a, b, need = a[order], b[order], need[order]
        first = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))
        c = np.diff(np.append(first, len(a)))
        return pa.RecordBatch.from_arrays([pa.array(a[first]), pa.array(b[first]), pa.array(need[first].astype(np.int32)), pa.array(c)], ["a", "b", "need", "c"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = [], 0
        for batch in batches:
            own, ids, n, pos, side = _flat(batch["sets"], "id", "n", "pos", "side")
            rest = n - _numbers(n, share)
            many = np.where(_dealt(ids, turns) == turn, _partners(own, n, share), 0)
            upto, at = np.cumsum(many), 0
            while at < len(ids):
                end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + HELD, "right")))
                x = np.repeat(np.arange(at, end), many[at:end])
                y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(many[at:end]) - many[at:end], many[at:end])
                both = n[x] + n[y]
                most = np.minimum(pos[x], pos[y]) + np.minimum(n[x] - pos[x], n[y] - pos[y])
                go = (most * (1 + share) >= (share - 1e-9) * both) & (ids[x] != ids[y]) & ((side[x] == 0) | (side[x] != side[y]))
                x, y, both, at = x[go], y[go], both[go], end
                if len(x):
                    common = np.ceil((share - 1e-9) * both / (1 + share) - 1e-6).astype(np.int64)
                    found.append((ids[x], ids[y], common - np.maximum(rest[x], rest[y])))
                    held += len(x)
                if held >= HELD:
                    yield summed(found)
                    found, held = [], 0
        if found:
            yield summed(found)

    return run


def _marked(store, i: int) -> Marked:
    """Set i of a store, ready to be measured against others of it."""
    items = store.items[store.offsets[i] : store.offsets[i + 1]]
    member = np.zeros(len(store.words) + 1, bool)
    member[items] = True
    return Marked(len(items), member)


def _measure(r: float):
    """(a, b, dist) of the pairs within r, from rows that hold pairs and each of their sets once."""
    m = METRICS["jaccard"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                sets, pairs = batch["sets"][k].values, batch["pairs"][k].values
                ids, texts = sets.field("id").to_numpy(), ",".join(sets.field("obj").to_pylist())
                store = m.read(pa.array(json.loads(f"[{texts}]"), pa.list_(pa.string())))
                order = np.argsort(ids, kind="stable")
                a, b = (pairs.field(x).to_numpy() for x in ("a", "b"))
                by = np.argsort(a, kind="stable")
                a, b = a[by], b[by]
                x, y = (order[np.searchsorted(ids, e, sorter=order)] for e in (a, b))
                cuts = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1], [True]]))
                dist = np.concatenate([m.many(_marked(store, x[i]), store, y[i:j]) for i, j in zip(cuts[:-1], cuts[1:], strict=True)])
                near = dist <= r
                yield pa.RecordBatch.from_arrays([pa.array(a[near]), pa.array(b[near]), pa.array(dist[near])], ["a", "b", "dist"])

    return run


def _within(pairs: DataFrame, sets: DataFrame, r: float, owner: str) -> DataFrame:
    """(a, b, dist) of the pairs (a, b) within r. Pairs are gathered by the smallest id that one of their sets is paired
    with, and a set goes once to all pairs of a gathering, which is cut by blocks of sets where it is large."""
    ends = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = ends.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    cells = pairs.select("a", "b").join(least.toDF("a", "ma"), "a").join(least.toDF("b", "mb"), "b").select(F.least("ma", "mb").alias("cell"), "a", "b")
    cells = scratch.write_table(cells, "pair-cells", owner)
    sides = cells.select("cell", F.col("a").alias("id")).unionByName(cells.select("cell", F.col("b").alias("id"))).distinct()
    large = sides.groupBy("cell").count().where(F.col("count") > BLOCK).select("cell", F.ceil(F.col("count") / BLOCK).alias("parts"))
    block = lambda c: F.pmod(F.xxhash64(c), F.coalesce("parts", F.lit(1)))
    cells = cells.join(scratch.small_side(large), "cell", "left").select("cell", block("a").alias("i"), block("b").alias("j"), "a", "b")
    key, as_text = ["cell", "i", "j"], F.to_json("obj")  # text is a third of a list of words in a shuffle
    asked = lambda c: c.select(*key, F.col("a").alias("obj_id")).unionByName(c.select(*key, F.col("b").alias("obj_id"))).distinct()
    turns = -(-(asked(cells).join(sets.select("obj_id", F.octet_length(as_text).alias("size")), "obj_id").agg(F.sum("size")).first()[0] or 0) // GATHERED) or 1
    found = None
    for turn in range(turns):
        mine = cells.where(F.pmod(F.xxhash64(*key), F.lit(turns)) == turn)
        held = sets.select("obj_id", as_text.alias("obj")).join(scratch.small_side(asked(mine)), "obj_id").groupBy(*key).agg(F.collect_list(F.struct(F.col("obj_id").alias("id"), "obj")).alias("sets"))
        rows = held.join(mine.groupBy(*key).agg(F.collect_list(F.struct("a", "b")).alias("pairs")), key).select("sets", "pairs")
        with scratch.small_batches(sets.sparkSession, 100):
            near = scratch.write_table(rows.mapInArrow(_measure(r), "a long, b long, dist double"), "near-found", "set-join")
        found = near if found is None else found.unionByName(near)
    return found


def jaccard_self_join(sets: DataFrame, r: float) -> DataFrame:
    """(s_id, t_id, dist) of all pairs s_id < t_id of sets (obj_id, obj: distinct words) within r, for r below 1.

    Equal sets are one class. Classes meet over shared words among their rarest; those that share as many of them as
    near sets must, if their sizes and the words' places allow it, are measured. Members come in at the end.

    Disk holds each set and its rare words once, and in turns the pairs of about ``PAIRS`` meetings, then ``GATHERED``
    bytes of sets to measure. What a step shuffled is dropped at its end."""
    spark, share, owner = sets.sparkSession, 1.0 - r, f"set-join/{uuid.uuid4().hex}"
    with scratch.freed_shuffles(spark):
        named = sets.where("obj_id is not null and obj is not null").select("obj_id", F.sort_array("obj").alias("obj"))
        named = scratch.write_table(named.withColumn("own", F.unhex(F.sha2(F.to_json("obj"), 256))), "word-sets", owner, compression="zstd")
        same = scratch.write_table(named.groupBy("own").agg(F.min("obj_id").alias("obj_id"), F.collect_list("obj_id").alias("ids")).select("obj_id", "ids"), "word-classes", "set-join")
        copies = same.where(F.size("ids") > 1).select("obj_id", F.explode("ids").alias("id")).where("id <> obj_id").select(F.col("id").alias("obj_id"))
        one = named.select("obj_id", "obj").join(scratch.small_side(copies), "obj_id", "left_anti")
        often = one.select(F.explode("obj").alias("w")).groupBy("w").agg(F.count("*").alias("c")).where("c > 1").orderBy(F.desc("c"), "w").limit(RANKED).toArrow()
        counts = spark.sparkContext.broadcast(dict(zip(often["w"].to_pylist(), often["c"].to_pylist(), strict=True)))
        with scratch.small_batches(spark):
            rare = one.mapInArrow(_rarest(counts, share), "word string, id long, n int, pos int").select(F.xxhash64("word").alias("h"), F.struct("id", "n", "pos").alias("e"))
            lists = scratch.write_table(rare.groupBy("h").agg(F.collect_list("e").alias("sets")).where("size(sets) > 1").select("sets"), "rare-words", owner, compression="zstd")
        with scratch.small_batches(spark, 10_000):
            cells = lists.mapInArrow(_cells(share), "route long, part int, work long, sets array<struct<id:long,n:int,pos:int,side:int>>").where("work > 0")
            cells = scratch.write_table(cells.repartition("route", "part").sortWithinPartitions("route", "part"), "rare-cells", owner, compression="zstd")
            turns = -(-(cells.agg(F.sum("work")).first()[0] or 0) // PAIRS) or 1
            pairs = None
            for turn in range(turns):
                met = cells.select("sets").mapInArrow(_meet(share, turn, turns), "a long, b long, need int, c long")
                met = scratch.write_table(met.groupBy("a", "b", "need").agg(F.sum("c").alias("c")).where("c >= need").select("a", "b"), "near-pairs", "set-join")
                pairs = met if pairs is None else pairs.unionByName(met)
        found = _within(pairs, one, r, owner)
    scratch.release(spark, owner)
    members = same.select(F.col("obj_id").alias("class"), F.explode("ids").alias("id"))
    narrow = scratch.small_side(members)
    both = found.join(narrow.toDF("a", "i"), "a").join(narrow.toDF("b", "j"), "b").select(F.least("i", "j").alias("s_id"), F.greatest("i", "j").alias("t_id"), "dist")
    copies = members.toDF("class", "s_id").join(members.toDF("class", "t_id"), "class").where("s_id < t_id").select("s_id", "t_id", F.lit(0.0).alias("dist"))
    return both.unionByName(copies)
