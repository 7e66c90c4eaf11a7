"""Exact Jaccard self-join of word-shingle sets by a token-group matrix, and the components of its links.

1. One row for each document: set size, a 128-bit digest of the set, and its least shingles. Documents of one digest
   are one class, whose least document stands for it.
2. Groups of similar documents: classes that share one of their least shingles are held against the least class among
   them, and linked ones make up a group. Large groups are cut into chunks of about ``CHUNK`` documents.
3. The matrix: for each shingle of a prefix (the rarest part of a set) the chunks that hold it in a member's prefix.
   A link between sets of sizes m <= n has at least 6m/7 shingles in common, so its least common shingles stand in
   both prefixes; a document is a candidate for a chunk if it meets it in ``SHARED`` of them, by size and position.
4. A candidate opens its chunk only if parities of a member and its overlap with the union of the chunk's sets allow
   the similarity; then members are compared one by one. Pairs within one group need no comparison, as it is connected already.
5. Where all links are asked for, and not the components alone, step 4 gives way to blocks: each pair of chunks of one
   group, and each pair of chunks that a candidate connects, is compared once, every member with every member.

The order of shingles is free: those found often anywhere come last, so passages that many documents share hardly
occur in prefixes. It rests on counts by batch and only changes the work, never the result. No pair is capped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import scratch, words
from .components import components

SKETCH = 4  # least shingles kept for grouping
SHARED = 4  # common prefix shingles a candidate needs, or as many as a link of its size has
CHUNK = 64
SLOTS = 1024  # of the parities that bound an overlap; a power of two
OFTEN = 16  # a shingle counted this often goes to the end of the order
MOST_OFTEN = 400_000  # the longest list of such shingles that is sent to the executors, 8 bytes each
BATCH_OFTEN = 20_000
COUNTED, COUNTED_SHINGLES = 2000, 1 << 21  # rows or shingles whose counts are taken together
STRIP = 200_000  # pairs of postings that are met at once


def _least_overlap(n: int, percent: int) -> int:
    """Least number of common shingles of a set of n with any set that it links to: n * percent / 100, rounded up."""
    return -(-n * percent // 100)


def _digest(shingles: np.ndarray) -> tuple[int, int]:
    a = np.bitwise_xor.reduce(words.mix(shingles * np.uint64(words.MIX_1)), initial=np.uint64(0))
    b = np.add.reduce(words.mix(shingles ^ np.uint64(words.MIX_2)), dtype=np.uint64)
    return int(np.uint64(a).view(np.int64)), int(np.uint64(b).view(np.int64))


def _parity(shingles: np.ndarray) -> list[int]:
    """Parities of the counts of shingles by slot, as 64-bit words: the slots in which two sets differ bound from
    below how many shingles are in one of them only."""
    odd = np.bincount((shingles & np.uint64(SLOTS - 1)).astype(np.int64), minlength=SLOTS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64).tolist()


def _found_often(sets: list[np.ndarray]) -> list[tuple]:
    """Rows of kind 1 for shingles that several of the sets hold, at most ``BATCH_OFTEN``, those held most."""
    found, count = np.unique(np.concatenate([np.zeros(0, np.uint64), *sets]), return_counts=True)
    found, count = found[count > 1].view(np.int64), count[count > 1]
    if len(found) > BATCH_OFTEN:
        top = np.argpartition(-count, BATCH_OFTEN)[:BATCH_OFTEN]
        found, count = found[top], count[top]
    return [(1, x, n, None, None, None, None) for x, n in zip(found.tolist(), count.tolist(), strict=True)]


def _survey(width: int):
    """Rows of kind 0: (doc_id, size, digest, least shingles, parities); of kind 1: (shingle, sets that hold it) over
    runs of ``COUNTED`` rows or some more, fewer at the end of a task or where sets are very large."""
    kinds = [pa.int32(), *[pa.int64()] * 4, *[pa.list_(pa.int64())] * 2]

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        columns = list(zip(*rows, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["kind", "doc_id", "n", "h1", "h2", "least", "bits"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        for batch in words.slices(batches):
            rows = []
            for doc_id, s in zip(batch["doc_id"].to_pylist(), words.shingle_sets(batch["text"], width), strict=True):
                rows.append((0, doc_id, len(s), *(_digest(s) if len(s) else (0, 0)), s[:SKETCH].view(np.int64).tolist(), _parity(s)))
                held.append(s)
            if len(held) >= COUNTED or sum(map(len, held)) >= COUNTED_SHINGLES:
                rows += _found_often(held)
                held = []
            if rows:
                yield batch_of(rows)
        if rest := _found_often(held):
            yield batch_of(rest)

    return run


def _postings(width: int, percent: int, often):
    """(shingle, doc_id, n, pos, grp, chunk) of each document's prefix, shingles counted often put last."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = often.value
        for batch in words.slices(batches):
            sets, lengths, sizes, places = [], [], [], []
            for s in words.shingle_sets(batch["text"], width):
                n = len(s)
                if len(last) and n:
                    at = np.searchsorted(last, s)
                    late = last[np.minimum(at, len(last) - 1)] == s
                    s = np.concatenate([s[~late], s[late]])
                m = min(n, n - _least_overlap(n, percent) + SHARED) if n else 0
                sets.append(s[:m])
                lengths.append(m)
                sizes.append(n)
                places.append(np.arange(m, dtype=np.int32))
            if not sum(lengths):
                continue
            by_row = np.repeat(np.arange(len(lengths)), lengths)
            size = np.array(sizes, np.int32)[by_row]
            pick = lambda name: pa.array(batch[name].to_numpy(zero_copy_only=False)[by_row])
            arrays = [pa.array(np.concatenate(sets).view(np.int64)), pick("doc_id"), pa.array(size), pa.array(np.concatenate(places)), pick("grp"), pick("chunk")]
            yield pa.RecordBatch.from_arrays(arrays, ["shingle", "doc_id", "n", "pos", "grp", "chunk"])

    return run


def _meet(q: np.ndarray, m: np.ndarray, c: dict[str, np.ndarray], percent: int) -> np.ndarray:
    """For index pairs (q, m) into one shingle's postings: may q, the larger document, link to m, judged here?"""
    nq, nm, pq, pm = (c[k][i].astype(np.int64) for k, i in (("n", q), ("n", m), ("pos", q), ("pos", m)))
    need = -(-(nq + nm) * percent // (100 + percent))
    ok = (c["grp"][q] != c["grp"][m]) & ((nq > nm) | ((nq == nm) & (c["doc_id"][q] > c["doc_id"][m]))) & (100 * nm >= percent * nq)
    own = -(-2 * percent * nm // (100 + percent))
    return ok & (pm < nm - own + SHARED) & (np.minimum(pq, pm) + 1 + np.minimum(nq - pq - 1, nm - pm - 1) >= need)


def _candidates(percent: int):
    """From postings sorted by shingle: a row (q, grp, chunk) for each document and chunk that meet at a shingle."""
    names = ["shingle", "doc_id", "n", "pos", "grp", "chunk"]

    def of_run(c: dict[str, np.ndarray], a: int, b: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of a run, met in strips of bounded size; those within one group are never made."""
        order = a + np.argsort(c["grp"][a:b], kind="stable")
        grp = c["grp"][order]
        cuts = np.flatnonzero(np.concatenate([[True], grp[1:] != grp[:-1], [True]])).tolist()
        for low, high in zip(cuts[:-1], cuts[1:], strict=True):
            others = np.concatenate([order[:low], order[high:]])
            step = max(1, STRIP // max(1, len(others)))
            for first in range(low, high, step):
                mine = order[first : min(high, first + step)]
                for at in range(0, len(others), STRIP):
                    some = others[at : at + STRIP]
                    q, m = np.repeat(mine, len(some)), np.tile(some, len(mine))
                    ok = _meet(q, m, c, percent)
                    if ok.any():
                        yield q[ok], m[ok]

    def pairs(c: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        s = c["shingle"]
        cuts = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1], [True]]))
        length = np.diff(cuts)
        two = cuts[:-1][length == 2]
        found = [(q[ok], m[ok]) for q, m in ((two, two + 1), (two + 1, two)) for ok in (_meet(q, m, c, percent),)]
        for a, n in zip(cuts[:-1][length > 2].tolist(), length[length > 2].tolist(), strict=True):
            if (c["grp"][a : a + n] != c["grp"][a]).any():
                found += of_run(c, a, a + n)
        if not sum(len(q) for q, _ in found):
            return
        q, m = np.concatenate([x for x, _ in found]), np.concatenate([x for _, x in found])
        met = pd.DataFrame({"shingle": c["shingle"][q], "q": c["doc_id"][q], "grp": c["grp"][m], "chunk": c["chunk"][m], "n": c["n"][q]})
        yield pa.RecordBatch.from_pandas(met.drop_duplicates()[["q", "grp", "chunk", "n"]], preserve_index=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[dict[str, np.ndarray]] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            c = {k: batch[k].to_numpy(zero_copy_only=False).astype(np.int64, copy=False) for k in names}
            cut = int(np.searchsorted(c["shingle"], c["shingle"][-1]))  # the last shingle may go on in the next batch
            if cut:
                kept.append({k: v[:cut] for k, v in c.items()})
                yield from pairs({k: np.concatenate([x[k] for x in kept]) for k in names})
                kept = []
            kept.append({k: v[cut:].copy() for k, v in c.items()})
        if kept:
            yield from pairs({k: np.concatenate([x[k] for x in kept]) for k in names})

    return run


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in words.slices(batches):
            sets = [s.tobytes() for s in words.shingle_sets(batch["text"], width)]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(sets, pa.binary())], ["doc_id", "shingles"])

    return run


def _open(percent: int):
    """(a, b) for each candidate (q, shingles) whose chunk has a member that links; the matrix row bounds it first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a_ids, b_ids = [], []
            for q, own, members in zip(batch["q"].to_pylist(), batch["shingles"], batch["members"], strict=True):
                s = np.frombuffer(own.as_buffer(), np.uint64)
                inner = members.values
                each = [np.frombuffer(x.as_buffer(), np.uint64) for x in inner.field("shingles")]
                if len(each) > 1:
                    union = np.unique(np.concatenate(each))
                    at = np.minimum(np.searchsorted(union, s), len(union) - 1)
                    if 100 * int((union[at] == s).sum()) < percent * len(s):
                        continue
                for b, t in zip(inner.field("doc_id").to_pylist(), each, strict=True):
                    small, large = (s, t) if len(s) <= len(t) else (t, s)
                    if not len(small) or 100 * len(small) < percent * len(large):
                        continue
                    at = np.minimum(np.searchsorted(large, small), len(large) - 1)
                    both = int((large[at] == small).sum())
                    if 100 * both >= percent * (len(s) + len(t) - both):
                        a_ids.append(q)
                        b_ids.append(b)
                        break
            yield pa.RecordBatch.from_arrays([pa.array(a_ids, pa.int64()), pa.array(b_ids, pa.int64())], ["a", "b"])

    return run


def _possible(candidates: DataFrame, members: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Candidates (q, grp, chunk) for which the parities allow a link to some member of the chunk.

    Sets of sizes a and b whose parities differ in d slots have at most (a + b - d) / 2 shingles in common.
    """
    known = classes.select("rep", F.col("n").cast("long").alias("n"), "bits")
    named = scratch.small_side(candidates.select("grp", "chunk").distinct())
    theirs = members.join(named, ["grp", "chunk"], "left_semi").join(known.toDF("doc_id", "m", "b"), "doc_id").drop("doc_id")
    mine = candidates.join(known.toDF("q", "n", "a"), "q")
    differ = F.aggregate(F.zip_with("a", "b", lambda x, y: F.bit_count(x.bitwiseXOR(y)).cast("long")), F.lit(0).cast("long"), lambda t, x: t + x)
    both = F.col("n") + F.col("m")
    met = mine.join(theirs, ["grp", "chunk"]).where((100 + percent) * (both - differ) >= 2 * percent * both)
    return met.select("q", "grp", "chunk").distinct()


def _verify(candidates: DataFrame, members: DataFrame, docs: DataFrame, width: int, percent: int, owner: str) -> DataFrame:
    """Links among ``candidates`` (q, grp, chunk), given ``members`` (grp, chunk, doc_id) of the chunks they name."""
    named = scratch.small_side(candidates.select("grp", "chunk").distinct())
    members = scratch.write_table(members.join(named, ["grp", "chunk"], "left_semi"), "members", owner)
    wanted = scratch.small_side(candidates.select(F.col("q").alias("doc_id")).union(members.select("doc_id")).distinct())
    sets = docs.join(wanted, "doc_id", "left_semi").mapInArrow(_sets(width), "doc_id long, shingles binary")
    with scratch.small_batches(docs.sparkSession):
        sets = scratch.write_table(sets, "sets", owner)
    matrix = members.join(sets, "doc_id").groupBy("grp", "chunk").agg(F.collect_list(F.struct("doc_id", "shingles")).alias("members"))
    asked = candidates.join(sets.withColumnRenamed("doc_id", "q"), "q").join(matrix, ["grp", "chunk"])
    links = asked.select("q", "shingles", "members").mapInArrow(_open(percent), "a long, b long")
    with scratch.small_batches(docs.sparkSession, 200):
        return scratch.write_table(links, "links", owner)


def _class_sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in words.slices(batches):
            sets = list(words.shingle_sets(batch["text"], width))
            digests = [_digest(s) if len(s) else (0, 0) for s in sets]
            columns = [[len(s) for s in sets], [x for x, _ in digests], [x for _, x in digests]]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array(c, pa.int64()) for c in columns), pa.array([s.tobytes() for s in sets], pa.binary())], ["doc_id", "n", "h1", "h2", "shingles"])

    return run


def _common(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """Numbers of common shingles of each set of ``a`` with each of ``b``, over slices of the shingles they share."""
    every = np.intersect1d(np.unique(np.concatenate(a)), np.unique(np.concatenate(b)), assume_unique=True)
    out = np.zeros((len(a), len(b)), np.int64)
    for at in range(0, len(every), 16_384):
        some, sides = every[at : at + 16_384], []
        for sets in (a, b):
            side = np.zeros((len(sets), len(some)), np.float32)
            for i, s in enumerate(sets):
                place = np.minimum(np.searchsorted(some, s), len(some) - 1)
                side[i, place[some[place] == s]] = 1
            sides.append(side)
        out += (sides[0] @ sides[1].T).astype(np.int64)
    return out


def _blocks(percent: int, counts: bool):
    """All links between the members of two chunks, or within one: pairs (a, b, common), or (class_id, n) for each
    class that has some."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for same, mine, theirs in zip(batch["same"].to_pylist(), batch["mine"], batch["theirs"], strict=True):
                names, sets = [], []
                for side in (mine, theirs):
                    names.append(np.array(side.values.field("class_id").to_pylist(), object))
                    sets.append([np.frombuffer(x.as_buffer(), np.uint64) for x in side.values.field("shingles")])
                size = [np.array([len(s) for s in x], np.int64) for x in sets]
                both = _common(*sets)
                link = 100 * both >= percent * (size[0][:, None] + size[1][None, :] - both)
                if same:
                    link &= names[0][:, None] < names[1][None, :]
                i, j = np.nonzero(link)
                if not len(i):
                    continue
                if counts:
                    found, n = np.unique(np.concatenate([names[0][i], names[1][j]]).astype(str), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(found.tolist(), pa.string()), pa.array(n, pa.int64())], ["class_id", "n"])
                else:
                    a, b = names[0][i], names[1][j]
                    swap = a > b
                    a, b = np.where(swap, b, a), np.where(swap, a, b)
                    yield pa.RecordBatch.from_arrays([pa.array(a.tolist(), pa.string()), pa.array(b.tolist(), pa.string()), pa.array(both[i, j], pa.int64())], ["a", "b", "common"])

    return run


def _class_id() -> Column:
    return F.concat(F.lpad(F.hex("h1"), 16, "0"), F.lpad(F.hex("h2"), 16, "0"), F.lit("-"), F.col("n").cast("string"))


def _all_links(candidates: DataFrame, whole: DataFrame, placed: DataFrame, classes: DataFrame, docs: DataFrame, width: int, percent: int, owner: str, counts: bool) -> DataFrame:
    """Links of all pairs of classes, given ``candidates`` (q, grp, chunk) between groups; see :func:`_blocks`.

    Each class is in one chunk and each pair of chunks is met once, so no pair is compared twice. Two classes that
    share their least document (one id with several texts) are in one chunk.
    """
    chunks = placed.select("grp", "chunk").distinct()
    lone = classes.groupBy("rep").agg(F.count("*").alias("texts")).where("texts > 1").select(F.col("rep").alias("doc_id"))
    own = chunks.unionByName(whole.join(lone, "doc_id", "left_semi").select("grp", "chunk")).distinct()
    inside = own.toDF("grp", "x").join(own.toDF("grp", "y"), "grp").where("x <= y").select("grp", "x", F.col("grp").alias("grp2"), "y")
    met = candidates.join(whole.toDF("q", "grp2", "y"), "q").select(F.col("grp").alias("g"), F.col("chunk").alias("c"), "grp2", "y")
    low, high = F.struct("g", "c"), F.struct(F.col("grp2").alias("g"), F.col("y").alias("c"))
    met = met.select(F.least(low, high).alias("l"), F.greatest(low, high).alias("h")).select("l.g", "l.c", F.col("h.g").alias("g2"), F.col("h.c").alias("c2"))
    blocks = scratch.write_table(inside.toDF("g", "c", "g2", "c2").unionByName(met).distinct(), "blocks", owner)
    named = blocks.select("g", "c").union(blocks.select("g2", "c2")).distinct().toDF("grp", "chunk")
    members = scratch.write_table(whole.join(scratch.small_side(named), ["grp", "chunk"], "left_semi"), "block-members", owner)
    texts = docs.join(scratch.small_side(members.select("doc_id")), "doc_id", "left_semi")
    sets = texts.mapInArrow(_class_sets(width), "doc_id long, n long, h1 long, h2 long, shingles binary")
    with scratch.small_batches(docs.sparkSession):
        sets = scratch.write_table(sets, "block-sets", owner)
    sets = sets.join(classes.select(F.col("rep").alias("doc_id"), "n", "h1", "h2"), ["doc_id", "n", "h1", "h2"], "left_semi").dropDuplicates(["n", "h1", "h2"])
    matrix = members.join(sets, "doc_id").groupBy("grp", "chunk").agg(F.collect_list(F.struct(_class_id().alias("class_id"), "shingles")).alias("members"))
    matrix = scratch.write_table(matrix, "matrix", owner)
    asked = blocks.join(matrix.toDF("g", "c", "mine"), ["g", "c"]).join(matrix.toDF("g2", "c2", "theirs"), ["g2", "c2"])
    asked = asked.select(((F.col("g") == F.col("g2")) & (F.col("c") == F.col("c2"))).alias("same"), "mine", "theirs")
    with scratch.small_batches(docs.sparkSession, 20):
        return scratch.write_table(asked.mapInArrow(_blocks(percent, counts), "class_id string, n long" if counts else "a string, b string, common long"), "all-links", owner)


def ngram_links(docs: DataFrame, width: int = 5, percent: int = 75, owner: str = "query") -> tuple[DataFrame, DataFrame]:
    """All links of ``docs``: pairs (a, b, common) of class ids, a < b, and the members (doc_id, class_id) of classes.

    A class holds the rows with one set of shingles; its members link to each other and to the members of each class
    it is paired with. Rows without doc_id or shingles are in no class. A group of N different near copies has up to
    N * (N - 1) / 2 pairs, and all are given. See :func:`ngram_components` for the rest.
    """
    rows, _, links = _join(docs, width, percent, owner, "pairs")
    return links, rows.where("n > 0 and doc_id is not null").select("doc_id", _class_id().alias("class_id")).distinct()


def ngram_link_counts(docs: DataFrame, width: int = 5, percent: int = 75, owner: str = "query") -> DataFrame:
    """(doc_id, n_shingles, component_id, n_links) of every row of ``docs``: as :func:`ngram_components`, with the
    number of other classes, sets of shingles different from the row's own, that the row's set links to.

    Pairs are counted block by block where they are found and not written out.
    """
    rows, named, links = _join(docs, width, percent, owner, "counts")
    total = links.groupBy("class_id").agg(F.sum("n").alias("n_links"))
    out = rows.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), _class_id()).alias("class_id"))
    out = out.join(scratch.small_side(total), "class_id", "left").join(scratch.small_side(named), F.col("doc_id") == F.col("node"), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"), F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"))


def ngram_components(docs: DataFrame, width: int = 5, percent: int = 75, owner: str = "query") -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row of ``docs`` (doc_id, text; other columns are left out).

    Two documents link if 100 * common >= ``percent`` * all of their distinct shingles of ``width`` words; a component
    is named by its least doc_id. Null, empty and blank texts have no shingles and stand alone. Rows with one doc_id
    are one document: each keeps its own set size, and all share the component of any of them. A row without doc_id
    links to nothing and has a null component. Very long texts are read whole. An empty table gives no rows.
    """
    rows, named, _ = _join(docs, width, percent, owner)
    out = rows.select("doc_id", F.col("n").alias("n_shingles")).join(scratch.small_side(named), F.col("doc_id") == F.col("node"), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def _join(docs: DataFrame, width: int, percent: int, owner: str, links_as: str | None = None) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """Rows with their sizes and digests, (node, component), and all links as "pairs" or "counts" if asked for."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    survey = docs.mapInArrow(_survey(width), "kind int, doc_id long, n long, h1 long, h2 long, least array<long>, bits array<long>")
    with scratch.small_batches(spark, 2000):
        survey = scratch.write_table(survey, "survey", owner)
    rows = survey.where("kind = 0").drop("kind")
    classes = rows.where("n > 0 and doc_id is not null").groupBy("h1", "h2", "n").agg(F.min("doc_id").alias("rep"), F.first("least").alias("least"), F.first("bits").alias("bits"), F.count("*").alias("copies"))
    classes = scratch.write_table(classes, "classes", owner)

    often = survey.where("kind = 1").groupBy("doc_id").agg(F.sum("n").alias("n")).where(F.col("n") >= OFTEN)
    often = often.orderBy(F.desc("n"), "doc_id").limit(MOST_OFTEN).select("doc_id").toPandas()["doc_id"]
    often = spark.sparkContext.broadcast(np.sort(often.to_numpy(np.int64).view(np.uint64)))

    # Groups: stars around the least class that shares one of the least shingles.
    keys = classes.select("rep", "n", F.explode("least").alias("key"))
    hubs = keys.groupBy("key").agg(F.min(F.struct("rep", "n")).alias("hub"), F.count("*").alias("met")).where("met > 1")
    stars = keys.join(hubs, "key").where(f"rep <> hub.rep and 100 * least(n, hub.n) >= {percent} * greatest(n, hub.n)")
    stars = stars.select(F.col("rep").alias("q"), F.col("hub.rep").alias("grp"), F.lit(0).cast("long").alias("chunk")).distinct()
    stars = scratch.write_table(stars, "stars", owner)
    alone = stars.select("grp", "chunk", F.col("grp").alias("doc_id")).distinct()
    stars = scratch.write_table(_possible(stars, alone, classes, percent), "possible-stars", owner)
    links = _verify(stars, alone, docs, width, percent, owner)
    groups = components(links, owner=owner)

    # The matrix over the groups' chunks; a class without a group is a chunk of its own.
    sizes = groups.groupBy("component").agg((F.ceil((F.count("*") + 1) / CHUNK)).alias("chunks"))
    cut = lambda node: F.pmod(F.xxhash64(node), F.col("chunks")).cast("long")
    placed = groups.join(sizes, "component").select(F.col("node").alias("doc_id"), F.col("component").alias("grp"), cut("node").alias("chunk"))
    heads = sizes.select(F.col("component").alias("doc_id"), F.col("component").alias("grp"), cut("component").alias("chunk"))
    placed = scratch.write_table(placed.union(heads), "placed", owner)
    reps = classes.select(F.col("rep").alias("doc_id")).distinct()
    whole = scratch.write_table(
        reps.join(scratch.small_side(placed), "doc_id", "left").select("doc_id", F.coalesce("grp", "doc_id").alias("grp"), F.coalesce("chunk", F.lit(0).cast("long")).alias("chunk")), "whole", owner
    )
    rest = scratch.small_side(rows.where("n > 0 and doc_id is not null").select("doc_id").distinct().join(reps, "doc_id", "left_anti"))
    texts = docs.where("doc_id is not null").join(rest, "doc_id", "left_anti").join(scratch.small_side(placed), "doc_id", "left")
    texts = texts.select("doc_id", "text", F.coalesce("grp", "doc_id").alias("grp"), F.coalesce("chunk", F.lit(0).cast("long")).alias("chunk"))
    postings = texts.mapInArrow(_postings(width, percent, often), "shingle long, doc_id long, n int, pos int, grp long, chunk long")
    dealt = postings.repartition("shingle").sortWithinPartitions("shingle")
    met = dealt.mapInArrow(_candidates(percent), "q long, grp long, chunk long, n long")
    need = F.least(F.lit(SHARED), F.ceil(F.max("n") * percent / F.lit(100)))
    candidates = met.groupBy("q", "grp", "chunk").agg(F.count("*").alias("met"), need.alias("need")).where("met >= need").select("q", "grp", "chunk")
    with scratch.small_batches(spark, 10_000):
        candidates = scratch.write_table(candidates, "candidates", owner)
    candidates = scratch.write_table(_possible(candidates, whole, classes, percent), "possible", owner)
    more = _verify(candidates, whole, docs, width, percent, owner)

    # Components of all links, and from classes back to documents.
    joined = groups.select(F.col("node").alias("a"), F.col("component").alias("b")).union(more)
    twice = rows.where("n > 0 and doc_id is not null").join(classes.where("copies > 1"), ["h1", "h2", "n"]).where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    named = components(joined.union(twice), owner=owner)
    if links_as is None:
        return rows, named, None
    return rows, named, _all_links(candidates, whole, placed, classes, docs, width, percent, owner, links_as == "counts")


def first_of_each(docs: DataFrame, width: int = 5, percent: int = 75, owner: str = "query") -> DataFrame:
    """``docs`` with one document of each component: its least doc_id. Rows without doc_id all stay."""
    found = ngram_components(docs, width, percent, owner)
    gone = found.where("doc_id <> component_id").select("doc_id").distinct()
    kept = docs.join(scratch.small_side(gone), "doc_id", "left_anti")
    return kept.select(*docs.columns)
