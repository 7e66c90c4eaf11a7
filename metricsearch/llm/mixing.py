"""Mixing sources to target weights by systematic sampling.

A document's expected number of copies is its source's target over its source's size. Within a source, documents
stand in order of size; one prefix sum of the expected copies plus one random offset runs along them, and a document
is emitted once for each whole number the sum crosses at it. In this order a source's words miss the target by about
the size of its largest document at most, and copies exceed the expected number by less than one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import scratch

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5.0, 2.0, 1.0)
CAP = 3.0


def word_total(text: str = "text") -> Column:
    """Number of words of a text column; null and empty count 0.

    Runs of white space are counted by plain replacements, which work on the bytes as they are: each space becomes an
    opening and a closing mark, a closing mark next to an opening one goes with it, and what is left is one pair for
    each run. A text with a space before and after it has one run more than words, or one run and no word.
    """
    same = F.concat(F.lit(" "), F.col(text), F.lit(" "))
    for space in "\t\n\x0b\x0c\r":
        same = F.replace(same, F.lit(space), F.lit(" "))
    for mark in "\x01\x02":  # only their number matters
        same = F.replace(same, F.lit(mark), F.lit("a"))
    pairs = F.replace(F.replace(same, F.lit(" "), F.lit("\x01\x02")), F.lit("\x02\x01"), F.lit(""))
    runs = F.floor((F.octet_length(pairs) - F.octet_length(F.replace(pairs, F.lit("\x01\x02"), F.lit("")))) / 2)
    return F.coalesce(runs - 1, F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: float = CAP) -> DataFrame:
    """(source, source_size, weight, target) from (source, size).

    Sources in code-point order, null last, take ``weights`` in turn. Targets share the whole size by weight, stop at
    ``cap`` times the source's own size, and the excess is shared anew by weight: so all sources below their cap get
    one amount for each unit of weight, found by a running sum over sources ordered by cap per weight. One row for
    each source is sorted here, never a document.
    """
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (place % len(weights) + 1).cast("int"))
    rows = by_source.withColumn("weight", weight).withColumn("_ratio", F.lit(cap) * F.col("source_size") / F.col("weight"))
    capped = Window.orderBy("_ratio", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    everyone = Window.partitionBy()
    left = F.sum("source_size").over(everyone) - F.coalesce(F.lit(cap) * F.sum("source_size").over(capped), F.lit(0.0))
    rows = rows.withColumn("_rate", left / (F.sum("weight").over(everyone) - F.coalesce(F.sum("weight").over(capped), F.lit(0.0))))
    # the first source whose cap is not below the rate ends the capped ones
    rate = F.min(F.when(F.col("_rate") <= F.col("_ratio"), F.struct("_ratio", "_rate"))).over(everyone)["_rate"]
    return rows.select("source", "source_size", "weight", F.coalesce(F.least(F.lit(cap) * F.col("source_size"), F.col("weight") * rate), F.lit(0.0)).alias("target"))


def random_offset(source: str = "source", seed: int = 7) -> Column:
    """A number in (0, 1) for each source, the same in every run."""
    digest = F.md5(F.concat(F.coalesce(F.col(source), F.lit("\x00null")), F.lit(f"|{seed}")))
    return (F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: float = CAP, seed: int = 7, owner: str = "query", size: str | None = None) -> DataFrame:
    """Every row of ``docs`` with size, source_size, target and ``copies``, the times the mix takes it (0 included).

    ``docs`` needs doc_id, source and text, or instead of a text the column that ``size`` names, which holds numbers of
    words; other columns pass through under any name, but for those four, which are made anew. Null sources form one
    source; rows without words have size 0. Rows with equal (size, doc_id) stand next to each other in an order by a
    hash of all they hold, so reruns agree. Rows are dealt by ranges of (source, size, doc_id): a hot source spans many
    tasks. Ranks within a source add the counts of the tasks before. An empty table gives no rows.
    """
    made = ("size", "source_size", "target", "copies")
    whole = {c: F.col(f"`{c}`") for c in docs.columns}
    tie = F.xxhash64(*[whole[c] for c, kind in docs.dtypes if c not in made and "map<" not in kind and kind != "variant"])
    count = word_total() if size is None else F.coalesce(whole[size].cast("long"), F.lit(0))
    rows = docs.select(F.struct(*[v.alias(c) for c, v in whole.items() if c not in made]).alias("row"), count.alias("size"), tie.alias("tie"))
    keys = [F.col("row.source").asc_nulls_last(), F.col("size"), F.col("row.doc_id"), F.col("tie")]
    rows = scratch.deal_by_range(rows, *keys).sortWithinPartitions(*keys)
    rows = scratch.write_table(rows.withColumn("no", F.monotonically_increasing_id()).drop("tie"), "mix-rows", owner)
    part, source = F.shiftright("no", 33).cast("int"), F.col("row.source")
    runs = rows.groupBy(source.alias("source"), part.alias("part")).agg(F.count("*").alias("n"), F.sum("size").alias("size"), F.min("no").alias("first"))
    earlier = Window.partitionBy("source").orderBy("part")
    runs = runs.select("source", "part", "first", (F.sum("n").over(earlier) - F.col("n")).alias("before"), "size")
    goals = source_targets(runs.select("source", "size"), weights, cap).select(F.col("source").alias("of"), "source_size", "target")
    runs = runs.drop("size").join(goals, F.col("source").eqNullSafe(F.col("of"))).drop("source")
    runs = scratch.small_side(scratch.write_table(runs, "mix-runs", owner))
    ranked = rows.join(runs, (part == F.col("part")) & source.eqNullSafe(F.col("of")))
    rank = (F.col("no") - F.col("first") + F.col("before")).cast("double")
    each = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    upto = lambda n: F.floor(random_offset("of", seed) + n * each)
    return ranked.select("row.*", "size", "source_size", "target", (upto(rank + 1) - upto(rank)).cast("long").alias("copies"))


def take(mixed: DataFrame) -> DataFrame:
    """The mix itself: each row as often as ``copies`` says; rows with null or no copies go."""
    again = F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("nth")
    return mixed.where("copies > 0").select(F.struct(*[F.col(f"`{c}`") for c in mixed.columns]).alias("row"), again).select("row.*")
